"""Choices and guarantees: planner, bounds, risk, penalty selection, measures."""
