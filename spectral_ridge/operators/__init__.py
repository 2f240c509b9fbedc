"""Operators on DataFrames: design rows, fitting, solving, prediction, relational twins."""
