"""Streaming ridge regression from small, mergeable spectral sketches, on Spark."""

from .operators.design import RidgeSpec
from .operators.fit import fit_sketch, merge_sketches
from .operators.predict import predict
from .operators.solve import solve

__all__ = ["RidgeSpec", "fit_sketch", "merge_sketches", "predict", "solve"]
