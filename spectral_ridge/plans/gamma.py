"""Penalty selection on held-out rows."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..operators.design import RidgeSpec
from ..operators.fit import fit_sketch
from ..operators.predict import prediction_error
from ..operators.solve import solve
from ..runtime import materialise

POWERS_OF_TWO = tuple(float(2**k) for k in range(21))


def gamma_losses(train: DataFrame, test: DataFrame, spec: RidgeSpec, grid: Sequence[float] = POWERS_OF_TWO, method: str = "exact_ridge", ell: int = 1, **options) -> DataFrame:
    """(gamma, residual_norm) of every penalty: one pass over ``train``, one over ``test``, however
    long the grid is."""
    sketch = materialise(fit_sketch(train, spec, method, ell, **options), "gamma-sketch")
    return prediction_error(test, solve(sketch, list(grid)), spec).select("gamma", "residual_norm")


def select_gamma(train: DataFrame, test: DataFrame, spec: RidgeSpec, grid: Sequence[float] = POWERS_OF_TWO, method: str = "exact_ridge", ell: int = 1, **options) -> DataFrame:
    """(gamma, residual_norm): the penalty of least held-out residual. ``method`` other than the
    exact one selects from a sketch and a stored test set."""
    losses = gamma_losses(train, test, spec, grid, method, ell, **options)
    return losses.agg(F.min_by("gamma", F.struct("residual_norm", "gamma")).alias("gamma"), F.min("residual_norm").alias("residual_norm"))
