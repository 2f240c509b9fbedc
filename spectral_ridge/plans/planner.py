"""What to run: exact or sketch, how many rows, how to merge, which solver."""

from __future__ import annotations

import math
from dataclasses import dataclass

import numpy as np
from pyspark.sql import DataFrame

from ..operators.design import RidgeSpec, feature_count
from ..operators.fit import expected_partitions
from .bounds import required_rows


@dataclass(frozen=True)
class FitPlan:
    method: str
    ell: int
    n_features: int
    partitions: int
    fan_in: int
    rounds: int
    sketch_bytes: int
    reason: str


def choose_method(n_features: int, ell: int, method: str = "robust_fd_ridge") -> tuple[str, str]:
    """The exact Gram matrix where it is no larger than the sketch."""
    if n_features * (n_features + 1) // 2 <= 2 * ell * n_features:
        return "exact_ridge", f"the Gram matrix of {n_features} features is no larger than a sketch of {ell} rows"
    return method, f"{ell} rows of {n_features} features are smaller than the Gram matrix"


def choose_solver(rows: int, n_features: int) -> str:
    """The small system: of the rows where these are fewer than the features."""
    return "dual" if rows < n_features else "primal"


def choose_fan_in(ell: int, n_features: int, task_bytes: int = 256 << 20) -> int:
    """Sketches that one merge task may hold."""
    return int(min(64, max(2, task_bytes // max(1, 8 * ell * n_features))))


def rows_for_target(tail: np.ndarray, gamma: float, eps: float, robust: bool = True) -> int:
    """Sketch rows for an error target; tails of a pilot sketch are upper bounds and so are safe."""
    return required_rows(tail, gamma, eps, robust)[0]


def plan_fit(df: DataFrame, spec: RidgeSpec, ell: int, method: str = "robust_fd_ridge") -> FitPlan:
    d = feature_count(df, spec) or 0
    chosen, reason = choose_method(d, ell, method)
    parts, fan_in = expected_partitions(df), choose_fan_in(ell, max(d, 1))
    size = 8 * (d * (d + 1) // 2 if chosen == "exact_ridge" else ell * d) + 8 * d
    return FitPlan(chosen, ell, d, parts, fan_in, max(1, math.ceil(math.log(max(parts, 2), fan_in))), size, reason)


def explain_fit(df: DataFrame, spec: RidgeSpec, ell: int, method: str = "robust_fd_ridge") -> str:
    p = plan_fit(df, spec, ell, method)
    return f"{p.method}: {p.reason}; {p.partitions} partial sketches of {p.sketch_bytes} bytes, {p.rounds} merge rounds of {p.fan_in}"
