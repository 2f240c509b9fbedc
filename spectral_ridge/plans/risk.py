"""Bias, variance and risk of exact and sketched solutions under a fixed design."""

from __future__ import annotations

from collections.abc import Iterable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F


@dataclass
class Risk:
    bias_sq: float
    variance: float
    rank_deficient: bool

    @property
    def risk(self) -> float:
        return self.bias_sq + self.variance


def risk(gram: np.ndarray, approx: np.ndarray, x_true: np.ndarray, noise_sd: float, gamma: float) -> Risk:
    """Closed form from d x d matrices only: ``approx`` is the Gram matrix itself for the exact
    solution, else what the sketch holds."""
    d = len(gram)
    h = np.linalg.inv(approx + gamma * np.eye(d))
    gap = (h @ gram - np.eye(d)) @ x_true
    hk = h @ gram
    lam = np.linalg.eigvalsh(gram)
    return Risk(float(gap @ gram @ gap), float(noise_sd**2 * np.trace(hk @ hk)), bool(lam[0] <= 1e-10 * lam[-1]))


def held_out_risk(gram: np.ndarray, test_gram: np.ndarray, x_true: np.ndarray, noise_sd: float, gammas: Iterable[float]) -> np.ndarray:
    """Expected squared prediction gap of the exact solution on other rows, over the noise of the
    training targets, for each penalty. One eigendecomposition serves all of them."""
    lam, v = np.linalg.eigh(gram)
    lam, x, other = np.maximum(lam, 0.0), v.T @ x_true, v.T @ test_gram @ v
    out = []
    for gamma in gammas:
        bias = gamma / (lam + gamma) * x
        variance = noise_sd**2 * float((lam / (lam + gamma) ** 2 * other.diagonal()).sum())
        out.append(float(bias @ other @ bias) + variance)
    return np.array(out)


def risk_factors(gram: np.ndarray, approx: np.ndarray, gamma: float, form: str = "safe") -> tuple[float, float]:
    """(bias factor, variance factor) that bound the sketched solution's risk by the exact one's.

    With t = |A|^2 |K - K'| / gamma^2, "safe" is (1 + t)^2; "printed" is 1 + t^2, which leaves out
    a cross term and can fail: a diagnostic only.
    """
    top = float(np.linalg.eigvalsh(gram)[-1])
    t = top * float(np.linalg.norm(gram - approx, 2)) / gamma**2
    return ((1 + t) ** 2 if form == "safe" else 1 + t**2), (1 + top / gamma) ** 2


def robust_printed_factors(gram: np.ndarray, eps: float, gamma: float) -> tuple[float, float]:
    """The robust method's looser printed bias factor and unsquared variance factor; diagnostics."""
    top = float(np.linalg.eigvalsh(gram)[-1])
    return 1 + 4 * eps**2 * top**2 / gamma**2, 1 + top / gamma


def monte_carlo(a: np.ndarray, solve_cross, x_true: np.ndarray, noise_sd: float, draws: int, seed: int = 0) -> float:
    """Mean squared prediction gap over noise draws; ``solve_cross`` maps moments (d x draws) to
    coefficients. The sketch does not depend on the noise, so all draws share it."""
    rng = np.random.default_rng(seed)
    b = (a @ x_true)[:, None] + noise_sd * rng.standard_normal((len(a), draws))
    gap = a @ (solve_cross(a.T @ b) - x_true[:, None])
    return float((gap**2).sum(axis=0).mean())


def noise_moments(rows: DataFrame, width: int, draws: int, seed: int = 0) -> np.ndarray:
    """Moments (d x draws) of all rows with unit noise, in one pass. A row's noise comes from its
    row_id: retries and other splits draw the same."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros((width, draws))
        for batch in batches:
            if batch.num_rows:
                a = np.array(batch.column(1).to_pylist(), dtype=np.float64)
                noise = np.array([np.random.default_rng([seed, i & 0xFFFFFFFFFFFFFFFF]).standard_normal(draws) for i in batch.column(0).to_pylist()])
                total += a.T @ noise
        yield pa.RecordBatch.from_arrays([pa.array(np.arange(width * draws, dtype=np.int32)), pa.array(total.reshape(-1))], names=["cell", "value"])

    sums = rows.select(F.col("row_id").cast("long"), "features").mapInArrow(run, "cell int, value double").groupBy("cell").agg(F.sum("value")).collect()
    out = np.zeros(width * draws)
    for cell, value in sums:
        out[cell] = value
    return out.reshape(width, draws)


def moments_risk(gram: np.ndarray, noise: np.ndarray, solve_cross, x_true: np.ndarray, noise_sd: float) -> float:
    """As ``monte_carlo``, from the Gram matrix and the noise moments of all rows."""
    gap = solve_cross((gram @ x_true)[:, None] + noise_sd * noise) - x_true[:, None]
    return float((gap * (gram @ gap)).sum(axis=0).mean())
