"""Cost and accuracy measures."""

from __future__ import annotations

import math

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..operators.design import RidgeSpec, feature_column
from ..operators.fit import collect_sketch, fit_sketch
from ..operators.predict import dot, prediction_error
from ..operators.solve import gram_of
from ..sketch import SketchRow
from ..sketch.linear import full_gram
from .bounds import prediction_gap_bound


def coef_error(approx: np.ndarray, exact: np.ndarray) -> float:
    """Relative distance of coefficients from the exact ones."""
    return float(np.linalg.norm(approx - exact) / np.linalg.norm(exact))


def cov_error(gram: np.ndarray, row: SketchRow, robust: bool | None = None) -> float:
    """Spectral distance of what the sketch holds from the Gram matrix."""
    return float(np.linalg.norm(gram - gram_of(row, robust), 2))


def pred_mse(df: DataFrame, models: DataFrame, spec: RidgeSpec) -> DataFrame:
    """(gamma, pred_mse): mean squared residual."""
    return prediction_error(df, models, spec).select("gamma", "pred_mse")


def holdout_norm(df: DataFrame, models: DataFrame, spec: RidgeSpec) -> DataFrame:
    """(gamma, residual_norm) on held-out rows."""
    return prediction_error(df, models, spec).select("gamma", "residual_norm")


def objective(df: DataFrame, models: DataFrame, spec: RidgeSpec, scale_by_rows: bool = False) -> DataFrame:
    """(gamma, objective): squared residual plus penalty times squared norm; with
    ``scale_by_rows`` the penalty counts once per row."""
    norms = models.select("gamma", F.aggregate("coefficients", F.lit(0.0), lambda s, x: s + x * x).alias("x_sq"))
    joined = prediction_error(df, models, spec).join(F.broadcast(norms), "gamma")
    weight = F.col("gamma") * (F.col("n") if scale_by_rows else F.lit(1))
    return joined.select("gamma", (F.col("residual_sq") + weight * F.col("x_sq")).alias("objective"))


def prediction_gap(df: DataFrame, approx: DataFrame, exact: DataFrame, spec: RidgeSpec) -> DataFrame:
    """Rows with ``gap``: how far the approximate prediction is from the exact one, for two models
    of one penalty each."""
    both = approx.select(F.col("coefficients").alias("gap_a")).crossJoin(exact.select(F.col("coefficients").alias("gap_b")))
    change = F.zip_with("gap_a", "gap_b", lambda a, b: a - b)
    return df.crossJoin(F.broadcast(both)).withColumn("gap", F.abs(dot(feature_column(df, spec), change))).drop("gap_a", "gap_b")


def prediction_gap_block(df: DataFrame, approx: DataFrame, exact: DataFrame, spec: RidgeSpec) -> DataFrame:
    """(n, gap_norm, gap_max, bound): the gap over a whole block of points. ``bound`` follows from the
    certificate of ``approx``, the size of the exact coefficients and the block's spectral norm; the
    models are one row each, the norm comes from the block's Gram matrix."""
    certified, size = approx.first()["certificate"], float(np.linalg.norm(exact.first()["coefficients"]))
    top = float(np.sqrt(max(0.0, np.linalg.eigvalsh(gram_matrix(df, spec))[-1])))
    gaps = prediction_gap(df, approx, exact, spec)
    summed = gaps.agg(F.count("*").alias("n"), F.sqrt(F.sum(F.col("gap") * F.col("gap"))).alias("gap_norm"), F.max("gap").alias("gap_max"))
    return summed.withColumn("bound", F.lit(None if certified is None else prediction_gap_bound(certified, size, top)))


def gram_matrix(df: DataFrame, spec: RidgeSpec) -> np.ndarray:
    """The exact Gram matrix, d x d, on the driver."""
    return full_gram(collect_sketch(fit_sketch(df, spec, "exact_ridge", 1)))


def spectrum(df: DataFrame, spec: RidgeSpec) -> DataFrame:
    """(idx, sigma, sigma_norm, idx_norm): singular values of the feature matrix, by the Gram
    matrix, normalised by the first one and by d."""
    s = np.sqrt(np.maximum(np.linalg.eigvalsh(gram_matrix(df, spec))[::-1], 0.0))
    top, d = max(float(s[0]), 1e-300), len(s)
    return df.sparkSession.createDataFrame([(i, float(v), float(v / top), i / d) for i, v in enumerate(s)], "idx int, sigma double, sigma_norm double, idx_norm double")


def sketch_norm(row: SketchRow, x: np.ndarray) -> float:
    """Approximate squared norm |Ax|^2 from the sketch."""
    return float(x @ gram_of(row) @ x)


def low_rank(row: SketchRow, k: int) -> np.ndarray:
    """The sketch's top ``k`` directions (k x d)."""
    if len(row.basis):
        return row.basis[:k]
    return np.linalg.eigh(gram_of(row))[1][:, ::-1][:, :k].T


def space_report(row: SketchRow) -> dict[str, int]:
    """Rows, floats and bytes that the sketch holds."""
    floats = len(row.sigma) + row.basis.size + row.payload.size + row.cross.size + row.proj_target.size
    return {"rows": row.ell, "floats": int(floats), "bytes": int(8 * floats)}


def log_slope(x: list[float], y: list[float]) -> float:
    """Slope of the log-log line: the power with which y follows x."""
    lx, ly = np.log(x), np.log(y)
    return float(np.polyfit(lx, ly, 1)[0])


def amortised_seconds(train: float, query: float, n: int, ell: int) -> float:
    """Training plus a query at every batch of ``ell`` rows."""
    return train + query * math.ceil(n / ell)
