"""Coefficients from a sketch row, for any number of penalties."""

from __future__ import annotations

from collections.abc import Iterator, Sequence

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..runtime import ship_package
from ..sketch import SketchRow
from ..sketch.linear import full_gram
from ..sketch.two_level import residual_rows

RCOND = 1e-10


def solve_spectral(sigma: np.ndarray, basis: np.ndarray, cross: np.ndarray, gamma: float) -> np.ndarray:
    """(basis' diag(sigma^2) basis + gamma I)^-1 cross in O(d l): the span and its complement apart.

    With a penalty of 0 only the span's part is defined; the remainder is left out.
    """
    inside = basis @ cross
    square = sigma**2 if cross.ndim == 1 else (sigma**2)[:, None]
    out = basis.T @ (inside / (square + gamma))
    return out + (cross - basis.T @ inside) / gamma if gamma > 0 else out


def solve_rows(rows: np.ndarray, cross: np.ndarray, gamma: float) -> np.ndarray:
    """(rows' rows + gamma I)^-1 cross through the small matrix of the rows."""
    if gamma <= 0:
        return solve_pinv(rows.T @ rows, cross)
    small = rows @ rows.T + gamma * np.eye(len(rows))
    return (cross - rows.T @ np.linalg.solve(small, rows @ cross)) / gamma


def solve_dual(x: np.ndarray, y: np.ndarray, gamma: float) -> np.ndarray:
    """x' (x x' + gamma I)^-1 y: the n x n form, for fewer rows than features."""
    return x.T @ np.linalg.solve(x @ x.T + gamma * np.eye(len(x)), y)


def solve_primal(gram: np.ndarray, cross: np.ndarray, gamma: float) -> np.ndarray:
    """(gram + gamma I)^-1 cross by Cholesky; by pseudo-inverse where that is not positive definite."""
    shifted = gram + gamma * np.eye(len(gram))
    try:
        low = np.linalg.cholesky(shifted)
    except np.linalg.LinAlgError:
        return solve_pinv(shifted, cross)
    return np.linalg.solve(low.T, np.linalg.solve(low, cross))


def solve_pinv(gram: np.ndarray, cross: np.ndarray, rcond: float = RCOND) -> np.ndarray:
    """Least squares: the pseudo-inverse of the Gram matrix times the moments."""
    lam, v = np.linalg.eigh(gram)
    live = lam > rcond * max(float(lam[-1]), 0.0)
    inside = v[:, live].T @ cross
    return v[:, live] @ (inside / (lam[live] if cross.ndim == 1 else lam[live][:, None]))


def solve_components(gram: np.ndarray, cross: np.ndarray, k: int) -> np.ndarray:
    """Principal component regression on the top ``k`` directions of a Gram matrix."""
    lam, v = np.linalg.eigh(gram)
    lam, v = lam[::-1][:k], v[:, ::-1][:, :k]
    live = lam > RCOND * max(float(lam[0]), 0.0)
    inside = v[:, live].T @ cross
    return v[:, live] @ (inside / (lam[live] if cross.ndim == 1 else lam[live][:, None]))


def gram_of(row: SketchRow, robust: bool | None = None) -> np.ndarray:
    """What the sketch holds for the Gram matrix, d x d: for diagnostics and small d."""
    if row.method == "exact_ridge":
        return full_gram(row)
    if row.method in ("sign_projection_ridge", "count_sketch_ridge", "srht_ridge"):
        c = row.payload.reshape(-1, row.n_features)
        return c.T @ c
    b = row.sigma[:, None] * row.basis
    out = b.T @ b
    if row.method == "two_level_ridge":
        q = residual_rows(row)
        out += q.T @ q
    if robust if robust is not None else row.method == "robust_fd_ridge":
        out += row.shrink_total / 2 * np.eye(row.n_features)
    return out


def effective_penalty(row: SketchRow, gamma: float, robust: bool | None = None) -> float:
    """The penalty with the robust method's half of the removed amount."""
    return gamma + row.shrink_total / 2 if (robust if robust is not None else row.method == "robust_fd_ridge") else gamma


def certificate(row: SketchRow, gamma: float, robust: bool | None = None) -> float | None:
    """Bound on the relative coefficient error that follows from what was removed, or None where
    the method has none. No second pass over the data is needed."""
    if row.method == "exact_ridge":
        return 0.0
    if row.method not in ("fd_ridge", "robust_fd_ridge", "truncated_svd_ridge") or gamma <= 0:
        return None
    if robust if robust is not None else row.method == "robust_fd_ridge":
        return (row.shrink_total / 2 + row.dropped_total) / (gamma + row.shrink_total / 2)
    return (row.shrink_total + row.dropped_total) / gamma


def coefficients(row: SketchRow, gamma: float, robust: bool | None = None, query: str = "auto", use_exact_cross: bool = False) -> np.ndarray:
    """Coefficients (d x targets). ``query``: "primal" or "dual" system for the projections;
    ``use_exact_cross`` solves a projection with the exact moments, as the spectral methods do."""
    if gamma < 0:
        raise ValueError("the penalty must not be negative")
    c = row.cross
    if row.method == "exact_ridge":
        gram = full_gram(row)
        return solve_primal(gram, c, gamma) if gamma > 0 else solve_pinv(gram, c)
    if row.method in ("sign_projection_ridge", "count_sketch_ridge", "srht_ridge"):
        rows = row.payload.reshape(-1, row.n_features)
        v = row.proj_target.reshape(-1, row.n_targets)
        if use_exact_cross:
            return solve_rows(rows, c, gamma)
        if query == "primal" or (query == "auto" and len(rows) > row.n_features) or gamma == 0:
            return solve_primal(rows.T @ rows, rows.T @ v, gamma) if gamma > 0 else solve_pinv(rows.T @ rows, rows.T @ v)
        return solve_dual(rows, v, gamma)
    if row.method == "two_level_ridge":
        return solve_rows(np.concatenate([row.sigma[:, None] * row.basis, residual_rows(row)]), c, gamma)
    return solve_spectral(row.sigma, row.basis, c, effective_penalty(row, gamma, robust))


SOLUTION = [
    T.StructField("gamma", T.DoubleType()), T.StructField("gamma_effective", T.DoubleType()), T.StructField("coefficients", T.ArrayType(T.DoubleType())), T.StructField("certificate", T.DoubleType()), T.StructField("remainder_dropped", T.BooleanType()), T.StructField("n_rows", T.LongType()), T.StructField("rank", T.IntegerType()),
]


def solve(sketches: DataFrame, gamma: float | Sequence[float], *, robust: bool | None = None, by: Sequence[str] = (), **options) -> DataFrame:
    """(groups..., gamma, gamma_effective, coefficients, certificate, remainder_dropped, n_rows,
    rank) for each sketch and penalty.

    The penalty is a query-time value: one fit serves any list of them, and with ``robust=True``
    a plain sketch answers for the robust method too. Coefficients of several targets are laid out
    target after target. Work stays on the executors.
    """
    ship_package(sketches.sparkSession)
    gammas = [float(g) for g in (gamma if isinstance(gamma, Sequence) else [gamma])]
    if any(g < 0 for g in gammas):
        raise ValueError("the penalty must not be negative")
    by = list(by)
    schema = T.StructType([*[sketches.schema[g] for g in by], *SOLUTION])
    lifted = sketches.withColumn("gamma", F.explode(F.array(*[F.lit(g) for g in gammas])))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for at in range(batch.num_rows):
                (r,) = batch.slice(at, 1).to_pylist()
                row, g = SketchRow.from_dict(r), r["gamma"]
                x = coefficients(row, g, robust, **options)
                wide = effective_penalty(row, g, robust)
                out = {**{k: r[k] for k in by}, "gamma": g, "gamma_effective": wide, "coefficients": x.T.reshape(-1).tolist(), "certificate": certificate(row, g, robust), "remainder_dropped": bool(wide == 0 and row.rank < row.n_features), "n_rows": row.n_rows, "rank": row.rank}
                yield pa.RecordBatch.from_pylist([out], schema=pa.schema([*[batch.schema.field(k) for k in by], ("gamma", pa.float64()), ("gamma_effective", pa.float64()), ("coefficients", pa.list_(pa.float64())), ("certificate", pa.float64()), ("remainder_dropped", pa.bool_()), ("n_rows", pa.int64()), ("rank", pa.int32())]))

    return lifted.mapInArrow(run, schema)


def solve_pcr(sketches: DataFrame, k: int) -> DataFrame:
    """Principal component regression from a sketch: (k, coefficients), no penalty."""
    ship_package(sketches.sparkSession)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for r in batch.to_pylist():
                row = SketchRow.from_dict(r)
                x = solve_components(gram_of(row), row.cross, k)
                yield pa.RecordBatch.from_pydict({"k": pa.array([k], pa.int32()), "coefficients": pa.array([x.T.reshape(-1).tolist()], pa.list_(pa.float64()))})

    return sketches.mapInArrow(run, "k int, coefficients array<double>")


def long_coefficients(solutions: DataFrame, by: Sequence[str] = ()) -> DataFrame:
    """(groups..., gamma, idx, coef): one row per coefficient."""
    return solutions.select(*by, "gamma", F.posexplode("coefficients").alias("idx", "coef"))
