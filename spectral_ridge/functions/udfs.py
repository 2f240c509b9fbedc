"""UDFs, aggregates and table functions over sketches, and their registration."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.pandas.functions import PandasUDFType

from ..operators.fit import _COLUMNS, SKETCH_TYPE
from ..operators.solve import coefficients
from ..runtime import ship_package
from ..sketch import SketchRow, make_sketcher

SKETCH_DDL = ", ".join(f"{f.name} {f.dataType.simpleString()}" for f in SKETCH_TYPE.fields)


def to_struct(row: SketchRow) -> dict:
    return {n: row.to_dict()[n] for n, _ in _COLUMNS}


def solve_udf():
    """solve_ridge(sketch struct, gamma) -> array<double>."""

    @F.pandas_udf(T.ArrayType(T.DoubleType()))
    def solve_ridge(sketch: pd.DataFrame, gamma: pd.Series) -> pd.Series:
        rows = sketch.to_dict("records")
        return pd.Series([coefficients(SketchRow.from_dict(r), float(g))[:, 0].tolist() for r, g in zip(rows, gamma, strict=True)])

    return solve_ridge


def norm_udf():
    """vector_norm(array<double>) -> double, in Arrow batches: for very wide vectors."""

    @F.pandas_udf("double")
    def vector_norm(v: pd.Series) -> pd.Series:
        held = v[v.notna()]
        lengths = held.map(len).to_numpy(dtype=np.int64)
        square = np.concatenate([[0.0], np.cumsum(np.concatenate([*held, np.zeros(0)]) ** 2)])
        ends = np.cumsum(lengths)
        return pd.Series(np.sqrt(np.maximum(square[ends] - square[ends - lengths], 0.0)), held.index).reindex(v.index)

    return vector_norm


def gram_udaf(ell: int = 8, method: str = "fd_ridge"):
    """sketch_gram(p, q, t) -> array<double>: upper triangle of the sketch's Gram matrix and the
    moments, as a grouped aggregate. It has no map-side part, so it is for small groups; large data
    goes through ``fit_sketch``."""

    def sketch_gram(p: pd.Series, q: pd.Series, t: pd.Series) -> list[float]:
        sketcher = make_sketcher(method, ell, 2)
        sketcher.update(np.column_stack([p, q]), t.to_numpy())
        row = sketcher.finish()
        b = row.sigma[:, None] * row.basis
        g = b.T @ b
        return [float(x) for x in (g[0, 0], g[0, 1], g[1, 1], *row.cross[:, 0])]

    return F.pandas_udf(sketch_gram, T.ArrayType(T.DoubleType()), PandasUDFType.GROUPED_AGG)


@F.udtf(returnType="row int, sigma double, idx int, value double")
class SketchRows:
    """sketch_rows(sigma, basis, n_features): the rows of B in long form."""

    def eval(self, sigma: list, basis: bytes, n_features: int):
        for r, (s, v) in enumerate(zip(sigma, np.frombuffer(basis, np.float64).reshape(-1, n_features), strict=True)):
            for i, x in enumerate(v):
                yield r, float(s), i, float(s * x)


@F.udtf(returnType="gamma double")
class GammaGrid:
    """gamma_grid(lo, hi, steps): a geometric grid of penalties."""

    def eval(self, lo: float, hi: float, steps: int):
        for g in np.geomspace(float(lo), float(hi), int(steps)):
            yield (float(g),)


@F.udtf(returnType=SKETCH_DDL)
class RidgeFit:
    """ridge_fit(TABLE(design) PARTITION BY (...), method, ell): partial sketch rows of a design with
    columns features and target; merge them with ``merge_sketches``."""

    def __init__(self):
        self.sketcher, self.rows = None, []

    def eval(self, row, method: str, ell: int):
        if self.sketcher is None:
            self.sketcher = make_sketcher(method, int(ell), len(row["features"]))
        self.rows.append((row["features"], row["target"]))
        if len(self.rows) >= 1024:
            self.flush()

    def flush(self):
        if self.rows:
            self.sketcher.update(np.array([r[0] for r in self.rows], dtype=np.float64), np.array([r[1] for r in self.rows], dtype=np.float64))
            self.rows = []

    def terminate(self):
        if self.sketcher is not None:
            self.flush()
            yield tuple(to_struct(self.sketcher.finish()).values())


def register(spark: SparkSession) -> None:
    """Register solve_ridge, vector_norm, sketch_rows, gamma_grid, ridge_fit, and the SQL functions
    dot and axpy (built-in expressions, no Python)."""
    ship_package(spark)
    spark.udf.register("solve_ridge", solve_udf())
    spark.udf.register("vector_norm", norm_udf())
    spark.udtf.register("sketch_rows", SketchRows)
    spark.udtf.register("gamma_grid", GammaGrid)
    spark.udtf.register("ridge_fit", RidgeFit)
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION dot(a ARRAY<DOUBLE>, b ARRAY<DOUBLE>) RETURNS DOUBLE RETURN aggregate(zip_with(a, b, (x, y) -> x * y), 0D, (s, x) -> s + x)")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION axpy(c DOUBLE, a ARRAY<DOUBLE>, b ARRAY<DOUBLE>) RETURNS ARRAY<DOUBLE> RETURN zip_with(a, b, (x, y) -> c * x + y)")

