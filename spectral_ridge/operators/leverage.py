"""Ridge leverage scores, and regression on rows sampled by them: the prior-work contrast."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..runtime import ship_package
from .design import RidgeSpec, feature_column, flat_matrix, number
from .fit import collect_sketch, fit_sketch
from .solve import effective_penalty, gram_of, long_coefficients, solve


def leverage_scores(df: DataFrame, sketch: DataFrame, spec: RidgeSpec, gamma: float) -> DataFrame:
    """Rows with ``leverage`` = a' (K + gamma I)^-1 a; K exact or from any sketch.

    The d x d inverse factor is the only thing sent to the workers; its size is fixed by d.
    """
    ship_package(df.sparkSession)
    row = collect_sketch(sketch)
    half = np.linalg.inv(np.linalg.cholesky(gram_of(row, robust=False) + effective_penalty(row, gamma) * np.eye(row.n_features)))
    rows = df.withColumn("leverage_features", feature_column(df, spec))
    at = rows.columns.index("leverage_features")
    schema = T.StructType([*df.schema.fields, T.StructField("leverage", T.DoubleType())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            if batch.num_rows:
                x, _ = flat_matrix(batch.column(at), row.n_features)
                score = ((x @ half.T) ** 2).sum(axis=1)
                yield pa.RecordBatch.from_arrays([*[c for k, c in enumerate(batch.columns) if k != at], pa.array(score)], names=[*[n for k, n in enumerate(batch.schema.names) if k != at], "leverage"])

    return rows.mapInArrow(run, schema)


def leverage_sample_ridge(df: DataFrame, spec: RidgeSpec, gamma: float, rows: int, deterministic: bool = False, seed: int = 0) -> DataFrame:
    """(gamma, idx, coef) of ridge on about ``rows`` rows: the highest scores, or rows drawn with a
    chance in proportion to their score and weighted by its inverse."""
    scored = leverage_scores(df, fit_sketch(df, spec, "exact_ridge", 1), spec, gamma)
    if deterministic:
        chosen = scored.orderBy(F.desc("leverage"), *spec.ids).limit(rows).withColumn("weight", F.lit(1.0))
    else:
        total = scored.agg(F.sum("leverage")).first()[0] or 1.0
        chance = F.least(F.lit(1.0), F.col("leverage") * F.lit(rows / total))
        coin = F.pmod(F.xxhash64(*spec.ids, F.lit(seed)), F.lit(1 << 52)) / float(1 << 52)
        chosen = scored.withColumn("chance", chance).where(coin < F.col("chance")).withColumn("weight", F.sqrt(1 / F.col("chance")))
    weighted = chosen.select(*spec.ids, F.transform(feature_column(df, spec), lambda x: x * F.col("weight")).alias("features"), (number(df, spec.targets[0]) * F.col("weight")).alias("target"))
    return long_coefficients(solve(fit_sketch(weighted, RidgeSpec("features", "target", spec.row_id), "exact_ridge", 1), gamma))
