"""Predictions and their errors, as Catalyst expressions over broadcast coefficients."""

from __future__ import annotations

from collections.abc import Iterator, Sequence

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..runtime import ship_package
from .design import RidgeSpec, feature_column, feature_count, flat_matrix, number


def dot(a: Column | str, b: Column | str) -> Column:
    """Inner product of two array columns, without a Python worker: for a few hundred elements at
    most, since higher-order functions go element by element."""
    a, b = (F.col(x) if isinstance(x, str) else x for x in (a, b))
    return F.aggregate(F.zip_with(a, b, lambda x, y: x * y), F.lit(0.0), lambda s, x: s + x)


def norm2(a: Column | str) -> Column:
    return F.sqrt(dot(a, a))


def predict(df: DataFrame, models: DataFrame, spec: RidgeSpec, output: str = "prediction", by: Sequence[str] = ()) -> DataFrame:
    """Rows of ``df`` with a prediction for each model (first target): joined on the groups ``by``,
    or to every model of the table.

    ``models`` holds one row per penalty and group. A single-group model table is a handful of
    rows and broadcast; grouped ones are left to the optimiser's size check.
    """
    slim = models.select(*[F.col(g).alias(f"model_{g}") for g in by], F.col("gamma").alias("model_gamma"), F.col("coefficients").alias("model_coefficients"))
    rows = df.withColumn("model_features", feature_column(df, spec))
    if by:
        rows = rows.join(slim, [F.col(g).eqNullSafe(F.col(f"model_{g}")) for g in by])
    else:
        rows = rows.crossJoin(F.broadcast(slim))
    return rows.withColumn(output, dot("model_features", "model_coefficients")).withColumn("gamma", F.col("model_gamma")).drop("model_features", "model_coefficients", "model_gamma", *[f"model_{g}" for g in by])


#: Features from which the errors of all models are taken as one matrix product per batch.
WIDE = 256


def _errors_by_product(df: DataFrame, models: DataFrame, spec: RidgeSpec, width: int) -> DataFrame:
    """(gamma, n, residual_sq) of every model: a batch is multiplied by all of them at once, and only
    its sums leave the worker. The models, one row per penalty, go to the workers as a matrix."""
    ship_package(df.sparkSession)
    held = models.select("gamma", "coefficients").collect()
    gammas = np.array([r[0] for r in held])
    matrix = np.array([r[1][:width] for r in held], dtype=np.float64).reshape(len(held), width).T
    rows = df.select(feature_column(df, spec).alias("features"), number(df, spec.targets[0]).alias("target"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        n, total = 0, np.zeros(len(gammas))
        for batch in batches:
            if batch.num_rows:
                x, _ = flat_matrix(batch.column(0), width)
                gap = x @ matrix - batch.column(1).to_numpy(zero_copy_only=False)[:, None]
                n, total = n + batch.num_rows, total + (gap * gap).sum(axis=0)
        if n:
            yield pa.RecordBatch.from_pydict({"gamma": gammas, "n": np.full(len(gammas), n), "residual_sq": total})

    sums = rows.mapInArrow(run, "gamma double, n long, residual_sq double")
    return sums.groupBy("gamma").agg(F.sum("n").alias("n"), F.sum("residual_sq").alias("residual_sq"))


def prediction_error(df: DataFrame, models: DataFrame, spec: RidgeSpec, by: Sequence[str] = ()) -> DataFrame:
    """(groups..., gamma, n, residual_sq, pred_mse, residual_norm) of each model, all in one scan."""
    width = None if by else feature_count(df, spec)
    if width is not None and width > WIDE:
        out = _errors_by_product(df, models, spec, width)
    else:
        target = number(df, spec.targets[0])
        scored = predict(df.withColumn("model_target", target), models, spec, "model_prediction", by)
        gap = F.col("model_prediction") - F.col("model_target")
        out = scored.groupBy(*by, "gamma").agg(F.count("*").alias("n"), F.sum(gap * gap).alias("residual_sq"))
    return out.withColumns({"pred_mse": F.col("residual_sq") / F.col("n"), "residual_norm": F.sqrt("residual_sq")})
