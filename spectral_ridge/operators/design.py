"""Design rows: features, targets, row hash and groups, from any DataFrame."""

from __future__ import annotations

from collections.abc import Sequence
from dataclasses import dataclass

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

POLICIES = ("error", "skip", "zero")


@dataclass(frozen=True)
class RidgeSpec:
    """Which columns make a design row.

    ``features``: an array column's name, or a list of scalar columns. ``target``: one column or
    several (one sketch then serves several right-hand sides). ``row_id``: columns that identify a
    row; without it the hash of all used columns does. ``on_invalid``: what to do with rows that
    hold null, NaN or infinity: "error", "skip" (counted), or "zero". ``fit_intercept`` appends a
    constant feature, which is penalised like the others.
    """

    features: str | Sequence[str]
    target: str | Sequence[str]
    row_id: str | Sequence[str] | None = None
    group_by: Sequence[str] = ()
    on_invalid: str = "error"
    fit_intercept: bool = False
    n_features: int | None = None

    def __post_init__(self):
        if self.on_invalid not in POLICIES:
            raise ValueError(f"on_invalid must be one of {POLICIES}")

    @property
    def targets(self) -> list[str]:
        return [self.target] if isinstance(self.target, str) else list(self.target)

    @property
    def ids(self) -> list[str]:
        return [] if self.row_id is None else [self.row_id] if isinstance(self.row_id, str) else list(self.row_id)


def number(df: DataFrame, name: str) -> Column:
    """A column of any numeric, boolean or time type as double."""
    kind = df.schema[name].dataType
    if isinstance(kind, T.TimestampType | T.TimestampNTZType | T.DateType):
        return F.unix_micros(F.col(name).cast("timestamp")).cast("double") / 1e6
    if isinstance(kind, T.BooleanType):
        return F.col(name).cast("int").cast("double")
    if isinstance(kind, T.NumericType):
        return F.col(name).cast("double")
    raise TypeError(f"column {name} of type {kind.simpleString()} is not a number; encode it first")


def feature_column(df: DataFrame, spec: RidgeSpec) -> Column:
    if isinstance(spec.features, str):
        kind = df.schema[spec.features].dataType
        if isinstance(kind, T.ArrayType):
            out = F.col(spec.features).cast("array<double>")
        elif kind.typeName() == "vectorudt" or "VectorUDT" in type(kind).__name__:
            from pyspark.ml.functions import vector_to_array

            out = vector_to_array(spec.features)
        else:
            out = F.array(number(df, spec.features))
    else:
        out = F.array(*[number(df, c) for c in spec.features])
    return F.concat(out, F.array(F.lit(1.0))) if spec.fit_intercept else out


def design_rows(df: DataFrame, spec: RidgeSpec) -> DataFrame:
    """(groups..., features array<double>, target array<double>, row_hash long).

    Only these columns go on, so a scan below reads what they need and nothing else.
    """
    features, target = feature_column(df, spec), F.array(*[number(df, c) for c in spec.targets])
    used = spec.ids or [*([spec.features] if isinstance(spec.features, str) else spec.features), *spec.targets]
    return df.select(*[F.col(g) for g in spec.group_by], features.alias("features"), target.alias("target"), F.xxhash64(*[F.col(c) for c in used]).alias("row_hash"))


def feature_count(df: DataFrame, spec: RidgeSpec) -> int | None:
    """The number of features where the spec or the columns tell it; else the first row tells."""
    if spec.n_features is not None:
        return spec.n_features + int(spec.fit_intercept)
    if isinstance(spec.features, str):
        first = df.select(F.size(feature_column(df, spec)).alias("n")).where("n >= 0").limit(1).collect()
        return int(first[0][0]) if first else None
    return len(spec.features) + int(spec.fit_intercept)


def flat_matrix(column, width: int) -> tuple[np.ndarray, np.ndarray]:
    """An Arrow list column as a matrix, without a copy where it can, and which rows are whole
    (not null, no null inside). A row of another length is an error that names its place."""
    lengths = np.diff(np.asarray(column.offsets)) if column.null_count == 0 else np.array([-1 if v is None else len(v) for v in column.to_pylist()])
    whole = lengths >= 0
    wrong = np.flatnonzero(whole & (lengths != width))
    if len(wrong):
        raise ValueError(f"row {int(wrong[0])} of the batch has {int(lengths[wrong[0]])} features; {width} expected")
    flat = column.flatten()
    values = flat.to_numpy(zero_copy_only=False).astype(np.float64, copy=False) if flat.null_count == 0 else np.array([np.nan if v is None else v for v in flat.to_pylist()], dtype=np.float64)
    out = np.full((len(lengths), width), np.nan)
    out[whole] = values.reshape(-1, width)
    return (values.reshape(-1, width), whole) if whole.all() else (out, whole)


def usable(x: np.ndarray, y: np.ndarray, policy: str) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Rows to use under the policy: (x, y, flags of the rows used)."""
    bad = ~(np.isfinite(x).all(axis=1) & np.isfinite(y).all(axis=1))
    if not bad.any():
        return x, y, ~bad
    if policy == "error":
        raise ValueError(f"row {int(np.flatnonzero(bad)[0])} of the batch holds null, NaN or infinity; set on_invalid to 'skip' or 'zero'")
    if policy == "skip":
        return x[~bad], y[~bad], ~bad
    return np.nan_to_num(x, nan=0.0, posinf=0.0, neginf=0.0), np.nan_to_num(y, nan=0.0, posinf=0.0, neginf=0.0), np.ones(len(x), dtype=bool)
