"""Feature building, in built-in functions."""

from __future__ import annotations

from collections.abc import Iterator, Sequence

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..runtime import ship_package


def assemble(*columns: Column | str) -> Column:
    return F.array(*[(F.col(c) if isinstance(c, str) else c).cast("double") for c in columns])


def one_hot(column: Column | str, vocabulary: Sequence[str]) -> Column:
    """1.0 at the value's place in the vocabulary; all 0 for other values and null."""
    c = F.col(column) if isinstance(column, str) else column
    return F.array(*[F.coalesce((c == F.lit(v)).cast("double"), F.lit(0.0)) for v in vocabulary])


def text_hash(text: Column, width: int, prime: int = 1_000_003) -> Column:
    """Sum of code points of a token modulo a prime, modulo the width: the same in any engine."""
    points = F.transform(F.filter(F.split(text, ""), lambda x: x != ""), lambda x: F.ascii(x))
    return F.pmod(F.aggregate(points, F.lit(0).cast("long"), lambda s, x: F.pmod(s * 31 + x, F.lit(prime).cast("long"))), F.lit(width))


def hash_features(df: DataFrame, columns: Sequence[str], width: int, name: str = "features") -> DataFrame:
    """Signed hashing of (column, value) pairs to a dense array of ``width``."""
    hashes = [F.xxhash64(F.lit(c), F.col(c).cast("string")) for c in columns]
    terms = F.array(*[F.struct(F.pmod(h, F.lit(width)).alias("at"), F.when(F.shiftrightunsigned(h, 63) == 0, 1.0).otherwise(-1.0).alias("sign")) for h in hashes])
    if width <= 64:  # plain expressions stay in generated code
        parts = [(F.pmod(h, F.lit(width)), F.when(F.shiftrightunsigned(h, 63) == 0, 1.0).otherwise(-1.0)) for h in hashes]
        return df.withColumn(name, F.array(*[sum((F.when(at == k, sign).otherwise(0.0) for at, sign in parts), F.lit(0.0)) for k in range(width)]))
    dense = F.transform(F.sequence(F.lit(0), F.lit(width - 1)), lambda k: F.aggregate(F.filter("hash_terms", lambda t: t["at"] == k), F.lit(0.0), lambda s, t: s + t["sign"]))
    return df.withColumn("hash_terms", terms).withColumn(name, dense).drop("hash_terms")


def sparse_text(df: DataFrame, text: str, width: int, keep: Sequence[str] = ()) -> DataFrame:
    """(keep..., sparse struct<indices, values>): signed hashed words of the whole text, one entry a
    word; entries of one index add up. Nothing is shuffled: the sketch sums them where the row is."""
    words = F.filter(F.split(F.lower(F.coalesce(F.col(text), F.lit(""))), r"[^\p{L}\p{N}]+"), lambda w: w != "")
    hashed = df.select(*keep, F.transform(words, lambda w: F.xxhash64(w)).alias("h"))
    at, sign = F.transform("h", lambda h: F.pmod(h, F.lit(width)).cast("int")), F.transform("h", lambda h: F.when(h >= 0, 1.0).otherwise(-1.0))
    return hashed.select(*keep, F.struct(at.alias("indices"), sign.alias("values")).alias("sparse"))


def polynomial(features: Column, degree: int = 2) -> Column:
    """The features and their powers up to ``degree``."""
    def power(p: int) -> Column:
        return F.transform(features, lambda x: F.pow(x, F.lit(p)))

    return F.flatten(F.array(*[power(p) for p in range(1, degree + 1)]))


def interactions(features: Column) -> Column:
    """Products of all pairs i < j."""
    return F.flatten(F.transform(features, lambda x, i: F.transform(F.slice(features, i + 2, F.size(features)), lambda y: x * y)))


def standardise(df: DataFrame, columns: Sequence[str]) -> DataFrame:
    """Columns less their mean, over their population deviation: one aggregate, broadcast back."""
    stats = df.agg(*[F.avg(c).alias(f"m_{c}") for c in columns], *[F.stddev_pop(c).alias(f"s_{c}") for c in columns])
    joined = df.crossJoin(F.broadcast(stats))
    scaled = {c: (F.col(c) - F.col(f"m_{c}")) / F.when(F.col(f"s_{c}") > 0, F.col(f"s_{c}")).otherwise(1.0) for c in columns}
    return joined.withColumns(scaled).select(*df.columns)


def add_intercept(features: Column) -> Column:
    return F.concat(features, F.array(F.lit(1.0)))


def scale_by(features: Column, weights: Sequence[float]) -> Column:
    return F.zip_with(features, F.array(*[F.lit(float(w)) for w in weights]), lambda x, w: x * w)


def valid_rows(features: Column) -> Column:
    """True where no entry is null, NaN or infinite."""
    return features.isNotNull() & F.forall(features, lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < float("inf")))


def cosine_matrix(d: int) -> np.ndarray:
    """The orthonormal discrete cosine transform of the second kind."""
    k = np.arange(d)
    out = np.cos(np.pi * (2 * k[None, :] + 1) * k[:, None] / (2 * d)) * np.sqrt(2 / d)
    out[0] /= np.sqrt(2)
    return out


def rotate(df: DataFrame, features: str = "features") -> DataFrame:
    """Features rotated by the cosine transform: a matrix product per Arrow batch."""
    ship_package(df.sparkSession)
    schema = df.schema

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        matrix = None
        for batch in batches:
            at = batch.schema.get_field_index(features)
            column = batch.column(at)
            if not batch.num_rows:
                continue
            x = np.array(column.to_pylist(), dtype=np.float64)
            if matrix is None or len(matrix) != x.shape[1]:
                matrix = cosine_matrix(x.shape[1])
            rows = pa.ListArray.from_arrays(np.arange(len(x) + 1, dtype=np.int32) * x.shape[1], pa.array((x @ matrix.T).reshape(-1)))
            yield batch.set_column(at, batch.schema.field(at), rows.cast(batch.schema.field(at).type))

    return df.mapInArrow(run, schema)


def split_column(key: Column, percent: int = 80) -> Column:
    """True for training rows: an arithmetic split that any engine repeats."""
    return F.pmod(key.cast("long") * 7919 + 13, F.lit(100)) < percent


def train_test(df: DataFrame, key: str, percent: int = 80) -> tuple[DataFrame, DataFrame]:
    flag = split_column(F.col(key), percent)
    return df.where(flag), df.where(~flag)


def hash_normal(key: Column, seed: int) -> Column:
    """A standard normal number from a row's key: the same whatever the partitioning."""
    def uniform(s: int) -> Column:
        return (F.pmod(F.xxhash64(key, F.lit(s)), F.lit(1 << 52)) + 0.5) / float(1 << 52)

    return F.sqrt(-2.0 * F.log(uniform(2 * seed))) * F.cos(2.0 * np.pi * uniform(2 * seed + 1))


def shingles(series: DataFrame, order: str, value: str, d: int) -> DataFrame:
    """(start, features, target): ``d`` consecutive first differences, and the next one.

    ``series`` is an aggregated series (a row per hour or day), so one ordered window over it is
    a window over few rows whatever the input's size.
    """
    w = Window.orderBy(order)
    diffs = series.select(order, (F.col(value) - F.lag(value).over(w)).alias("diff")).where("diff is not null")
    ahead = w.rowsBetween(0, d)
    rows = diffs.select(F.col(order).alias("start"), F.collect_list("diff").over(ahead).alias("run")).where(F.size("run") == d + 1)
    return rows.select("start", F.slice("run", 1, d).alias("features"), F.element_at("run", d + 1).alias("target"))


def sample_rows(df: DataFrame, key: str, n: int, seed: int = 0) -> DataFrame:
    """``n`` rows without replacement: the lowest by hashed key."""
    return df.orderBy(F.xxhash64(F.col(key), F.lit(seed)), key).limit(n)


def fill_calendar(series: DataFrame, order: str, value: str, step: str = "INTERVAL 1 HOUR") -> DataFrame:
    """The series on every step of its range; gaps carry the last value on."""
    calendar = series.agg(F.min(order).alias("lo"), F.max(order).alias("hi")).select(F.explode(F.expr(f"sequence(lo, hi, {step})")).alias("tick"))
    joined = calendar.join(series, F.col("tick") == F.col(order), "left")
    return joined.select(F.col("tick").alias(order), F.last(value, ignorenulls=True).over(Window.orderBy("tick")).alias(value))
