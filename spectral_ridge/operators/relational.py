"""The additive summaries as plain aggregations: partial and final hash aggregates, no Python."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: Modulus of the arithmetic row hash: prime, and small enough for products to stay in 64 bits.
HASH_PRIME = 2_147_483_647


def affine_hash(key: Column, a: int, b: int) -> Column:
    """((a * key + b) mod prime): the same in any SQL engine."""
    return F.pmod(F.lit(a).cast("long") * F.pmod(key.cast("long"), F.lit(HASH_PRIME)) + F.lit(b), F.lit(HASH_PRIME))


def gram_terms(names: Sequence[str]) -> list[tuple[int, int]]:
    return [(i, j) for i in range(len(names)) for j in range(i, len(names))]


def gram_wide(df: DataFrame, features: Sequence[Column], by: Sequence[str] = ()) -> DataFrame:
    """One row with sums g_i_j of products, i <= j: one hash aggregate, for few features."""
    rows = df.select(*by, *[f.alias(f"f{i}") for i, f in enumerate(features)])
    aggs = [F.sum(F.col(f"f{i}") * F.col(f"f{j}")).alias(f"g_{i}_{j}") for i, j in gram_terms(features)]
    return rows.groupBy(*by).agg(*aggs) if by else rows.agg(*aggs)


def gram_long(df: DataFrame, features: Sequence[Column]) -> DataFrame:
    """(i, j, value) of the Gram matrix's upper triangle."""
    wide = gram_wide(df, features)
    return wide.select(F.explode(F.array(*[F.struct(F.lit(i).alias("i"), F.lit(j).alias("j"), F.col(f"g_{i}_{j}").alias("value")) for i, j in gram_terms(features)])).alias("t")).select("t.*")


def gram_from_arrays(df: DataFrame, features: str) -> DataFrame:
    """(i, j, value) for an array column of any width: exploded pairs, summed map-side first."""
    rows = df.select(F.posexplode(features).alias("i", "x"), F.col(features).alias("rest"))
    pairs = rows.select("i", "x", F.posexplode("rest").alias("j", "y")).where("i <= j")
    return pairs.groupBy("i", "j").agg(F.sum(F.col("x").cast("double") * F.col("y").cast("double")).alias("value"))


def cross_moment(df: DataFrame, features: Sequence[Column], target: Column, by: Sequence[str] = ()) -> DataFrame:
    """(groups..., idx, value): feature-target moments, exact."""
    rows = df.select(*by, *[(f * target).alias(f"c{i}") for i, f in enumerate(features)])
    sums = [F.sum(f"c{i}").alias(f"c{i}") for i in range(len(features))]
    wide = rows.groupBy(*by).agg(*sums) if by else rows.agg(*sums)
    return wide.select(*by, F.posexplode(F.array(*[f"c{i}" for i in range(len(features))])).alias("idx", "value"))


def count_sketch(df: DataFrame, key: Column, features: Sequence[Column], target: Column, ell: int, seed: int = 17) -> DataFrame:
    """(bucket, f0.., t): signed sums per bucket, one hash aggregate of ``ell`` groups."""
    h = affine_hash(key, 48_271 + 2 * seed, 11 + seed)
    sign = F.when(F.pmod(affine_hash(key, 69_621 + 2 * seed, 7 + seed), F.lit(2)) == 0, 1.0).otherwise(-1.0)
    rows = df.select(F.pmod(h, F.lit(ell)).alias("bucket"), *[(sign * f).alias(f"f{i}") for i, f in enumerate(features)], (sign * target).alias("t"))
    return rows.groupBy("bucket").agg(*[F.sum(f"f{i}").alias(f"f{i}") for i in range(len(features))], F.sum("t").alias("t"))


def sign_projection(df: DataFrame, key: Column, features: Sequence[Column], target: Column, ell: int, seed: int = 17) -> DataFrame:
    """(r, f0.., t): each row goes to all ``ell`` sums with a hashed sign, scaled by 1/sqrt(ell)."""
    rows = df.select(key.cast("long").alias("k"), *[f.alias(f"f{i}") for i, f in enumerate(features)], target.alias("t"))
    lanes = rows.withColumn("r", F.explode(F.sequence(F.lit(0), F.lit(ell - 1))))
    bit = F.pmod(F.floor(affine_hash(F.col("k") * ell + F.col("r"), 48_271 + 2 * seed, 11 + seed) / F.lit(1024)), F.lit(2))
    sign = F.when(bit == 0, 1.0).otherwise(-1.0) / F.sqrt(F.lit(float(ell)))
    return lanes.groupBy("r").agg(*[F.sum(sign * F.col(f"f{i}")).alias(f"f{i}") for i in range(len(features))], F.sum(sign * F.col("t")).alias("t"))


def ridge_2d(moments: DataFrame, gamma: Column | float, prefix: Sequence[str] = ("g_0_0", "g_0_1", "g_1_1", "c0", "c1")) -> DataFrame:
    """Adds x0 and x1: two-feature ridge by Cramer's rule, as expressions."""
    a, b, d, u, v = (F.col(p) for p in prefix)
    g = gamma if isinstance(gamma, Column) else F.lit(float(gamma))
    det = (a + g) * (d + g) - b * b
    return moments.withColumns({"x0": ((d + g) * u - b * v) / det, "x1": ((a + g) * v - b * u) / det})


def moments_2d(df: DataFrame, f0: Column, f1: Column, target: Column, by: Sequence[str] = ()) -> DataFrame:
    """(groups..., n, g_0_0, g_0_1, g_1_1, c0, c1, t2): all that two-feature ridge needs."""
    rows = df.select(*by, f0.alias("p"), f1.alias("q"), target.alias("t"))
    p, q, t = F.col("p"), F.col("q"), F.col("t")
    aggs = [F.count("*").alias("n"), F.sum(p * p).alias("g_0_0"), F.sum(p * q).alias("g_0_1"), F.sum(q * q).alias("g_1_1"), F.sum(p * t).alias("c0"), F.sum(q * t).alias("c1"), F.sum(t * t).alias("t2")]
    return rows.groupBy(*by).agg(*aggs) if by else rows.agg(*aggs)
