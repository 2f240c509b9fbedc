"""The experiment workloads on the given tables: (row_id, features, target) DataFrames."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .operators import features as ft
from .sources.generators import planted, spread
from .sources.tables import load_table

#: Selected penalties of the stand-ins (powers of two, least held-out residual at sf0.1).
GAMMA = {"low_rank": 64.0, "high_rank": 512.0, "events": 64.0, "daily": 64.0}


def _planted_embeddings(spark: SparkSession, sf_dir: str, rank: int, seed: int) -> DataFrame:
    d = 64
    x = planted(d, rank, seed)
    base = load_table(spark, sf_dir, "embeddings", ["vec_id", "embedding"])
    scaled = ft.scale_by(F.col("embedding").cast("array<double>"), 8.0 * spread(d, rank))
    rows = base.select(F.col("vec_id").alias("row_id"), scaled.alias("features"))
    signal = F.aggregate(F.zip_with("features", F.array(*[F.lit(float(v)) for v in x]), lambda a, b: a * b), F.lit(0.0), lambda s, v: s + v)
    return ft.rotate(rows.withColumn("target", signal + 2.0 * ft.hash_normal(F.col("row_id"), seed + 5)))


def workload_low_rank(spark: SparkSession, sf_dir: str, seed: int = 0) -> DataFrame:
    """Embeddings scaled to a tenth of the dimensions, planted coefficients, noise of variance 4."""
    return _planted_embeddings(spark, sf_dir, 6, seed)


def workload_high_rank(spark: SparkSession, sf_dir: str, seed: int = 0) -> DataFrame:
    """The same with half of the dimensions."""
    return _planted_embeddings(spark, sf_dir, 32, seed)


def hourly_series(spark: SparkSession, sf_dir: str) -> DataFrame:
    events = load_table(spark, sf_dir, "events", ["ts", "value"])
    hours = events.groupBy(F.date_trunc("HOUR", F.col("ts").cast("timestamp")).alias("hour")).agg(F.avg("value").alias("mean_value"))
    return ft.fill_calendar(hours, "hour", "mean_value")


def workload_event_shingles(spark: SparkSession, sf_dir: str, d: int = 24) -> DataFrame:
    """Hourly mean event value: ``d`` differences predict the next one."""
    return ft.shingles(hourly_series(spark, sf_dir), "hour", "mean_value", d).select(F.unix_seconds("start").alias("row_id"), "features", "target")


def daily_series(spark: SparkSession, sf_dir: str, table: str = "orders") -> DataFrame:
    day, value, how = {"orders": ("o_orderdate", "o_totalprice", F.sum), "lineitem": ("l_shipdate", "l_extendedprice", F.avg)}[table]
    rows = load_table(spark, sf_dir, table, [day, value])
    scale = 1e6 if table == "orders" else 1e4
    return rows.groupBy(F.to_date(day).alias("day")).agg((how(value) / scale).alias("level"))


def workload_daily_shingles(spark: SparkSession, sf_dir: str, table: str = "orders", d: int = 64) -> DataFrame:
    """Daily order totals or mean line prices, shingled."""
    return ft.shingles(daily_series(spark, sf_dir, table), "day", "level", d).select(F.unix_date("start").cast("long").alias("row_id"), "features", "target")


def workload_text_hash(spark: SparkSession, sf_dir: str, width: int = 2048) -> DataFrame:
    """Signed hashed word counts of whole documents; the target is the log of the length. Sparse:
    (row_id, sparse, target)."""
    docs = load_table(spark, sf_dir, "documents", ["doc_id", "text", "n_chars"])
    rows = docs.select(F.col("doc_id").alias("row_id"), "text", F.log1p("n_chars").alias("target"))
    return ft.sparse_text(rows, "text", width, ["row_id", "target"])


def workload_star(spark: SparkSession, sf_dir: str, d: int = 16) -> DataFrame:
    """Order lines with the dimensions of their order, customer, part and supplier: numbers,
    one-hot flags, and hashed dimensions up to ``d`` features."""
    line = load_table(spark, sf_dir, "lineitem")
    orders = load_table(spark, sf_dir, "orders", ["o_orderkey", "o_custkey", "o_orderpriority"])
    customer = load_table(spark, sf_dir, "customer", ["c_custkey", "c_nationkey", "c_mktsegment", "c_acctbal"])
    part = load_table(spark, sf_dir, "part", ["p_partkey", "p_brand", "p_size", "p_retailprice"])
    supplier = load_table(spark, sf_dir, "supplier", ["s_suppkey", "s_nationkey"])
    joined = line.join(orders, F.col("l_orderkey") == F.col("o_orderkey")).join(customer, F.col("o_custkey") == F.col("c_custkey")).join(part, F.col("l_partkey") == F.col("p_partkey")).join(supplier, F.col("l_suppkey") == F.col("s_suppkey"))
    numbers = [F.col("l_quantity") / 50, F.col("l_discount") * 10, F.col("l_tax") * 10, F.col("p_size") / 50, F.col("p_retailprice") / 1000, F.col("c_acctbal") / 1e4, F.lit(1.0)]
    flags = ft.one_hot("l_returnflag", ["A", "N", "R"])
    rest = max(0, d - len(numbers) - 3)
    hashed = ft.hash_features(joined, ["o_orderpriority", "c_mktsegment", "p_brand", "c_nationkey", "s_nationkey"], max(rest, 1), "hashed")
    whole = F.concat(ft.assemble(*numbers), flags, F.col("hashed") if rest else F.array().cast("array<double>"))
    return hashed.select(F.xxhash64(*line.columns).alias("row_id"), F.slice(whole, 1, d).alias("features"), (F.col("l_extendedprice") / 1e5).alias("target"))


def workload_adversarial(spark: SparkSession, n: int = 4096, d: int = 32, strong: int = 8) -> DataFrame:
    """Strong axes first, then a long weak tail along one further direction that carries the
    target: truncation drops each weak batch and never sees it."""
    ids = spark.range(n, numPartitions=1)
    first = F.col("id") < 4 * strong
    axis = F.pmod("id", F.lit(strong)).cast("int")
    weak = F.lit(0.5) + 0.1 * ft.hash_normal(F.col("id"), 3)
    entry = lambda k: F.when(first & (axis == k), 10.0).when(~first & F.lit(k == strong), weak).otherwise(0.0)
    rows = ids.select(F.col("id").alias("row_id"), F.array(*[entry(k) for k in range(d)]).alias("features"))
    return rows.withColumn("target", F.element_at("features", strong + 1) + 0.1 * ft.hash_normal(F.col("row_id"), 4))


def workload_flat(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Embeddings as they are: near-equal top singular values, the unstable case of principal
    component regression."""
    base = load_table(spark, sf_dir, "embeddings")
    return base.select(F.col("vec_id").alias("row_id"), F.col("embedding").cast("array<double>").alias("features"), F.col("label").cast("double").alias("target"))


def dense(df: DataFrame, n: int) -> tuple[np.ndarray, np.ndarray]:
    """All rows as matrices on the driver, for tables of at most ``n`` rows: a larger one is an error."""
    rows = df.select("row_id", "features", "target").limit(n + 1).collect()
    if len(rows) > n:
        raise ValueError(f"more than {n} rows")
    rows.sort(key=lambda r: r[0])
    return np.array([r[1] for r in rows], dtype=np.float64), np.array([r[2] for r in rows], dtype=np.float64)
