"""Registered queries of the methods, baselines, measures and workloads, with their SQL.

Lossy sketches have SQL twins where the sketch has one row over two features and one row per
batch: a shrink step then takes the smallest eigenvalue off the 2 x 2 Gram matrix, which a
recursive query replays. Everything else is compared in closed form, or has no SQL and is held
against NumPy in the tests.
"""

from __future__ import annotations

from collections.abc import Callable

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import workloads as wl
from .operators import features as ft
from .operators import relational as rel
from .operators.design import RidgeSpec
from .operators.fit import collect_sketch, fit_sketch, fit_sparse, merge_sketches
from .operators.predict import predict, prediction_error
from .operators.solve import coefficients, gram_of, long_coefficients, solve, solve_components, solve_dual, solve_primal
from .plans import bounds, metrics
from .plans.gamma import gamma_losses, select_gamma
from .plans.risk import risk, risk_factors
from .sources.generators import planted
from .sources.tables import load_table
from .streaming.sketches import windowed_sketches

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
SQL: dict[str, str] = {}

D2 = RidgeSpec(["p", "q"], "t", "k")


def query(sql: str | None = None) -> Callable[[Query], Query]:
    def add(f: Query) -> Query:
        QUERIES[f.__name__] = f
        if sql is not None:
            SQL[f.__name__] = sql
        return f

    return add


def supplier_rows(spark: SparkSession, sf_dir: str) -> DataFrame:
    s = load_table(spark, sf_dir, "supplier", ["s_suppkey", "s_acctbal", "s_nationkey"])
    return s.select(F.col("s_suppkey").alias("k"), (F.col("s_acctbal") / 1e4).alias("p"), (F.col("s_nationkey") / 25.0).alias("q"), (F.col("s_suppkey") / 100.0).alias("t"))


def customer_rows(spark: SparkSession, sf_dir: str) -> DataFrame:
    c = load_table(spark, sf_dir, "customer", ["c_custkey", "c_acctbal", "c_nationkey"])
    return c.select(F.col("c_custkey").alias("k"), (F.col("c_acctbal") / 1e4).alias("p"), (F.col("c_nationkey") / 25.0).alias("q")).withColumn("t", 0.7 * F.col("p") - 0.3 * F.col("q"))


def lineitem_rows(spark: SparkSession, sf_dir: str) -> DataFrame:
    li = load_table(spark, sf_dir, "lineitem")
    return li.select(F.xxhash64(*li.columns).alias("k"), (F.col("l_quantity") / 50).alias("p"), (F.col("l_discount") * 10).alias("q"), (F.col("l_extendedprice") / 1e5).alias("t"), "l_orderkey", "l_partkey", "l_suppkey", "l_linenumber")


def _rounded(df: DataFrame, digits: int, *names: str) -> DataFrame:
    return df.withColumns({n: F.round(n, digits) + F.lit(0.0) for n in names})


def _coefs(solution: DataFrame, digits: int = 6, *by: str) -> DataFrame:
    return _rounded(long_coefficients(solution, by), digits, "coef").select(*by, "idx", "coef")


def lossy(spark: SparkSession, sf_dir: str, method: str, rows: Callable = supplier_rows) -> DataFrame:
    return fit_sketch(rows(spark, sf_dir), D2, method, 1, batch_rows=1, deterministic_order=True, partitions=1)


# ---------------------------------------------------------------- SQL building blocks

S_ROWS = "SELECT s_suppkey AS k, s_acctbal / 1e4 AS p, s_nationkey / 25.0 AS q, s_suppkey / 100.0 AS t FROM supplier"
C_ROWS = "SELECT c_custkey AS k, c_acctbal / 1e4 AS p, c_nationkey / 25.0 AS q, 0.7 * (c_acctbal / 1e4) - 0.3 * (c_nationkey / 25.0) AS t FROM customer"
L_ROWS = "SELECT l_quantity / 50 AS p, l_discount * 10 AS q, l_extendedprice / 1e5 AS t, l_orderkey, l_partkey, l_suppkey, l_linenumber FROM lineitem"


def moments_sql(rows: str, by: str = "") -> str:
    return f"SELECT {by + ', ' if by else ''}CAST(count(*) AS DOUBLE) AS n, sum(p * p) AS a, sum(p * q) AS b, sum(q * q) AS d, sum(p * t) AS u, sum(q * t) AS v, sum(t * t) AS w FROM ({rows}){' GROUP BY ' + by if by else ''}"


def cramer(a: str, b: str, d: str, g: str) -> tuple[str, str]:
    det = f"(({a} + {g}) * ({d} + {g}) - {b} * {b})"
    return f"((({d} + {g}) * u - {b} * v) / {det})", f"((({a} + {g}) * v - {b} * u) / {det})"


def two_rows(x0: str, x1: str, source: str, digits: int = 6, extra: str = "") -> str:
    part = f"{extra + ', ' if extra else ''}"
    return f"SELECT {part}CAST(0 AS INTEGER) AS idx, round({x0}, {digits}) AS coef FROM {source} UNION ALL SELECT {part}CAST(1 AS INTEGER) AS idx, round({x1}, {digits}) AS coef FROM {source}"


def exact_sql(rows: str, gamma: str, digits: int = 6) -> str:
    return f"WITH m AS ({moments_sql(rows)}) {two_rows(*cramer('a', 'b', 'd', gamma), 'm', digits)}"


def replay_sql(rows: str, kind: str = "shrink") -> str:
    """CTE ``last``: the sketch's Gram matrix after the last row, the removed amount, and moments."""
    low = "greatest(0.0, ((a11 + a22) - sqrt((a11 - a22) * (a11 - a22) + 4 * a12 * a12)) / 2)"
    high = "(((a11 + a22) + sqrt((a11 - a22) * (a11 - a22) + 4 * a12 * a12)) / 2)"
    scale = "1.0" if kind == "shrink" else f"({high} / ({high} - {low}))"
    return f"""
src AS ({rows}), ordered AS (SELECT row_number() OVER (ORDER BY k) AS rn, p, q FROM src),
r AS (
  SELECT CAST(0 AS BIGINT) AS rn, CAST(0 AS DOUBLE) AS g11, CAST(0 AS DOUBLE) AS g12, CAST(0 AS DOUBLE) AS g22, CAST(0 AS DOUBLE) AS removed
  UNION ALL
  SELECT rn, {scale} * (a11 - {low}), {scale} * a12, {scale} * (a22 - {low}), removed + {low}
  FROM (SELECT o.rn, g11 + p * p AS a11, g12 + p * q AS a12, g22 + q * q AS a22, removed FROM r JOIN ordered o ON o.rn = r.rn + 1)),
m AS ({moments_sql('SELECT * FROM src')}),
last AS (SELECT r.*, m.* FROM r, m WHERE rn = (SELECT max(rn) FROM r))"""


def lossy_sql(gamma: str, rows: str = S_ROWS, kind: str = "shrink", digits: int = 6) -> str:
    return f"WITH RECURSIVE {replay_sql(rows, kind)} {two_rows(*cramer('g11', 'g12', 'g22', gamma), 'last', digits)}"


# ---------------------------------------------------------------- exact Gram, moments, ridge

@query("WITH f AS (SELECT [l_quantity / 50, l_discount * 10, l_tax * 10, 1.0] AS x FROM lineitem), ij AS (SELECT CAST(i AS INTEGER) AS i, CAST(j AS INTEGER) AS j FROM range(4) a(i), range(4) b(j) WHERE i <= j) SELECT i, j, round(sum(x[i + 1] * x[j + 1]), 3) AS value FROM f, ij GROUP BY i, j")
def gram_lineitem_long(spark, sf_dir):
    li = load_table(spark, sf_dir, "lineitem", ["l_quantity", "l_discount", "l_tax"])
    return _rounded(rel.gram_long(li, [F.col("l_quantity") / 50, F.col("l_discount") * 10, F.col("l_tax") * 10, F.lit(1.0)]), 3, "value")


@query(f"WITH m AS ({moments_sql(L_ROWS)}) SELECT CAST(0 AS INTEGER) AS idx, round(u, 4) AS value FROM m UNION ALL SELECT CAST(1 AS INTEGER), round(v, 4) FROM m")
def cross_moment_lineitem(spark, sf_dir):
    li = load_table(spark, sf_dir, "lineitem", ["l_quantity", "l_discount", "l_extendedprice"])
    return _rounded(rel.cross_moment(li, [F.col("l_quantity") / 50, F.col("l_discount") * 10], F.col("l_extendedprice") / 1e5), 4, "value")


@query(exact_sql(L_ROWS, "64.0"))
def exact_ridge_lineitem_d2(spark, sf_dir):
    return _coefs(solve(fit_sketch(lineitem_rows(spark, sf_dir), D2, "exact_ridge", 1), 64.0))


@query(exact_sql(L_ROWS, "64.0"))
def exact_ridge_sql_lineitem_d2(spark, sf_dir):
    """The same by aggregation and Cramer's rule alone: no Python."""
    m = rel.ridge_2d(rel.moments_2d(lineitem_rows(spark, sf_dir), F.col("p"), F.col("q"), F.col("t")), 64.0)
    return _rounded(m.select(F.posexplode(F.array("x0", "x1")).alias("idx", "coef")), 6, "coef")


_O_ROWS = "SELECT o_orderpriority, month(o_orderdate) / 12.0 AS p, dayofweek(o_orderdate) / 7.0 AS q, o_totalprice / 5e5 AS t FROM orders"


@query(f"WITH m AS ({moments_sql(_O_ROWS, 'o_orderpriority')}) {two_rows(*cramer('a', 'b', 'd', '8.0'), 'm', 6, 'o_orderpriority')}")
def exact_ridge_orders_by_priority(spark, sf_dir):
    o = load_table(spark, sf_dir, "orders", ["o_orderkey", "o_orderpriority", "o_orderdate", "o_totalprice"])
    rows = o.select("o_orderpriority", F.col("o_orderkey").alias("k"), (F.month("o_orderdate") / 12.0).alias("p"), ((F.dayofweek("o_orderdate") - 1) / 7.0).alias("q"), (F.col("o_totalprice") / 5e5).alias("t"))
    spec = RidgeSpec(["p", "q"], "t", "k", ("o_orderpriority",))
    return _coefs(solve(fit_sketch(rows, spec, "exact_ridge", 1), 8.0, by=["o_orderpriority"]), 6, "o_orderpriority")


def _full_rank(name: str, method: str, ell: int) -> None:
    def f(spark, sf_dir):
        return _coefs(solve(fit_sketch(lineitem_rows(spark, sf_dir), D2, method, ell, batch_rows=512), 64.0))

    f.__name__ = name
    query(exact_sql(L_ROWS, "64.0"))(f)


for _name, _method, _ell in (("fd_ridge_full_rank_lineitem", "fd_ridge", 2), ("robust_fd_ridge_full_rank_lineitem", "robust_fd_ridge", 3), ("truncated_svd_ridge_full_rank", "truncated_svd_ridge", 2), ("two_level_full_rank", "two_level_ridge", 4)):
    _full_rank(_name, _method, _ell)


# ---------------------------------------------------------------- lossy sketches, replayed in SQL

@query(lossy_sql("2.0"))
def fd_ridge_lossy_supplier(spark, sf_dir):
    return _coefs(solve(lossy(spark, sf_dir, "fd_ridge"), 2.0))


@query(lossy_sql("(2.0 + removed / 2)"))
def robust_fd_ridge_lossy_supplier(spark, sf_dir):
    return _coefs(solve(lossy(spark, sf_dir, "robust_fd_ridge"), 2.0))


@query(lossy_sql("(2.0 + removed / 2)"))
def robust_from_plain_sketch_supplier(spark, sf_dir):
    """A plain sketch answers for the robust method: the removed amount is kept apart."""
    return _coefs(solve(lossy(spark, sf_dir, "fd_ridge"), 2.0, robust=True))


@query(lossy_sql("2.0", kind="truncate"))
def truncated_svd_lossy_supplier(spark, sf_dir):
    return _coefs(solve(lossy(spark, sf_dir, "truncated_svd_ridge"), 2.0))


@query(f"WITH RECURSIVE {replay_sql(C_ROWS)} SELECT round(g11, 5) AS g11, round(g12, 5) AS g12, round(g22, 5) AS g22, round(removed, 5) AS removed, n AS n_rows FROM last")
def fd_sketch_gram_lossy_customer(spark, sf_dir):
    row = collect_sketch(lossy(spark, sf_dir, "fd_ridge", customer_rows))
    g = gram_of(row)
    return _rounded(spark.createDataFrame([(float(g[0, 0]), float(g[0, 1]), float(g[1, 1]), row.shrink_total, float(row.n_rows))], "g11 double, g12 double, g22 double, removed double, n_rows double"), 5, "g11", "g12", "g22", "removed")


_PATH = [0.5, 2.0, 8.0, 32.0]
_PX = cramer("g11", "g12", "g22", "gamma")


@query(f"WITH RECURSIVE {replay_sql(S_ROWS)}, path AS (SELECT CAST(unnest([0.5, 2.0, 8.0, 32.0]) AS DOUBLE) AS gamma), both_ AS (SELECT * FROM last, path) {two_rows(*_PX, 'both_', 6, 'gamma')}")
def fd_ridge_gamma_path_supplier(spark, sf_dir):
    return _rounded(long_coefficients(solve(lossy(spark, sf_dir, "fd_ridge"), _PATH)), 6, "coef").select("gamma", "idx", "coef")


@query(f"WITH RECURSIVE {replay_sql(S_ROWS)} SELECT round(removed / 2.0, 6) AS plain, round((removed / 2) / (2.0 + removed / 2), 6) AS robust FROM last")
def certificate_supplier(spark, sf_dir):
    sketch = lossy(spark, sf_dir, "fd_ridge")
    plain = solve(sketch, 2.0).select(F.col("certificate").alias("plain"))
    robust = solve(sketch, 2.0, robust=True).select(F.col("certificate").alias("robust"))
    return _rounded(plain.crossJoin(robust), 6, "plain", "robust")


_EX = cramer("a", "b", "d", "2.0")
_LX = cramer("g11", "g12", "g22", "2.0")


@query(f"WITH RECURSIVE {replay_sql(S_ROWS)}, x AS (SELECT {_EX[0]} AS e0, {_EX[1]} AS e1, {_LX[0]} AS l0, {_LX[1]} AS l1 FROM last) SELECT round(sqrt((e0 - l0) * (e0 - l0) + (e1 - l1) * (e1 - l1)) / sqrt(e0 * e0 + e1 * e1), 6) AS coef_error FROM x")
def coef_error_lossy_supplier(spark, sf_dir):
    exact = collect_sketch(fit_sketch(supplier_rows(spark, sf_dir), D2, "exact_ridge", 1))
    lossy_row = collect_sketch(lossy(spark, sf_dir, "fd_ridge"))
    return spark.createDataFrame([(round(metrics.coef_error(coefficients(lossy_row, 2.0), coefficients(exact, 2.0)), 6),)], "coef_error double")


@query(f"WITH RECURSIVE {replay_sql(S_ROWS)}, x AS (SELECT {_LX[0]} AS l0, {_LX[1]} AS l1 FROM last) SELECT CAST(2.0 AS DOUBLE) AS gamma, round(avg((l0 * p + l1 * q - t) * (l0 * p + l1 * q - t)), 6) AS pred_mse FROM src, x")
def pred_mse_lossy_supplier(spark, sf_dir):
    return _rounded(metrics.pred_mse(supplier_rows(spark, sf_dir), solve(lossy(spark, sf_dir, "fd_ridge"), 2.0), D2), 6, "pred_mse")


@query(f"WITH RECURSIVE {replay_sql(S_ROWS)}, x AS (SELECT {_LX[0]} AS l0, {_LX[1]} AS l1 FROM last) SELECT CAST(2.0 AS DOUBLE) AS gamma, round(sum((l0 * p + l1 * q - t) * (l0 * p + l1 * q - t)) + 2.0 * (any_value(l0) * any_value(l0) + any_value(l1) * any_value(l1)), 5) AS objective FROM src, x")
def objective_lossy_supplier(spark, sf_dir):
    return _rounded(metrics.objective(supplier_rows(spark, sf_dir), solve(lossy(spark, sf_dir, "fd_ridge"), 2.0), D2), 5, "objective")


# ---------------------------------------------------------------- random transforms as aggregations

P = rel.HASH_PRIME
_SEED = 17
_H1, _H2 = (48_271 + 2 * _SEED, 11 + _SEED), (69_621 + 2 * _SEED, 7 + _SEED)


def hash_sql(key: str, a: int, b: int) -> str:
    return f"((({a} * ({key} % {P})) + {b}) % {P})"


def count_sketch_sql(rows: str, key: str, columns: list[str], ell: int) -> str:
    sign = f"(CASE WHEN {hash_sql(key, *_H2)} % 2 = 0 THEN 1.0 ELSE -1.0 END)"
    return f"SELECT CAST({hash_sql(key, *_H1)} % {ell} AS BIGINT) AS bucket, " + ", ".join(f"sum({sign} * {c}) AS {n}" for n, c in columns) + f" FROM ({rows}) GROUP BY 1"


_OC = "SELECT o_orderkey, month(o_orderdate) / 12.0 AS p, dayofweek(o_orderdate) / 7.0 AS q, o_totalprice / 5e5 AS t FROM orders"
_OCS = count_sketch_sql(_OC, "o_orderkey", [("f0", "p"), ("f1", "q"), ("t", "t")], 16)


def _orders_design(spark, sf_dir):
    o = load_table(spark, sf_dir, "orders", ["o_orderkey", "o_orderdate", "o_totalprice"])
    return o.select("o_orderkey", (F.month("o_orderdate") / 12.0).alias("p"), ((F.dayofweek("o_orderdate") - 1) / 7.0).alias("q"), (F.col("o_totalprice") / 5e5).alias("t"))


def _orders_count_sketch(spark, sf_dir, ell: int = 16):
    return rel.count_sketch(_orders_design(spark, sf_dir), F.col("o_orderkey"), [F.col("p"), F.col("q")], F.col("t"), ell)


@query(f"SELECT bucket, round(f0, 5) AS f0, round(f1, 5) AS f1, round(t, 5) AS t FROM ({_OCS})")
def count_sketch_rows_orders(spark, sf_dir):
    return _rounded(_orders_count_sketch(spark, sf_dir), 5, "f0", "f1", "t")


def _sketch_solution(rows: DataFrame, gamma: float) -> DataFrame:
    c = rel.moments_2d(rows, F.col("f0"), F.col("f1"), F.col("t"))
    return _rounded(rel.ridge_2d(c, gamma).select(F.posexplode(F.array("x0", "x1")).alias("idx", "coef")), 5, "coef")


_CS_MOM = "SELECT sum(f0 * f0) AS a, sum(f0 * f1) AS b, sum(f1 * f1) AS d, sum(f0 * t) AS u, sum(f1 * t) AS v FROM"


@query(f"WITH m AS ({_CS_MOM} ({_OCS})) {two_rows(*cramer('a', 'b', 'd', '64.0'), 'm', 5)}")
def count_sketch_ridge_orders(spark, sf_dir):
    return _sketch_solution(_orders_count_sketch(spark, sf_dir), 64.0)


def sign_sql(rows: str, key: str, columns: list[str], ell: int) -> str:
    bit = f"CAST(floor({hash_sql(f'({key} * {ell} + r)', *_H1)} / 1024) AS BIGINT) % 2"
    sign = f"((CASE WHEN {bit} = 0 THEN 1.0 ELSE -1.0 END) / sqrt({float(ell)}))"
    return "SELECT CAST(r AS INTEGER) AS r, " + ", ".join(f"sum({sign} * {c}) AS {n}" for n, c in columns) + f" FROM ({rows}), range({ell}) lanes(r) GROUP BY r"


_EV = "SELECT event_id, value / 100 AS p, hour(ts) / 24.0 AS q, user_id % 10 / 10.0 AS t FROM events"
_EVS = sign_sql(_EV, "event_id", [("f0", "p"), ("f1", "q"), ("t", "t")], 16)


def _event_signs(spark, sf_dir):
    e = load_table(spark, sf_dir, "events", ["event_id", "ts", "user_id", "value"])
    rows = e.select("event_id", (F.col("value") / 100).alias("p"), (F.hour("ts") / 24.0).alias("q"), (F.col("user_id") % 10 / 10.0).alias("t"))
    return rel.sign_projection(rows, F.col("event_id"), [F.col("p"), F.col("q")], F.col("t"), 16)


@query(f"SELECT r, round(f0, 5) AS f0, round(f1, 5) AS f1, round(t, 5) AS t FROM ({_EVS})")
def sign_projection_rows_events(spark, sf_dir):
    return _rounded(_event_signs(spark, sf_dir), 5, "f0", "f1", "t")


@query(f"WITH m AS ({_CS_MOM} ({_EVS})) {two_rows(*cramer('a', 'b', 'd', '64.0'), 'm', 5)}")
def sign_projection_ridge_events(spark, sf_dir):
    return _sketch_solution(_event_signs(spark, sf_dir), 64.0)


@query(f"WITH e AS (SELECT vec_id, unnest(range(64)) AS i, unnest(embedding) AS x FROM embeddings) SELECT CAST({hash_sql('vec_id', *_H1)} % 8 AS BIGINT) AS bucket, CAST(i AS INTEGER) AS i, round(sum((CASE WHEN {hash_sql('vec_id', *_H2)} % 2 = 0 THEN 1.0 ELSE -1.0 END) * CAST(x AS DOUBLE)), 5) AS value FROM e GROUP BY 1, 2")
def count_sketch_embeddings(spark, sf_dir):
    e = load_table(spark, sf_dir, "embeddings", ["vec_id", "embedding"])
    sign = F.when(F.pmod(rel.affine_hash(F.col("vec_id"), *_H2), F.lit(2)) == 0, 1.0).otherwise(-1.0)
    rows = e.select(F.pmod(rel.affine_hash(F.col("vec_id"), *_H1), F.lit(8)).alias("bucket"), sign.alias("sign"), F.posexplode("embedding").alias("i", "x"))
    return _rounded(rows.groupBy("bucket", "i").agg(F.sum(F.col("sign") * F.col("x").cast("double")).alias("value")), 5, "value")


@query("WITH e AS (SELECT vec_id, unnest(embedding) AS x FROM embeddings) SELECT round(sum(CAST(x AS DOUBLE) * CAST(x AS DOUBLE)), 4) AS frob_sq, count(DISTINCT vec_id) AS n_rows FROM e")
def gram_embeddings_trace_frob(spark, sf_dir):
    row = fit_sketch(load_table(spark, sf_dir, "embeddings"), RidgeSpec("embedding", "label", "vec_id"), "exact_ridge", 1)
    return _rounded(row.select("frob_sq", "n_rows"), 4, "frob_sq")


@query("WITH e AS (SELECT vec_id, unnest(range(64)) AS i, unnest(embedding) AS x FROM embeddings) SELECT CAST(a.i AS INTEGER) AS i, CAST(b.i AS INTEGER) AS j, round(sum(CAST(a.x AS DOUBLE) * CAST(b.x AS DOUBLE)), 4) AS value FROM e a JOIN e b ON a.vec_id = b.vec_id AND a.i <= b.i GROUP BY 1, 2")
def gram_embeddings_long(spark, sf_dir):
    return _rounded(rel.gram_from_arrays(load_table(spark, sf_dir, "embeddings", ["embedding"]), "embedding"), 4, "value")


# ---------------------------------------------------------------- merging, other solvers, selection

@query(exact_sql(C_ROWS, "4.0"))
def merge_equals_single_full_rank(spark, sf_dir):
    """One sketch per region, merged: five sites answer like one stream."""
    c, n = load_table(spark, sf_dir, "customer", ["c_custkey", "c_nationkey"]), load_table(spark, sf_dir, "nation", ["n_nationkey", "n_regionkey"])
    site = c.join(F.broadcast(n), c["c_nationkey"] == n["n_nationkey"]).select(F.col("c_custkey").alias("k"), "n_regionkey")
    rows = customer_rows(spark, sf_dir).join(site, "k")
    per_site = fit_sketch(rows, RidgeSpec(["p", "q"], "t", "k", ("n_regionkey",)), "fd_ridge", 2)
    merged = merge_sketches(per_site.withColumn("part_id", F.col("n_regionkey").cast("long")), (), 16, 5, "fd_ridge")
    return _coefs(solve(merged, 4.0))


@query(exact_sql(L_ROWS, "0.0"))
def least_squares_lineitem(spark, sf_dir):
    return _coefs(solve(fit_sketch(lineitem_rows(spark, sf_dir), D2, "exact_ridge", 1), 0.0))


_N_ROWS = "SELECT n_nationkey / 25.0 AS p, n_regionkey / 5.0 AS q, length(n_name) / 10.0 AS t FROM nation"


@query(exact_sql(_N_ROWS, "0.5"))
def dual_ridge_region(spark, sf_dir):
    """The row-by-row form on a table of 25 rows."""
    rows = load_table(spark, sf_dir, "nation").select((F.col("n_nationkey") / 25.0).alias("p"), (F.col("n_regionkey") / 5.0).alias("q"), (F.length("n_name") / 10.0).alias("t")).collect()
    x = solve_dual(np.array([[r[0], r[1]] for r in rows]), np.array([r[2] for r in rows]), 0.5)
    return spark.createDataFrame([(i, round(float(v), 6)) for i, v in enumerate(x)], "idx int, coef double")


_SPLIT = "(l_orderkey * 7919 + 13) % 100"
_GRID = [float(2**k) for k in range(0, 21, 2)]
_TR = f"SELECT * FROM ({L_ROWS}) WHERE {_SPLIT} < 80"
_GX = cramer("a", "b", "d", "gamma")
_LOSS = f"""m AS ({moments_sql(_TR)}), g AS (SELECT CAST(unnest({_GRID}) AS DOUBLE) AS gamma), x AS (SELECT gamma, {_GX[0]} AS x0, {_GX[1]} AS x1 FROM m, g),
test AS (SELECT * FROM ({L_ROWS}) WHERE {_SPLIT} >= 80),
loss AS (SELECT gamma, sqrt(sum((x0 * p + x1 * q - t) * (x0 * p + x1 * q - t))) AS residual_norm FROM test, x GROUP BY gamma)"""


@query(f"WITH {_LOSS} SELECT gamma, round(residual_norm, 5) AS residual_norm FROM loss ORDER BY loss.residual_norm, gamma LIMIT 1")
def gamma_selection_lineitem_d2(spark, sf_dir):
    train, test = ft.train_test(lineitem_rows(spark, sf_dir), "l_orderkey")
    return _rounded(select_gamma(train, test, D2, _GRID), 5, "residual_norm")


@query(f"WITH {_LOSS} SELECT gamma, round(residual_norm, 5) AS residual_norm FROM loss")
def holdout_norm_lineitem(spark, sf_dir):
    train, test = ft.train_test(lineitem_rows(spark, sf_dir), "l_orderkey")
    return _rounded(gamma_losses(train, test, D2, _GRID), 5, "residual_norm")


@query(f"""WITH m AS ({moments_sql(S_ROWS)}), e AS (SELECT *, ((a + d) + sqrt((a - d) * (a - d) + 4 * b * b)) / 2 AS top FROM m),
v AS (SELECT *, b / sqrt(b * b + (top - a) * (top - a)) AS y0, (top - a) / sqrt(b * b + (top - a) * (top - a)) AS y1 FROM e),
c AS (SELECT *, (y0 * u + y1 * v) / top AS z FROM v) {two_rows('y0 * z', 'y1 * z', 'c')}""")
def pcr_supplier_k1(spark, sf_dir):
    row = collect_sketch(fit_sketch(supplier_rows(spark, sf_dir), D2, "exact_ridge", 1))
    x = solve_components(gram_of(row), row.cross, 1)[:, 0]
    return spark.createDataFrame([(i, round(float(v), 6)) for i, v in enumerate(x)], "idx int, coef double")


@query(f"""WITH m AS ({moments_sql(S_ROWS)}), h AS (SELECT a, b, d, (d + 2.0) / ((a + 2.0) * (d + 2.0) - b * b) AS p, -b / ((a + 2.0) * (d + 2.0) - b * b) AS q, (a + 2.0) / ((a + 2.0) * (d + 2.0) - b * b) AS r FROM m),
k AS (SELECT *, p * a + q * b AS k11, p * b + q * d AS k12, q * a + r * b AS k21, q * b + r * d AS k22 FROM h),
z AS (SELECT *, (k11 - 1) * 0.7 + k12 * -0.3 AS z0, k21 * 0.7 + (k22 - 1) * -0.3 AS z1 FROM k)
SELECT round(a * z0 * z0 + 2 * b * z0 * z1 + d * z1 * z1, 6) AS bias_sq, round(0.25 * (k11 * k11 + 2 * k12 * k21 + k22 * k22), 6) AS variance FROM z""")
def risk_supplier_d2(spark, sf_dir):
    gram = metrics.gram_matrix(supplier_rows(spark, sf_dir), D2)
    r = risk(gram, gram, np.array([0.7, -0.3]), 0.5, 2.0)
    return spark.createDataFrame([(round(r.bias_sq, 6), round(r.variance, 6))], "bias_sq double, variance double")


_TAILS = f"m AS ({moments_sql(S_ROWS)}), t AS (SELECT a + d AS t0, ((a + d) - sqrt((a - d) * (a - d) + 4 * b * b)) / 2 AS t1 FROM m)"


@query(f"WITH {_TAILS} SELECT CAST(least(greatest(ceil(least(t0 / (4.0 * 0.5), 1 + t1 / (4.0 * 0.5), 2.0)), CASE WHEN t0 / (4.0 * 0.5) <= least(1 + t1 / (4.0 * 0.5), 2.0) THEN 1 WHEN 1 + t1 / (4.0 * 0.5) <= 2.0 THEN 2 ELSE 3 END), 2) AS BIGINT) AS ell FROM t")
def required_rows_supplier(spark, sf_dir):
    tail = bounds.tail_energy(np.linalg.eigvalsh(metrics.gram_matrix(supplier_rows(spark, sf_dir), D2)))
    return spark.createDataFrame([(bounds.required_rows(tail, 4.0, 0.5)[0],)], "ell long")


@query(f"WITH {_TAILS} SELECT round(t0 / 0.5, 5) AS plain, round(t0 / (2 * 0.5), 5) AS robust FROM t")
def required_gamma_supplier(spark, sf_dir):
    tail = bounds.tail_energy(np.linalg.eigvalsh(metrics.gram_matrix(supplier_rows(spark, sf_dir), D2)))
    return spark.createDataFrame([(round(bounds.required_gamma(tail, 1, 0.5), 5), round(bounds.required_gamma(tail, 1, 0.5, True), 5))], "plain double, robust double")


_LPX = cramer("a", "b", "d", "64.0")


@query(f"WITH m AS ({moments_sql(L_ROWS)}), x AS (SELECT {_LPX[0]} AS x0, {_LPX[1]} AS x1 FROM m) SELECT l_orderkey, l_partkey, l_suppkey, l_linenumber, round(x0 * p + x1 * q, 4) AS prediction FROM ({L_ROWS}), x")
def predict_lineitem(spark, sf_dir):
    rows = lineitem_rows(spark, sf_dir)
    scored = predict(rows, solve(fit_sketch(rows, D2, "robust_fd_ridge", 2, batch_rows=512), 64.0), D2)
    return _rounded(scored.select("l_orderkey", "l_partkey", "l_suppkey", "l_linenumber", "prediction"), 4, "prediction")


@query(f"WITH m AS ({moments_sql(L_ROWS)}), x AS (SELECT {_LPX[0]} AS x0, {_LPX[1]} AS x1 FROM m) SELECT CAST(64.0 AS DOUBLE) AS gamma, CAST(count(*) AS BIGINT) AS n, round(avg((x0 * p + x1 * q - t) * (x0 * p + x1 * q - t)), 6) AS pred_mse FROM ({L_ROWS}), x")
def prediction_error_lineitem(spark, sf_dir):
    rows = lineitem_rows(spark, sf_dir)
    return _rounded(prediction_error(rows, solve(fit_sketch(rows, D2, "exact_ridge", 1), 64.0), D2).select("gamma", "n", "pred_mse"), 6, "pred_mse")


@query(f"SELECT CAST(sum(CASE WHEN p IS NULL THEN 1 ELSE 0 END) AS BIGINT) AS n_skipped, CAST(count(p) AS BIGINT) AS n_rows, round(sum(p * p), 4) AS frob_sq FROM (SELECT CASE WHEN l_linenumber % 7 = 3 THEN NULL ELSE l_quantity / 50 END AS p FROM lineitem)")
def skip_invalid_lineitem(spark, sf_dir):
    """Rows with nulls are skipped and counted."""
    rows = lineitem_rows(spark, sf_dir).withColumn("p", F.when(F.col("l_linenumber") % 7 != 3, F.col("p")))
    return _rounded(fit_sketch(rows, RidgeSpec(["p"], "t", "k", on_invalid="skip"), "exact_ridge", 1).select("n_skipped", "n_rows", "frob_sq"), 4, "frob_sq")


# ---------------------------------------------------------------- workloads in SQL

_HOURS = "SELECT date_trunc('hour', ts) AS hour, avg(value) AS v FROM events GROUP BY 1"
_FILLED = f"""h AS ({_HOURS}), cal AS (SELECT unnest(generate_series((SELECT min(hour) FROM h), (SELECT max(hour) FROM h), INTERVAL 1 HOUR)) AS tick),
filled AS (SELECT epoch(tick) AS s, last_value(v IGNORE NULLS) OVER (ORDER BY tick ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW) AS v FROM cal LEFT JOIN h ON tick = hour)"""


@query(f"WITH {_FILLED} SELECT CAST(s AS BIGINT) AS seconds, round(v, 9) AS mean_value FROM filled")
def event_hourly_series(spark, sf_dir):
    s = wl.hourly_series(spark, sf_dir)
    return _rounded(s.select(F.unix_seconds("hour").alias("seconds"), "mean_value"), 9, "mean_value")


def _shingle_sql(series: str, order: str, value: str, d: int) -> str:
    return f"""WITH {series}, df AS (SELECT {order} AS o, {value} - lag({value}) OVER (ORDER BY {order}) AS x FROM filled),
w AS (SELECT o, list(x) OVER (ORDER BY o ROWS BETWEEN CURRENT ROW AND {d} FOLLOWING) AS run FROM df WHERE x IS NOT NULL)
SELECT CAST(o AS BIGINT) AS row_id, round(run[1], 9) AS first_diff, round(run[{d}], 9) AS last_diff, round(list_sum(run[1:{d}]), 9) AS sum_diff, round(run[{d + 1}], 9) AS target FROM w WHERE len(run) = {d + 1}"""


def _shingle_scalars(rows: DataFrame) -> DataFrame:
    total = F.aggregate("features", F.lit(0.0), lambda s, x: s + x)
    return _rounded(rows.select("row_id", F.element_at("features", 1).alias("first_diff"), F.element_at("features", -1).alias("last_diff"), total.alias("sum_diff"), "target"), 9, "first_diff", "last_diff", "sum_diff", "target")


@query(_shingle_sql(_FILLED, "s", "v", 24))
def event_shingles(spark, sf_dir):
    return _shingle_scalars(wl.workload_event_shingles(spark, sf_dir))


@query(_shingle_sql("filled AS (SELECT date_diff('day', DATE '1970-01-01', CAST(o_orderdate AS DATE)) AS s, sum(o_totalprice) / 1e6 AS v FROM orders GROUP BY 1)", "s", "v", 64))
def order_daily_shingles(spark, sf_dir):
    return _shingle_scalars(wl.workload_daily_shingles(spark, sf_dir))


@query("SELECT CASE WHEN (o_orderkey * 7919 + 13) % 100 < 80 THEN 'train' ELSE 'test' END AS part, CAST(count(*) AS BIGINT) AS n, CAST(sum(o_orderkey) AS BIGINT) AS key_sum FROM orders GROUP BY 1")
def train_test_split_orders(spark, sf_dir):
    o = load_table(spark, sf_dir, "orders", ["o_orderkey"])
    return o.groupBy(F.when(ft.split_column(F.col("o_orderkey")), "train").otherwise("test").alias("part")).agg(F.count("*").alias("n"), F.sum("o_orderkey").alias("key_sum"))


@query("SELECT p_partkey, round((p_size - (SELECT avg(p_size) FROM part)) / (SELECT stddev_pop(p_size) FROM part), 5) AS z_size, round((p_retailprice - (SELECT avg(p_retailprice) FROM part)) / (SELECT stddev_pop(p_retailprice) FROM part), 5) AS z_price FROM part")
def standardize_features_part(spark, sf_dir):
    p = load_table(spark, sf_dir, "part", ["p_partkey", "p_size", "p_retailprice"])
    return _rounded(ft.standardise(p, ["p_size", "p_retailprice"]).select("p_partkey", F.col("p_size").alias("z_size"), F.col("p_retailprice").alias("z_price")), 5, "z_size", "z_price")


_SEGMENTS = ["AUTOMOBILE", "BUILDING", "FURNITURE", "HOUSEHOLD", "MACHINERY"]


@query("SELECT CAST(i AS INTEGER) AS i, CAST(sum(CASE WHEN c_mktsegment = s THEN 1.0 ELSE 0.0 END) AS DOUBLE) AS total FROM customer, (SELECT unnest(range(5)) AS i, unnest(['AUTOMOBILE', 'BUILDING', 'FURNITURE', 'HOUSEHOLD', 'MACHINERY']) AS s) GROUP BY i")
def one_hot_segment_customer(spark, sf_dir):
    c = load_table(spark, sf_dir, "customer", ["c_mktsegment"])
    return c.select(F.posexplode(ft.one_hot("c_mktsegment", _SEGMENTS)).alias("i", "x")).groupBy("i").agg(F.sum("x").alias("total"))


@query("""WITH w AS (SELECT doc_id, unnest(regexp_extract_all(lower(text), '[a-z]+')) AS word FROM documents),
h AS (SELECT doc_id, list_sum(list_transform(range(1, length(word) + 1), lambda i: ascii(word[i]))) % 64 AS bucket FROM w)
SELECT doc_id, CAST(bucket AS BIGINT) AS bucket, CAST(count(*) AS BIGINT) AS n FROM h GROUP BY 1, 2""")
def text_hash_counts_documents(spark, sf_dir):
    """Hashed word counts with an arithmetic hash any engine repeats: sum of letters' codes."""
    docs = load_table(spark, sf_dir, "documents", ["doc_id", "text"])
    words = docs.select("doc_id", F.explode(F.regexp_extract_all(F.lower("text"), F.lit("([a-z]+)"), 1)).alias("word"))
    code = F.aggregate(F.transform(F.sequence(F.lit(1), F.length("word")), lambda i: F.ascii(F.substring("word", i, 1))), F.lit(0), lambda s, x: s + x)
    return words.groupBy("doc_id", F.pmod(code, F.lit(64)).cast("long").alias("bucket")).agg(F.count("*").alias("n"))


_WX = cramer("a", "b", "d", "16.0")
_DAYS = "SELECT CAST(epoch(date_trunc('day', ts)) AS BIGINT) AS day_s, value / 100 AS p, hour(ts) / 24.0 AS q, (user_id % 10) / 10.0 AS t FROM events"


@query(f"WITH m AS ({moments_sql(_DAYS, 'day_s')}) {two_rows(*_WX, 'm', 5, 'day_s')}")
def windowed_sketch_events(spark, sf_dir):
    """One sketch per day of event time."""
    e = load_table(spark, sf_dir, "events", ["event_id", "ts", "user_id", "value"])
    rows = e.select(F.col("event_id").alias("k"), F.col("ts").cast("timestamp").alias("ts"), (F.col("value") / 100).alias("p"), (F.hour("ts") / 24.0).alias("q"), (F.col("user_id") % 10 / 10.0).alias("t"))
    sketches = windowed_sketches(rows, D2, "fd_ridge", 2, "ts", "1 day").withColumn("day_s", F.unix_seconds("window_start"))
    return _coefs(solve(sketches, 16.0, by=["day_s"]), 5, "day_s")


# ---------------------------------------------------------------- methods without SQL

EMB = RidgeSpec("features", "target", "row_id")


def _method_on(name: str, method: str, ell: int, **options) -> None:
    def f(spark, sf_dir):
        return long_coefficients(solve(fit_sketch(wl.workload_high_rank(spark, sf_dir), EMB, method, ell, **options), wl.GAMMA["high_rank"]))

    f.__name__ = name
    query()(f)


for _name, _method, _options in (
    ("fd_ridge_embeddings_lossy", "fd_ridge", {}), ("fd_ridge_shrink_at_ell", "fd_ridge", {"shrink_at": "ell"}), ("fd_ridge_row_gram", "fd_ridge", {"svd": "row_gram"}), ("fd_ridge_batch_one", "fd_ridge", {"batch_rows": 1}), ("robust_fd_ridge_embeddings_lossy", "robust_fd_ridge", {}), ("truncated_svd_ridge_embeddings", "truncated_svd_ridge", {}), ("two_level_ridge_embeddings", "two_level_ridge", {}),
    ("sign_projection_ridge_embeddings", "sign_projection_ridge", {}), ("count_sketch_ridge_embeddings", "count_sketch_ridge", {}), ("srht_ridge_embeddings", "srht_ridge", {}), ("exact_ridge_embeddings", "exact_ridge", {}),
):
    _method_on(_name, _method, 16, **_options)


@query()
def fd_ridge_text_sparse(spark, sf_dir):
    """Sparse rows of whole texts."""
    return long_coefficients(solve(fit_sparse(wl.workload_text_hash(spark, sf_dir, 512), 512, 16), 64.0))


@query()
def leverage_scores_embeddings(spark, sf_dir):
    from .operators.leverage import leverage_scores

    rows = wl.workload_high_rank(spark, sf_dir)
    return leverage_scores(rows, fit_sketch(rows, EMB, "exact_ridge", 1), EMB, wl.GAMMA["high_rank"]).select("row_id", "leverage")


@query()
def leverage_sample_ridge_embeddings(spark, sf_dir):
    from .operators.leverage import leverage_sample_ridge

    return leverage_sample_ridge(wl.workload_high_rank(spark, sf_dir), EMB, wl.GAMMA["high_rank"], 200)


@query()
def rank_sized_projection_embeddings(spark, sf_dir):
    """A projection sized by the rank: one pass for the rank, one for the sketch."""
    rows = wl.workload_high_rank(spark, sf_dir)
    lam = np.linalg.eigvalsh(metrics.gram_matrix(rows, EMB))
    rank = int((lam > 1e-10 * lam[-1]).sum())
    return long_coefficients(solve(fit_sketch(rows, EMB, "sign_projection_ridge", rank), wl.GAMMA["high_rank"]))


@query()
def risk_embeddings(spark, sf_dir):
    """Bias, variance and their bounds for the plain and the robust sketch."""
    rows, gamma, x = wl.workload_high_rank(spark, sf_dir), wl.GAMMA["high_rank"], ft.cosine_matrix(64) @ planted(64, 32, 0)
    gram, out = metrics.gram_matrix(rows, EMB), []
    exact = risk(gram, gram, x, 2.0, gamma)
    for method in ("fd_ridge", "robust_fd_ridge"):
        approx = gram_of(collect_sketch(fit_sketch(rows, EMB, method, 16)))
        r, safe, printed = risk(gram, approx, x, 2.0, gamma), risk_factors(gram, approx, gamma), risk_factors(gram, approx, gamma, "printed")
        out.append((method, r.bias_sq, r.variance, r.bias_sq / exact.bias_sq, r.variance / exact.variance, safe[0], printed[0], safe[1]))
    return spark.createDataFrame(out, "method string, bias_sq double, variance double, bias_ratio double, variance_ratio double, bias_safe double, bias_printed double, variance_bound double")


@query()
def multi_site_sketches(spark, sf_dir):
    """Documents' sources as sites: a sketch each, and the certificate of their merge."""
    docs = load_table(spark, sf_dir, "documents", ["doc_id", "lang", "n_chars", "text"])
    rows = docs.select("lang", F.col("doc_id").alias("k"), (F.col("n_chars") / 1e4).alias("p"), (F.size(F.split("text", "\n")) / 10.0).alias("q"), F.log1p("n_chars").alias("t"))
    per = fit_sketch(rows, RidgeSpec(["p", "q"], "t", "k", ("lang",)), "fd_ridge", 1)
    ids = per.withColumn("part_id", F.pmod(F.xxhash64("lang"), F.lit(64)).cast("long"))
    return per.select("lang", "n_rows", "frob_sq", "shrink_total").unionByName(merge_sketches(ids, (), 64, 64, "fd_ridge").select(F.lit("all").alias("lang"), "n_rows", "frob_sq", "shrink_total"))


_PRIMAL_DUAL = " UNION ALL ".join(f"SELECT CAST({i} AS INTEGER) AS idx, round({x}, 6) AS primal_coef, round({x}, 6) AS dual_coef FROM m" for i, x in enumerate(cramer("a", "b", "d", "0.5")))


@query(f"WITH m AS ({moments_sql(_N_ROWS)}) {_PRIMAL_DUAL}")
def solver_forms_agree(spark, sf_dir):
    """The d x d and the n x n form, on a table of 25 rows by its nature."""
    rows = load_table(spark, sf_dir, "nation").select(F.col("n_nationkey").alias("row_id"), F.array(F.col("n_nationkey") / 25.0, F.col("n_regionkey") / 5.0).alias("features"), (F.length("n_name") / 10.0).alias("target"))
    a, b = wl.dense(rows, 1000)
    primal, dual = solve_primal(a.T @ a, a.T @ b, 0.5), solve_dual(a, b, 0.5)
    return spark.createDataFrame([(i, round(float(p), 6), round(float(q), 6)) for i, (p, q) in enumerate(zip(primal, dual, strict=True))], "idx int, primal_coef double, dual_coef double")


def entry(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Robust shrinking sketch of 16 rows on the high-rank stand-in: (idx, coef, certificate)."""
    solution = solve(fit_sketch(wl.workload_high_rank(spark, sf_dir), EMB, "robust_fd_ridge", 16), wl.GAMMA["high_rank"])
    return solution.select(F.posexplode("coefficients").alias("idx", "coef"), "certificate")

