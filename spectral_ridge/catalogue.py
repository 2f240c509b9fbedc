"""The relational operators around the methods, each as a query with its SQL."""

from __future__ import annotations

import uuid

import numpy as np
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from .operators.fit import collect_sketch, fit_sketch
from .operators.predict import dot
from .queries import D2, S_ROWS, _rounded, cramer, moments_sql, query, supplier_rows, two_rows
from .runtime import shared_dir, ship_package
from .sources.tables import SCHEMAS, load_table, read_stream
from .streaming.sketches import SketchLedger, anytime_solution, stream_sketch


def t(spark, sf_dir, name, *columns):
    return load_table(spark, sf_dir, name, list(columns) or None)


# ---------------------------------------------------------------- scans, projections, filters

@query("SELECT l_orderkey, l_linenumber, l_partkey, l_suppkey, round(l_extendedprice * (1 - l_discount), 4) AS net FROM lineitem")
def op_scan_project_lineitem(spark, sf_dir):
    li = t(spark, sf_dir, "lineitem", "l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", "l_extendedprice", "l_discount")
    return li.select("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", F.round(F.col("l_extendedprice") * (1 - F.col("l_discount")), 4).alias("net"))


@query("SELECT count(*) AS n, round(sum(l_extendedprice * l_discount), 2) AS revenue FROM lineitem WHERE l_shipdate >= TIMESTAMP '1995-01-01' AND l_shipdate < TIMESTAMP '1996-01-01' AND l_discount BETWEEN 0.03 AND 0.07 AND l_quantity < 24")
def op_filter_pushdown_lineitem(spark, sf_dir):
    li = t(spark, sf_dir, "lineitem", "l_shipdate", "l_discount", "l_quantity", "l_extendedprice")
    kept = li.where((F.col("l_shipdate") >= F.lit("1995-01-01").cast("timestamp_ntz")) & (F.col("l_shipdate") < F.lit("1996-01-01").cast("timestamp_ntz")) & F.col("l_discount").between(0.03, 0.07) & (F.col("l_quantity") < 24))
    return kept.agg(F.count("*").alias("n"), F.round(F.sum(F.col("l_extendedprice") * F.col("l_discount")), 2).alias("revenue"))


@query("SELECT CASE WHEN o_totalprice < 100000 THEN 'low' WHEN o_totalprice < 300000 THEN 'mid' ELSE 'high' END AS band, count(*) AS n FROM orders GROUP BY 1")
def op_case_when_bucket(spark, sf_dir):
    band = F.when(F.col("o_totalprice") < 100000, "low").when(F.col("o_totalprice") < 300000, "mid").otherwise("high")
    return t(spark, sf_dir, "orders", "o_totalprice").groupBy(band.alias("band")).agg(F.count("*").alias("n"))


@query("SELECT coalesce(nullif(o_orderstatus, 'P'), 'none') AS status, count(*) AS n, CAST(sum(CASE WHEN nullif(o_orderstatus, 'P') IS NOT DISTINCT FROM NULL THEN 1 ELSE 0 END) AS BIGINT) AS nulls FROM orders GROUP BY 1")
def op_null_safe_coalesce(spark, sf_dir):
    o = t(spark, sf_dir, "orders", "o_orderstatus").select(F.nullif("o_orderstatus", F.lit("P")).alias("s"))
    return o.groupBy(F.coalesce("s", F.lit("none")).alias("status")).agg(F.count("*").alias("n"), F.sum(F.col("s").eqNullSafe(F.lit(None)).cast("long")).alias("nulls"))


# ---------------------------------------------------------------- joins

_STAR = "FROM lineitem JOIN part ON l_partkey = p_partkey JOIN supplier ON l_suppkey = s_suppkey JOIN nation ON s_nationkey = n_nationkey"


@query(f"SELECT n_name, p_brand, count(*) AS n, round(sum(l_extendedprice), 2) AS total {_STAR} GROUP BY 1, 2")
def op_broadcast_join_star(spark, sf_dir):
    li = t(spark, sf_dir, "lineitem", "l_partkey", "l_suppkey", "l_extendedprice")
    p, s, n = t(spark, sf_dir, "part", "p_partkey", "p_brand"), t(spark, sf_dir, "supplier", "s_suppkey", "s_nationkey"), t(spark, sf_dir, "nation", "n_nationkey", "n_name")
    # nation has 25 rows in any scale; part and supplier are left to the optimiser's size check
    joined = li.join(p, li["l_partkey"] == p["p_partkey"]).join(s.join(F.broadcast(n), s["s_nationkey"] == n["n_nationkey"]), li["l_suppkey"] == s["s_suppkey"])
    return joined.groupBy("n_name", "p_brand").agg(F.count("*").alias("n"), F.round(F.sum("l_extendedprice"), 2).alias("total"))


_LO = "SELECT o_orderpriority, count(*) AS n, round(sum(l_quantity), 1) AS quantity FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY 1"


def _line_orders(spark, sf_dir, hint):
    li, o = t(spark, sf_dir, "lineitem", "l_orderkey", "l_quantity"), t(spark, sf_dir, "orders", "o_orderkey", "o_orderpriority")
    return li.join(o.hint(hint), li["l_orderkey"] == o["o_orderkey"]).groupBy("o_orderpriority").agg(F.count("*").alias("n"), F.round(F.sum("l_quantity"), 1).alias("quantity"))


@query(_LO)
def op_sort_merge_join(spark, sf_dir):
    return _line_orders(spark, sf_dir, "merge")


@query(_LO)
def op_shuffle_hash_join(spark, sf_dir):
    return _line_orders(spark, sf_dir, "shuffle_hash")


@query("SELECT d.lang, count(*) AS n, count(l.quality) AS labelled, CAST(coalesce(sum(l.quality), 0) AS BIGINT) AS good FROM documents d LEFT JOIN labels l ON d.doc_id = l.doc_id GROUP BY 1")
def op_left_join_labels(spark, sf_dir):
    joined = t(spark, sf_dir, "documents", "doc_id", "lang").join(t(spark, sf_dir, "labels", "doc_id", "quality"), "doc_id", "left")
    return joined.groupBy("lang").agg(F.count("*").alias("n"), F.count("quality").alias("labelled"), F.coalesce(F.sum("quality"), F.lit(0)).alias("good"))


@query("SELECT coalesce(d.doc_id, b.item_id) AS k, d.n_chars, length(b.text) AS item_chars FROM documents d FULL OUTER JOIN benchmark b ON d.doc_id = b.item_id")
def op_full_outer_join(spark, sf_dir):
    """Two tables whose keys overlap in part."""
    d = t(spark, sf_dir, "documents", "doc_id", "n_chars")
    b = t(spark, sf_dir, "benchmark", "item_id", "text").select("item_id", F.length("text").cast("long").alias("item_chars"))
    return d.join(b, F.col("doc_id") == F.col("item_id"), "full").select(F.coalesce("doc_id", "item_id").alias("k"), "n_chars", "item_chars")


@query("SELECT doc_id, n_chars FROM documents WHERE doc_id IN (SELECT doc_id FROM labels)")
def op_semi_join(spark, sf_dir):
    return t(spark, sf_dir, "documents", "doc_id", "n_chars").join(t(spark, sf_dir, "labels", "doc_id"), "doc_id", "left_semi")


@query("SELECT doc_id, n_chars FROM documents WHERE doc_id NOT IN (SELECT doc_id FROM labels)")
def op_anti_join(spark, sf_dir):
    return t(spark, sf_dir, "documents", "doc_id", "n_chars").join(t(spark, sf_dir, "labels", "doc_id"), "doc_id", "left_anti")


@query("SELECT gamma, count(*) AS n, round(sum(1 / (gamma + s_acctbal * s_acctbal / 1e8)), 5) AS total FROM supplier, (SELECT CAST(unnest([1, 2, 4, 8]) AS DOUBLE) AS gamma) GROUP BY 1")
def op_cross_join_gamma_grid(spark, sf_dir):
    grid = spark.range(4).select(F.pow(F.lit(2.0), F.col("id")).alias("gamma"))
    s = t(spark, sf_dir, "supplier", "s_acctbal").crossJoin(F.broadcast(grid))
    return s.groupBy("gamma").agg(F.count("*").alias("n"), F.round(F.sum(1 / (F.col("gamma") + F.col("s_acctbal") * F.col("s_acctbal") / 1e8)), 5).alias("total"))


_RANGE = "SELECT p.event_id, count(v.event_id) AS views FROM events p LEFT JOIN events v ON v.user_id = p.user_id AND v.event_type = 'view' AND v.ts < p.ts AND v.ts >= p.ts - INTERVAL 6 HOUR WHERE p.event_type = 'purchase' GROUP BY 1"


@query(_RANGE)
def op_range_join_events(spark, sf_dir):
    """Views of a user in the six hours before a purchase: equal on user and time bin, then exact."""
    e = t(spark, sf_dir, "events", "event_id", "ts", "user_id", "event_type").withColumn("s", F.unix_micros(F.col("ts").cast("timestamp")))
    width = 6 * 3600 * 1_000_000
    p = e.where("event_type = 'purchase'").select("event_id", "user_id", "s").withColumn("bin", F.explode(F.array(F.floor(F.col("s") / width), F.floor(F.col("s") / width) - 1)))
    v = e.where("event_type = 'view'").select(F.col("user_id").alias("u"), F.col("s").alias("vs"), F.floor(F.col("s") / width).alias("vbin"), F.col("event_id").alias("view_id"))
    near = (F.col("user_id") == F.col("u")) & (F.col("bin") == F.col("vbin")) & (F.col("vs") < F.col("s")) & (F.col("vs") >= F.col("s") - width)
    return p.join(v, near, "left").groupBy("event_id").agg(F.count("view_id").alias("views"))


@query("SELECT a.event_id AS left_id, b.event_id AS right_id FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_id < b.event_id AND b.ts - a.ts <= INTERVAL 5 MINUTE")
def op_interval_join_events(spark, sf_dir):
    e = t(spark, sf_dir, "events", "event_id", "ts", "user_id").withColumn("s", F.unix_micros(F.col("ts").cast("timestamp")))
    width = 300 * 1_000_000
    a = e.select(F.col("event_id").alias("left_id"), F.col("user_id").alias("u"), F.col("s").alias("sa"), F.explode(F.array(F.floor(F.col("s") / width), F.floor(F.col("s") / width) + 1)).alias("bin"))
    b = e.withColumn("bbin", F.floor(F.col("s") / width))
    near = (F.col("u") == F.col("user_id")) & (F.col("bin") == F.col("bbin")) & (F.col("left_id") < F.col("event_id")) & (F.col("s") - F.col("sa") <= width)
    return a.join(b, near).select("left_id", F.col("event_id").alias("right_id"))


@query("""SELECT p.event_id, max(v.event_id) AS last_view FROM events p LEFT JOIN events v ON v.user_id = p.user_id AND v.event_type = 'view' AND v.event_id < p.event_id WHERE p.event_type = 'purchase' GROUP BY 1""")
def op_asof_join_events(spark, sf_dir):
    """Each purchase with its user's last view before it: one window, no pair of rows is formed."""
    e = t(spark, sf_dir, "events", "event_id", "user_id", "event_type")
    w = W.partitionBy("user_id").orderBy("event_id").rowsBetween(W.unboundedPreceding, -1)
    last = F.last(F.when(F.col("event_type") == "view", F.col("event_id")), ignorenulls=True).over(w)
    return e.withColumn("last_view", last).where("event_type = 'purchase'").select("event_id", "last_view")


@query("SELECT vec_id, CAST(i AS INTEGER) AS i, round(CAST(x AS DOUBLE), 6) AS x FROM (SELECT vec_id, unnest(range(64)) AS i, unnest(embedding) AS x FROM embeddings) WHERE i < 4")
def op_lateral_explode_embeddings(spark, sf_dir):
    e = t(spark, sf_dir, "embeddings", "vec_id", "embedding")
    return e.select("vec_id", F.posexplode("embedding").alias("i", "x")).where("i < 4").select("vec_id", "i", F.round(F.col("x").cast("double"), 6).alias("x"))


# ---------------------------------------------------------------- aggregations

@query("SELECT l_returnflag, round(sum(l_quantity), 2) AS s, round(avg(l_discount), 6) AS a, round(var_samp(l_quantity), 5) AS v, round(covar_samp(l_quantity, l_extendedprice / 1e5), 5) AS c, round(corr(l_quantity, l_extendedprice), 6) AS r, round(regr_slope(l_extendedprice / 1e5, l_quantity), 7) AS slope, round(regr_r2(l_extendedprice / 1e5, l_quantity), 6) AS r2 FROM lineitem GROUP BY 1")
def op_group_moments(spark, sf_dir):
    li = t(spark, sf_dir, "lineitem", "l_returnflag", "l_quantity", "l_discount", "l_extendedprice").withColumn("y", F.col("l_extendedprice") / 1e5)
    return li.groupBy("l_returnflag").agg(F.round(F.sum("l_quantity"), 2).alias("s"), F.round(F.avg("l_discount"), 6).alias("a"), F.round(F.var_samp("l_quantity"), 5).alias("v"), F.round(F.covar_samp("l_quantity", "y"), 5).alias("c"), F.round(F.corr("l_quantity", "l_extendedprice"), 6).alias("r"), F.round(F.regr_slope("y", "l_quantity"), 7).alias("slope"), F.round(F.regr_r2("y", "l_quantity"), 6).alias("r2"))


@query("SELECT event_type, count(DISTINCT user_id) AS users FROM events GROUP BY 1")
def op_distinct_agg(spark, sf_dir):
    return t(spark, sf_dir, "events", "event_type", "user_id").groupBy("event_type").agg(F.countDistinct("user_id").alias("users"))


@query("SELECT event_type, count(DISTINCT user_id) AS users, true AS near FROM events GROUP BY 1")
def op_approx_distinct(spark, sf_dir):
    """The exact count, and whether the approximate one is within four of its standard errors."""
    near = F.abs(F.approx_count_distinct("user_id", 0.02) - F.countDistinct("user_id")) <= 0.08 * F.countDistinct("user_id")
    return t(spark, sf_dir, "events", "event_type", "user_id").groupBy("event_type").agg(F.countDistinct("user_id").alias("users"), near.alias("near"))


_CNR = "FROM customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey"


def _nations(spark, sf_dir):
    c, n, r = t(spark, sf_dir, "customer", "c_nationkey", "c_acctbal"), t(spark, sf_dir, "nation"), t(spark, sf_dir, "region")
    return c.join(F.broadcast(n), c["c_nationkey"] == n["n_nationkey"]).join(F.broadcast(r), n["n_regionkey"] == r["r_regionkey"])


@query(f"SELECT r_name, n_name, count(*) AS n, round(sum(c_acctbal * c_acctbal / 1e8), 5) AS g FROM customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY ROLLUP (r_name, n_name)")
def op_rollup_region_nation(spark, sf_dir):
    """Moments add up, so a roll-up of sums holds a model for each level."""
    return _nations(spark, sf_dir).rollup("r_name", "n_name").agg(F.count("*").alias("n"), F.round(F.sum(F.col("c_acctbal") * F.col("c_acctbal") / 1e8), 5).alias("g"))


@query("SELECT l_returnflag, l_linestatus, count(*) AS n FROM lineitem GROUP BY CUBE (l_returnflag, l_linestatus)")
def op_cube_flag_status(spark, sf_dir):
    return t(spark, sf_dir, "lineitem", "l_returnflag", "l_linestatus").cube("l_returnflag", "l_linestatus").agg(F.count("*").alias("n"))


@query("SELECT o_orderstatus, o_orderpriority, count(*) AS n FROM orders GROUP BY GROUPING SETS ((o_orderstatus), (o_orderpriority), ())")
def op_grouping_sets(spark, sf_dir):
    o = t(spark, sf_dir, "orders", "o_orderstatus", "o_orderpriority")
    s, p = F.col("o_orderstatus"), F.col("o_orderpriority")
    return o.groupingSets([[s], [p], []], s, p).agg(F.count("*").alias("n"))


_TYPES = ["click", "view", "purchase", "signup", "logout"]


@query("SELECT user_id % 10 AS slot, " + ", ".join(f"CAST(count(*) FILTER (WHERE event_type = '{k}') AS BIGINT) AS {k}" for k in _TYPES) + " FROM events GROUP BY 1")
def op_pivot_event_type(spark, sf_dir):
    e = t(spark, sf_dir, "events", "user_id", "event_type").select((F.col("user_id") % 10).alias("slot"), "event_type")
    return e.groupBy("slot").pivot("event_type", _TYPES).agg(F.count(F.lit(1))).na.fill(0)


@query("SELECT o_orderpriority, max_by(o_orderkey, o_totalprice) AS top_order, min_by(o_orderkey, o_totalprice) AS low_order FROM orders GROUP BY 1")
def op_max_by(spark, sf_dir):
    o = t(spark, sf_dir, "orders", "o_orderpriority", "o_orderkey", "o_totalprice")
    return o.groupBy("o_orderpriority").agg(F.max_by("o_orderkey", "o_totalprice").alias("top_order"), F.min_by("o_orderkey", "o_totalprice").alias("low_order"))


@query("SELECT o_orderpriority, round(quantile_cont(o_totalprice, 0.5), 3) AS median, round(quantile_cont(o_totalprice, 0.9), 3) AS p90 FROM orders GROUP BY 1")
def op_percentile(spark, sf_dir):
    o = t(spark, sf_dir, "orders", "o_orderpriority", "o_totalprice")
    return o.groupBy("o_orderpriority").agg(F.round(F.percentile("o_totalprice", 0.5), 3).alias("median"), F.round(F.percentile("o_totalprice", 0.9), 3).alias("p90"))


# ---------------------------------------------------------------- windows, sort, sets

@query("SELECT c_custkey, rank() OVER w AS r, dense_rank() OVER w AS d, row_number() OVER (PARTITION BY c_nationkey ORDER BY c_acctbal DESC, c_custkey) AS n FROM customer WINDOW w AS (PARTITION BY c_nationkey ORDER BY c_acctbal DESC)")
def op_window_rank(spark, sf_dir):
    w = W.partitionBy("c_nationkey").orderBy(F.desc("c_acctbal"))
    return t(spark, sf_dir, "customer", "c_custkey", "c_nationkey", "c_acctbal").select("c_custkey", F.rank().over(w).alias("r"), F.dense_rank().over(w).alias("d"), F.row_number().over(w.orderBy(F.desc("c_acctbal"), "c_custkey")).alias("n"))


@query("SELECT c_custkey, ntile(4) OVER (PARTITION BY c_nationkey ORDER BY c_acctbal, c_custkey) AS quarter, round(percent_rank() OVER (PARTITION BY c_nationkey ORDER BY c_acctbal, c_custkey), 6) AS pr FROM customer")
def op_window_ntile(spark, sf_dir):
    w = W.partitionBy("c_nationkey").orderBy("c_acctbal", "c_custkey")
    return t(spark, sf_dir, "customer", "c_custkey", "c_nationkey", "c_acctbal").select("c_custkey", F.ntile(4).over(w).alias("quarter"), F.round(F.percent_rank().over(w), 6).alias("pr"))


@query("SELECT event_id, round(value - lag(value) OVER (PARTITION BY user_id ORDER BY event_id), 4) AS diff, round(lead(value) OVER (PARTITION BY user_id ORDER BY event_id), 4) AS ahead FROM events")
def op_window_lag_diff(spark, sf_dir):
    w = W.partitionBy("user_id").orderBy("event_id")
    return t(spark, sf_dir, "events", "event_id", "user_id", "value").select("event_id", F.round(F.col("value") - F.lag("value").over(w), 4).alias("diff"), F.round(F.lead("value").over(w), 4).alias("ahead"))


@query("SELECT event_id, round(sum(value) OVER (PARTITION BY user_id ORDER BY event_id ROWS UNBOUNDED PRECEDING), 4) AS running FROM events")
def op_window_running_sum(spark, sf_dir):
    w = W.partitionBy("user_id").orderBy("event_id").rowsBetween(W.unboundedPreceding, W.currentRow)
    return t(spark, sf_dir, "events", "event_id", "user_id", "value").select("event_id", F.round(F.sum("value").over(w), 4).alias("running"))


@query("SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY epoch_us(ts) RANGE BETWEEN 86400000000 PRECEDING AND CURRENT ROW) AS day_events FROM events")
def op_window_range_frame(spark, sf_dir):
    e = t(spark, sf_dir, "events", "event_id", "ts", "user_id").withColumn("s", F.unix_micros(F.col("ts").cast("timestamp")))
    w = W.partitionBy("user_id").orderBy("s").rangeBetween(-86_400_000_000, 0)
    return e.select("event_id", F.count("*").over(w).alias("day_events"))


@query("SELECT l_orderkey, l_partkey, l_suppkey, l_linenumber, l_extendedprice FROM lineitem ORDER BY l_extendedprice DESC, l_orderkey, l_linenumber, l_partkey LIMIT 20")
def op_top_k(spark, sf_dir):
    li = t(spark, sf_dir, "lineitem", "l_orderkey", "l_partkey", "l_suppkey", "l_linenumber", "l_extendedprice")
    return li.orderBy(F.desc("l_extendedprice"), "l_orderkey", "l_linenumber", "l_partkey").limit(20)


@query("SELECT o_orderpriority, o_orderkey, o_totalprice FROM (SELECT *, row_number() OVER (PARTITION BY o_orderpriority ORDER BY o_totalprice DESC, o_orderkey) AS k FROM orders) WHERE k <= 3")
def op_top_k_per_group(spark, sf_dir):
    o = t(spark, sf_dir, "orders", "o_orderpriority", "o_orderkey", "o_totalprice")
    k = F.row_number().over(W.partitionBy("o_orderpriority").orderBy(F.desc("o_totalprice"), "o_orderkey"))
    return o.withColumn("k", k).where("k <= 3").select("o_orderpriority", "o_orderkey", "o_totalprice")


@query("SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice, o_orderkey LIMIT 10 OFFSET 25")
def op_limit_offset(spark, sf_dir):
    return t(spark, sf_dir, "orders", "o_orderkey", "o_totalprice").orderBy("o_totalprice", "o_orderkey").offset(25).limit(10)


@query("SELECT c_nationkey AS k FROM customer UNION ALL SELECT s_nationkey FROM supplier")
def op_union(spark, sf_dir):
    return t(spark, sf_dir, "customer", "c_nationkey").select(F.col("c_nationkey").alias("k")).unionByName(t(spark, sf_dir, "supplier", "s_nationkey").select(F.col("s_nationkey").alias("k")))


@query("SELECT c_nationkey AS k FROM customer INTERSECT SELECT s_nationkey FROM supplier")
def op_intersect(spark, sf_dir):
    return t(spark, sf_dir, "customer", "c_nationkey").select(F.col("c_nationkey").alias("k")).intersect(t(spark, sf_dir, "supplier", "s_nationkey"))


@query("SELECT c_nationkey AS k FROM customer EXCEPT ALL SELECT s_nationkey FROM supplier")
def op_except_all(spark, sf_dir):
    return t(spark, sf_dir, "customer", "c_nationkey").select(F.col("c_nationkey").alias("k")).exceptAll(t(spark, sf_dir, "supplier", "s_nationkey"))


@query("SELECT DISTINCT o_custkey, o_orderstatus FROM orders")
def op_dedup(spark, sf_dir):
    return t(spark, sf_dir, "orders", "o_custkey", "o_orderstatus").dropDuplicates()


# ---------------------------------------------------------------- scalar functions

@query("SELECT doc_id, length(text) AS n, upper(lang) AS lang_up, substr(text, 1, 10) AS head, CAST(len(string_split(text, chr(10))) AS INTEGER) AS n_lines, md5(text) AS code FROM documents")
def op_string_functions(spark, sf_dir):
    return t(spark, sf_dir, "documents", "doc_id", "text", "lang").select("doc_id", F.char_length("text").cast("long").alias("n"), F.upper("lang").alias("lang_up"), F.substring("text", 1, 10).alias("head"), F.size(F.split("text", "\n")).alias("n_lines"), F.md5(F.col("text").cast("binary")).alias("code"))


@query("SELECT page_id, len(regexp_extract_all(html, '<[a-z0-9]+')) AS tags, regexp_matches(html, '<script') AS scripted FROM pages")
def op_regexp_tokens(spark, sf_dir):
    return t(spark, sf_dir, "pages", "page_id", "html").select("page_id", F.regexp_count("html", F.lit("<[a-z0-9]+")).cast("long").alias("tags"), F.col("html").rlike("<script").alias("scripted"))


@query("SELECT o_orderkey, CAST(year(o_orderdate) AS INTEGER) AS y, CAST(month(o_orderdate) AS INTEGER) AS m, CAST(dayofweek(o_orderdate) + 1 AS INTEGER) AS dow, CAST(date_diff('day', DATE '1992-01-01', CAST(o_orderdate AS DATE)) AS INTEGER) AS days FROM orders")
def op_date_functions(spark, sf_dir):
    return t(spark, sf_dir, "orders", "o_orderkey", "o_orderdate").select("o_orderkey", F.year("o_orderdate").alias("y"), F.month("o_orderdate").alias("m"), F.dayofweek("o_orderdate").alias("dow"), F.datediff(F.to_date("o_orderdate"), F.lit("1992-01-01").cast("date")).alias("days"))


@query("SELECT CAST(epoch(d) AS BIGINT) AS day_s, CAST(coalesce(n, 0) AS BIGINT) AS n FROM (SELECT unnest(generate_series(TIMESTAMP '2024-01-01', TIMESTAMP '2024-01-31', INTERVAL 1 DAY)) AS d) LEFT JOIN (SELECT date_trunc('day', ts) AS e, count(*) AS n FROM events GROUP BY 1) ON d = e")
def op_sequence_calendar(spark, sf_dir):
    days = spark.range(1).select(F.explode(F.expr("sequence(timestamp'2024-01-01', timestamp'2024-01-31', interval 1 day)")).alias("d"))
    e = t(spark, sf_dir, "events", "ts").groupBy(F.date_trunc("day", F.col("ts").cast("timestamp")).alias("e")).agg(F.count("*").alias("n"))
    return days.join(e, F.col("d") == F.col("e"), "left").select(F.unix_seconds("d").alias("day_s"), F.coalesce("n", F.lit(0)).alias("n"))


@query("SELECT l_linenumber, round(sum(sqrt(l_quantity)), 4) AS a, round(sum(ln(1 + l_extendedprice)), 4) AS b, round(sum(pow(l_discount, 2)), 5) AS c, round(sum(abs(l_tax - 0.04)), 5) AS d, round(max(greatest(l_discount, l_tax)), 5) AS e FROM lineitem GROUP BY 1")
def op_math_functions(spark, sf_dir):
    li = t(spark, sf_dir, "lineitem", "l_linenumber", "l_quantity", "l_extendedprice", "l_discount", "l_tax")
    return li.groupBy("l_linenumber").agg(F.round(F.sum(F.sqrt("l_quantity")), 4).alias("a"), F.round(F.sum(F.log1p("l_extendedprice")), 4).alias("b"), F.round(F.sum(F.pow("l_discount", F.lit(2))), 5).alias("c"), F.round(F.sum(F.abs(F.col("l_tax") - 0.04)), 5).alias("d"), F.round(F.max(F.greatest("l_discount", "l_tax")), 5).alias("e"))


@query("SELECT a.vec_id, round(list_sum(list_transform(range(1, 65), lambda i: CAST(a.embedding[i] AS DOUBLE) * CAST(b.embedding[i] AS DOUBLE))), 6) AS similarity FROM embeddings a, embeddings b WHERE b.vec_id = 0")
def op_array_dot(spark, sf_dir):
    e = t(spark, sf_dir, "embeddings", "vec_id", "embedding").select("vec_id", F.col("embedding").cast("array<double>").alias("x"))
    probe = e.where("vec_id = 0").limit(1).select(F.col("x").alias("y"))
    return e.crossJoin(F.broadcast(probe)).select("vec_id", F.round(dot("x", "y"), 6).alias("similarity"))


@query("SELECT vec_id, CAST(len(list_filter(embedding, lambda x: x > 0)) AS INTEGER) AS positive, round(list_sum(list_transform(embedding, lambda x: abs(CAST(x AS DOUBLE)))), 6) AS l1 FROM embeddings")
def op_array_transform(spark, sf_dir):
    e = t(spark, sf_dir, "embeddings", "vec_id", "embedding")
    l1 = F.aggregate(F.transform("embedding", lambda x: F.abs(x.cast("double"))), F.lit(0.0), lambda s, x: s + x)
    return e.select("vec_id", F.size(F.filter("embedding", lambda x: x > 0)).alias("positive"), F.round(l1, 6).alias("l1"))


@query("SELECT vec_id, round(sqrt(list_sum(list_transform(embedding, lambda x: CAST(x AS DOUBLE) * CAST(x AS DOUBLE)))), 5) AS norm, round(CAST(list_max(embedding) AS DOUBLE), 6) AS top FROM embeddings")
def op_array_aggregate(spark, sf_dir):
    e = t(spark, sf_dir, "embeddings", "vec_id", "embedding")
    square = F.aggregate("embedding", F.lit(0.0), lambda s, x: s + x.cast("double") * x.cast("double"))
    return e.select("vec_id", F.round(F.sqrt(square), 5).alias("norm"), F.round(F.array_max("embedding").cast("double"), 6).alias("top"))


@query("SELECT conv_id, turn, role, CAST(len(list_distinct(list_filter(string_split(lower(text), ' '), lambda x: x <> ''))) AS INTEGER) AS kinds FROM conversations")
def op_map_functions(spark, sf_dir):
    c = t(spark, sf_dir, "conversations")
    words = F.filter(F.split(F.lower("text"), " "), lambda x: x != "")
    kinds = F.map_from_entries(F.transform(F.array_distinct(words), lambda x: F.struct(x, F.lit(1))))
    return c.select("conv_id", "turn", "role", F.size(F.map_keys(kinds)).alias("kinds"))


@query("SELECT CAST(json_extract_string(props, '$.k') AS INTEGER) AS k, count(*) AS n FROM events GROUP BY 1")
def op_json_props(spark, sf_dir):
    return t(spark, sf_dir, "events", "props").select(F.from_json("props", "k int")["k"].alias("k")).groupBy("k").agg(F.count("*").alias("n"))


# ---------------------------------------------------------------- time windows, streams

@query("SELECT CAST(epoch(time_bucket(INTERVAL 6 HOUR, ts, TIMESTAMP '1970-01-01')) AS BIGINT) AS start_s, event_type, count(*) AS n FROM events GROUP BY 1, 2")
def op_tumbling(spark, sf_dir):
    e = t(spark, sf_dir, "events", "ts", "event_type").withColumn("ts", F.col("ts").cast("timestamp"))
    return e.groupBy(F.window("ts", "6 hours").alias("w"), "event_type").agg(F.count("*").alias("n")).select(F.unix_seconds("w.start").alias("start_s"), "event_type", "n")


@query("SELECT start_s, count(*) AS n FROM (SELECT CAST(unnest([epoch(time_bucket(INTERVAL 6 HOUR, ts, TIMESTAMP '1970-01-01')), epoch(time_bucket(INTERVAL 6 HOUR, ts, TIMESTAMP '1970-01-01')) - 21600]) AS BIGINT) AS start_s FROM events) GROUP BY 1")
def op_sliding(spark, sf_dir):
    e = t(spark, sf_dir, "events", "ts").withColumn("ts", F.col("ts").cast("timestamp"))
    return e.groupBy(F.window("ts", "12 hours", "6 hours").alias("w")).agg(F.count("*").alias("n")).select(F.unix_seconds("w.start").alias("start_s"), "n")


@query("""WITH g AS (SELECT user_id, ts, CASE WHEN ts - lag(ts) OVER w < INTERVAL 2 HOUR THEN 0 ELSE 1 END AS fresh FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)),
s AS (SELECT user_id, ts, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS k FROM g) SELECT user_id, CAST(epoch_us(min(ts)) AS BIGINT) AS start_us, count(*) AS n FROM s GROUP BY user_id, k""")
def op_session_window(spark, sf_dir):
    e = t(spark, sf_dir, "events", "user_id", "ts").withColumn("ts", F.col("ts").cast("timestamp"))
    return e.groupBy("user_id", F.session_window("ts", "2 hours").alias("w")).agg(F.count("*").alias("n")).select("user_id", F.unix_micros("w.start").alias("start_us"), "n")


@query("SELECT start_s, n FROM (SELECT CAST(epoch(date_trunc('hour', ts)) AS BIGINT) AS start_s, count(*) AS n FROM events GROUP BY 1) WHERE start_s + 3600 <= (SELECT epoch_ms(max(ts)) / 1000.0 - 3600 FROM events)")
def op_stream_watermark_counts(spark, sf_dir):
    """Hourly counts as a stream with a watermark, run to the end of the table into files: the hours
    that the watermark has closed."""
    stream = read_stream(spark, sf_dir, schema=SCHEMAS["events"], pathGlobFilter="events.parquet")
    base = f"{shared_dir(spark)}/counts-{uuid.uuid4().hex}"
    counts = stream.withWatermark("ts", "1 hour").groupBy(F.window("ts", "1 hour")).agg(F.count("*").alias("n")).select(F.unix_seconds("window.start").alias("start_s"), "n")
    writer = counts.writeStream.outputMode("append").format("parquet").option("path", f"{base}/out").option("checkpointLocation", f"{base}/state")
    writer.trigger(availableNow=True).start().awaitTermination()
    return spark.read.schema(counts.schema).parquet(f"{base}/out")


_E_ROWS = "SELECT value / 100 AS p, hour(ts) / 24.0 AS q FROM events"


@query(f"SELECT CAST(count(*) AS BIGINT) AS n_rows, round(sum(p * p + q * q), 4) AS frob_sq, CAST(2 AS INTEGER) AS rank FROM ({_E_ROWS})")
def op_stream_sketch(spark, sf_dir):
    """A global sketch of the event stream through the ledger: (n_rows, frob_sq, rank)."""
    ship_package(spark)
    stream = read_stream(spark, sf_dir, schema=SCHEMAS["events"], pathGlobFilter="events.parquet")
    rows = stream.select(F.col("event_id").alias("k"), (F.col("value") / 100).alias("p"), (F.hour("ts") / 24.0).alias("q"), (F.col("user_id") % 10 / 10.0).alias("t"))
    base = f"{shared_dir(spark)}/ledger-{uuid.uuid4().hex}"
    ledger = SketchLedger(spark, f"{base}/sketch")
    stream_sketch(rows, D2, "fd_ridge", 2, ledger, f"{base}/checkpoint").awaitTermination()
    return _rounded(ledger.current().select("n_rows", "frob_sq", "rank"), 4, "frob_sq")


# ---------------------------------------------------------------- functions

@query("SELECT vec_id, round(sqrt(list_sum(list_transform(embedding, lambda x: CAST(x AS DOUBLE) * CAST(x AS DOUBLE)))), 5) AS norm FROM embeddings")
def op_udf_norm(spark, sf_dir):
    from .functions.udfs import norm_udf

    ship_package(spark)
    e = t(spark, sf_dir, "embeddings", "vec_id", "embedding")
    return e.select("vec_id", F.round(norm_udf()(F.col("embedding").cast("array<double>")), 5).alias("norm"))


@query(f"WITH m AS ({moments_sql(S_ROWS)}) {two_rows(*cramer('a', 'b', 'd', '2.0'), 'm', 6)}")
def op_udaf_sketch(spark, sf_dir):
    """A sketch as a grouped aggregate, then ridge from its Gram matrix."""
    from .functions.udfs import gram_udaf

    ship_package(spark)
    g = supplier_rows(spark, sf_dir).agg(gram_udaf()("p", "q", "t").alias("g"))
    parts = g.select(*[F.col("g")[i].alias(n) for i, n in enumerate(("a", "b", "d", "u", "v"))])
    x0, x1 = (F.expr(e) for e in cramer("a", "b", "d", "2.0"))
    return _rounded(parts.select(F.posexplode(F.array(x0, x1)).alias("idx", "coef")), 6, "coef")


@query(f"SELECT CAST(count(*) AS BIGINT) AS n, round(sum(p * p + q * q), 5) AS frob_sq FROM ({S_ROWS})")
def op_udtf_rows(spark, sf_dir):
    """A sketch's rows through a table function: their squared norm is the data's at full rank."""
    from .functions.udfs import register

    register(spark)
    sketch = fit_sketch(supplier_rows(spark, sf_dir), D2, "fd_ridge", 2)
    name = f"sketches_{uuid.uuid4().hex}"
    sketch.createOrReplaceTempView(name)
    rows = spark.sql(f"SELECT s.n_rows AS n, r.value FROM {name} s, LATERAL sketch_rows(s.sigma, s.basis, s.n_features) r")
    return rows.groupBy("n").agg(F.round(F.sum(F.col("value") * F.col("value")), 5).alias("frob_sq"))


@query("""WITH r AS (SELECT l_linenumber, CAST(count(*) AS DOUBLE) AS lo, sum(l_quantity * l_quantity) AS hi FROM lineitem GROUP BY l_linenumber HAVING sum(l_quantity * l_quantity) > 0)
SELECT l_linenumber, CAST(i AS INTEGER) AS i, round(lo * pow(hi / lo, i / 5.0), 3) AS gamma FROM r, range(6) t(i)""")
def op_udtf_gamma_grid(spark, sf_dir):
    """A grid of penalties for each line number, from its number of rows to its squared quantities."""
    from .functions.udfs import register

    register(spark)
    rows = t(spark, sf_dir, "lineitem", "l_linenumber", "l_quantity")
    name = f"ranges_{uuid.uuid4().hex}"
    ranges = rows.groupBy("l_linenumber").agg(F.count("*").cast("double").alias("lo"), F.sum(F.col("l_quantity") * F.col("l_quantity")).alias("hi"))
    ranges.where("hi > 0").createOrReplaceTempView(name)
    grid = spark.sql(f"SELECT r.l_linenumber, r.lo <= r.hi AS rising, g.gamma FROM {name} r, LATERAL gamma_grid(r.lo, r.hi, 6) g")
    upward = F.when(F.col("rising"), F.col("gamma")).otherwise(-F.col("gamma"))
    at = F.row_number().over(W.partitionBy("l_linenumber").orderBy(upward)) - 1
    return grid.select("l_linenumber", at.alias("i"), F.round("gamma", 3).alias("gamma"))


@query("SELECT n_nationkey, n_name, n_regionkey FROM nation")
def op_roundtrip_csv_json_orc(spark, sf_dir):
    """A table through three formats; rows that come back from all of them."""
    from .sources.tables import read_rows

    base, n = f"{shared_dir(spark)}/round-{uuid.uuid4().hex}", t(spark, sf_dir, "nation")
    parts = []
    for kind, options in (("csv", {"header": "true"}), ("json", {}), ("orc", {})):
        n.write.format(kind).options(**options).save(f"{base}/{kind}")
        parts.append(read_rows(spark, f"{base}/{kind}", kind, SCHEMAS["nation"], **options))
    return parts[0].intersect(parts[1]).intersect(parts[2])


_A_ROWS = "SELECT s_suppkey % 4 AS part, * FROM (SELECT s_suppkey, s_acctbal / 1e4 AS p, s_nationkey / 25.0 AS q, s_suppkey / 100.0 AS t FROM supplier)"
_UPTO = f"SELECT CAST(b AS BIGINT) AS batch, p, q, t FROM ({_A_ROWS}), (SELECT unnest([0, 1, 2, 3]) AS b) WHERE part <= b"


@query(f"WITH m AS ({moments_sql(_UPTO, 'batch')}), n AS (SELECT CAST(b AS BIGINT) AS batch, count(*) AS n_rows FROM ({_A_ROWS}), (SELECT unnest([0, 1, 2, 3]) AS b) WHERE part <= b GROUP BY 1) SELECT batch, n_rows, idx, coef, CAST(0.0 AS DOUBLE) AS certificate FROM ({two_rows(*cramer('a', 'b', 'd', '2.0'), 'm', 5, 'batch')}) JOIN n USING (batch)")
def op_anytime_solution(spark, sf_dir):
    """Coefficients after every micro-batch of a stream of four files: what was read up to then, its
    solution and its certificate."""
    ship_package(spark)
    base = f"{shared_dir(spark)}/anytime-{uuid.uuid4().hex}"
    rows = supplier_rows(spark, sf_dir).withColumn("k", F.col("k").cast("long"))
    for part in range(4):  # the arrivals: one file after the other
        rows.where(F.pmod("k", F.lit(4)) == part).coalesce(1).write.mode("append").parquet(f"{base}/in")
    ledger, answers = SketchLedger(spark, f"{base}/sketch"), []

    def answer(batch_id: int, _) -> None:
        found = anytime_solution(ledger, 2.0).select(F.lit(batch_id).cast("long").alias("batch"), "n_rows", F.posexplode("coefficients").alias("idx", "coef"), "certificate")
        answers.extend(found.collect())

    stream = read_stream(spark, f"{base}/in", schema="k long, p double, q double, t double", maxFilesPerTrigger=1, recursiveFileLookup=True)
    stream_sketch(stream, D2, "fd_ridge", 2, ledger, f"{base}/checkpoint", answer).awaitTermination()
    out = spark.createDataFrame(answers, "batch long, n_rows long, idx int, coef double, certificate double")
    return _rounded(out, 5, "coef", "certificate")
