"""Registered measures, bounds and variants in two dimensions, each with its SQL.

Over two features a Gram matrix is three numbers, so its eigenvalues, inverse and norm are closed
forms; a sketch of one row is replayed row by row by a recursive query (``queries.replay_sql``).
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import functions as F

from .operators import features as ft
from .operators import relational as rel
from .operators.design import RidgeSpec
from .operators.fit import SketchPlan, collect_sketch, fit_many, fit_sketch, merge_sketches
from .operators.leverage import leverage_scores
from .operators.predict import prediction_error
from .operators.solve import coefficients, effective_penalty, gram_of, long_coefficients, solve, solve_pcr
from .plans import bounds, metrics
from .plans.gamma import gamma_losses
from .plans.risk import risk, risk_factors
from .queries import _EV, _EVS, _GRID, _LOSS, _O_ROWS, D2, L_ROWS, S_ROWS, _coefs, _event_signs, _rounded, cramer, exact_sql, lineitem_rows, lossy, lossy_sql, moments_sql, query, replay_sql, supplier_rows, two_rows
from .sources.tables import load_table
from .streaming.sketches import windowed_sketches


def _one(spark, names: str, *values):
    """A one-row table of rounded numbers."""
    row = tuple(round(float(v), 5) + 0.0 for v in values)
    return spark.createDataFrame([row], ", ".join(f"{n} double" for n in names.split()))


def _eigen(x: str, y: str, z: str) -> tuple[str, str]:
    """Larger and smaller eigenvalue of [[x, y], [y, z]] as SQL."""
    root = f"sqrt(({x} - {z}) * ({x} - {z}) + 4 * {y} * {y})"
    return f"((({x} + {z}) + {root}) / 2)", f"((({x} + {z}) - {root}) / 2)"


def _exact_gram(spark, sf_dir) -> np.ndarray:
    return metrics.gram_matrix(supplier_rows(spark, sf_dir), D2)


REPLAY = f"WITH RECURSIVE {replay_sql(S_ROWS)}"
_K1, _K2 = _eigen("a", "b", "d")
_S1, _S2 = _eigen("g11", "g12", "g22")
_D1, _D2 = _eigen("(a - g11)", "(b - g12)", "(d - g22)")


# ---------------------------------------------------------------- variants of the sketch

@query(lossy_sql("2.0"))
def fd_ridge_shrink_at_ell_supplier(spark, sf_dir):
    """Two rows, the last kept value removed: one direction stays, as with one row."""
    rows = supplier_rows(spark, sf_dir)
    return _coefs(solve(fit_sketch(rows, D2, "fd_ridge", 2, batch_rows=1, shrink_at="ell", deterministic_order=True, partitions=1), 2.0))


@query(lossy_sql("2.0", digits=5))
def fd_ridge_row_gram_supplier(spark, sf_dir):
    """The factorisation by the small matrix of the rows."""
    rows = supplier_rows(spark, sf_dir)
    return _coefs(solve(fit_sketch(rows, D2, "fd_ridge", 1, batch_rows=1, svd="row_gram", deterministic_order=True, partitions=1), 2.0), 5)


_BOTH = " UNION ALL ".join(
    f"SELECT '{name}' AS method, * FROM ({two_rows(*cramer(*gram, gamma), 'last')})"
    for name, gram, gamma in (("exact_ridge", "abd", "2.0"), ("fd_ridge", ("g11", "g12", "g22"), "2.0"), ("robust_fd_ridge", ("g11", "g12", "g22"), "(2.0 + removed / 2)"))
)


@query(f"{REPLAY} {_BOTH}")
def several_sketches_one_pass_supplier(spark, sf_dir):
    """Exact, plain and robust from a single pass over the rows."""
    plans = [SketchPlan("exact_ridge", 1), *[SketchPlan(m, 1, 0, (("batch_rows", 1),)) for m in ("fd_ridge", "robust_fd_ridge")]]
    rows = supplier_rows(spark, sf_dir).repartition(1).sortWithinPartitions("k")
    names = F.element_at(F.array(*[F.lit(p.method) for p in plans]), F.col("plan") + 1)
    sketches = fit_many(rows, D2, plans).withColumn("kind", names)
    return _coefs(solve(sketches, 2.0, by=["kind"]), 6, "kind").withColumnRenamed("kind", "method")


_T2 = "SELECT p, q, l_tax * 10 AS t FROM (SELECT *, l_quantity / 50 AS p, l_discount * 10 AS q FROM lineitem)"
_L_TARGETS = "SELECT l_quantity / 50 AS p, l_discount * 10 AS q, l_extendedprice / 1e5 AS t FROM lineitem"


def _targets_sql() -> str:
    first, second = (exact_sql(r, "64.0") for r in (_L_TARGETS, _T2))
    return f"SELECT idx, coef FROM ({first}) UNION ALL SELECT CAST(idx + 2 AS INTEGER) AS idx, coef FROM ({second})"


@query(_targets_sql())
def two_targets_lineitem(spark, sf_dir):
    """One sketch, two right-hand sides."""
    li = load_table(spark, sf_dir, "lineitem", ["l_quantity", "l_discount", "l_extendedprice", "l_tax"])
    rows = li.select((F.col("l_quantity") / 50).alias("p"), (F.col("l_discount") * 10).alias("q"), (F.col("l_extendedprice") / 1e5).alias("t"), (F.col("l_tax") * 10).alias("t2"))
    return _coefs(solve(fit_sketch(rows, RidgeSpec(["p", "q"], ["t", "t2"]), "fd_ridge", 2, batch_rows=512), 64.0))


@query(f"WITH {_LOSS} SELECT gamma, round(residual_norm, 5) AS residual_norm FROM loss")
def holdout_norm_from_sketch_lineitem(spark, sf_dir):
    """Every penalty's held-out residual from one robust sketch."""
    train, test = ft.train_test(lineitem_rows(spark, sf_dir), "l_orderkey")
    return _rounded(gamma_losses(train, test, D2, _GRID, "robust_fd_ridge", 3, batch_rows=512), 5, "residual_norm")


_CS = "SELECT sum(f0 * f0) AS a, sum(f0 * f1) AS b, sum(f1 * f1) AS d FROM"


@query(f"WITH m AS (SELECT * FROM ({_CS} ({_EVS})), (SELECT sum(p * t) AS u, sum(q * t) AS v FROM ({_EV}))) {two_rows(*cramer('a', 'b', 'd', '64.0'), 'm', 5)}")
def sign_projection_exact_moments_events(spark, sf_dir):
    """Projected features with the exact moments of the targets."""
    gram = rel.moments_2d(_event_signs(spark, sf_dir), F.col("f0"), F.col("f1"), F.col("t")).select("g_0_0", "g_0_1", "g_1_1")
    e = load_table(spark, sf_dir, "events", ["ts", "user_id", "value"])
    exact = rel.moments_2d(e, F.col("value") / 100, F.hour("ts") / 24.0, F.col("user_id") % 10 / 10.0).select("c0", "c1")
    both = rel.ridge_2d(gram.crossJoin(exact), 64.0)  # one row each
    return _rounded(both.select(F.posexplode(F.array("x0", "x1")).alias("idx", "coef")), 5, "coef")


_W_EVENTS = "SELECT CAST(epoch(date_trunc('day', ts)) AS BIGINT) AS day_s, value / 100 AS p, hour(ts) / 24.0 AS q, (user_id % 10) / 10.0 AS t FROM events"
_SLIDE = f"SELECT w.day_s - 86400 * back AS day_s, p, q, t FROM ({_W_EVENTS}) w, (SELECT unnest([0, 1]) AS back)"


@query(f"WITH m AS ({moments_sql(_SLIDE, 'day_s')}) {two_rows(*cramer('a', 'b', 'd', '16.0'), 'm', 5, 'day_s')}")
def sliding_sketch_events(spark, sf_dir):
    """Sketches of two days, one starting every day, merged from daily ones."""
    e = load_table(spark, sf_dir, "events", ["event_id", "ts", "user_id", "value"])
    rows = e.select(F.col("event_id").alias("k"), F.col("ts").cast("timestamp").alias("ts"), (F.col("value") / 100).alias("p"), (F.hour("ts") / 24.0).alias("q"), (F.col("user_id") % 10 / 10.0).alias("t"))
    sketches = windowed_sketches(rows, D2, "fd_ridge", 2, "ts", "2 days", "1 day", batch_rows=64)
    return _coefs(solve(sketches.withColumn("day_s", F.unix_seconds("window_start")), 16.0, by=["day_s"]), 5, "day_s")


_SITES = "SELECT lang, n_chars / 1e4 AS p, len(string_split(text, chr(10))) / 10.0 AS q FROM documents"


@query(f"SELECT lang, count(*) AS n_rows, round(sum(p * p + q * q), 5) AS frob_sq FROM ({_SITES}) GROUP BY lang UNION ALL SELECT 'all', count(*), round(sum(p * p + q * q), 5) FROM ({_SITES})")
def multi_site_totals_documents(spark, sf_dir):
    """A sketch for each language; counts and norms of these and of their merge."""
    docs = load_table(spark, sf_dir, "documents", ["doc_id", "lang", "n_chars", "text"])
    rows = docs.select("lang", F.col("doc_id").alias("k"), (F.col("n_chars") / 1e4).alias("p"), (F.size(F.split("text", "\n")) / 10.0).alias("q"), F.log1p("n_chars").alias("t"))
    per = fit_sketch(rows, RidgeSpec(["p", "q"], "t", "k", ("lang",)), "fd_ridge", 2)
    whole = merge_sketches(per.withColumn("part_id", F.pmod(F.xxhash64("lang"), F.lit(64)).cast("long")), (), 64, 64, "fd_ridge")
    named = per.select("lang", "n_rows", "frob_sq").unionByName(whole.select(F.lit("all").alias("lang"), "n_rows", "frob_sq"))
    return _rounded(named, 5, "frob_sq")


_STAR = "SELECT o_totalprice / 5e5 AS p, p_size / 50.0 AS q, l_extendedprice / 1e5 AS t FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN part ON l_partkey = p_partkey"


@query(exact_sql(_STAR, "32.0"))
def robust_ridge_star_join_d2(spark, sf_dir):
    """A fit over a join: the rows go from the join into the fold."""
    li = load_table(spark, sf_dir, "lineitem", ["l_orderkey", "l_partkey", "l_extendedprice"])
    o, p = load_table(spark, sf_dir, "orders", ["o_orderkey", "o_totalprice"]), load_table(spark, sf_dir, "part", ["p_partkey", "p_size"])
    joined = li.join(o, F.col("l_orderkey") == F.col("o_orderkey")).join(p, F.col("l_partkey") == F.col("p_partkey"))
    rows = joined.select((F.col("o_totalprice") / 5e5).alias("p"), (F.col("p_size") / 50.0).alias("q"), (F.col("l_extendedprice") / 1e5).alias("t"))
    return _coefs(solve(fit_sketch(rows, RidgeSpec(["p", "q"], "t"), "robust_fd_ridge", 2, batch_rows=512), 32.0))


_OX = cramer("a", "b", "d", "8.0")


@query(f"WITH m AS ({moments_sql(_O_ROWS, 'o_orderpriority')}), x AS (SELECT o_orderpriority, {_OX[0]} AS x0, {_OX[1]} AS x1 FROM m) SELECT o.o_orderpriority, CAST(count(*) AS BIGINT) AS n, round(avg((x0 * p + x1 * q - t) * (x0 * p + x1 * q - t)), 6) AS pred_mse FROM ({_O_ROWS}) o JOIN x ON x.o_orderpriority = o.o_orderpriority GROUP BY 1")
def prediction_error_by_priority(spark, sf_dir):
    """Each group's rows against its own model, in one scan."""
    o = load_table(spark, sf_dir, "orders", ["o_orderkey", "o_orderpriority", "o_orderdate", "o_totalprice"])
    rows = o.select("o_orderpriority", F.col("o_orderkey").alias("k"), (F.month("o_orderdate") / 12.0).alias("p"), ((F.dayofweek("o_orderdate") - 1) / 7.0).alias("q"), (F.col("o_totalprice") / 5e5).alias("t"))
    spec = RidgeSpec(["p", "q"], "t", "k", ("o_orderpriority",))
    models = solve(fit_sketch(rows, spec, "fd_ridge", 2), 8.0, by=["o_orderpriority"])
    return _rounded(prediction_error(rows, models, spec, ["o_orderpriority"]).select("o_orderpriority", "n", "pred_mse"), 6, "pred_mse")


# ---------------------------------------------------------------- spectra and errors

@query(f"WITH m AS ({moments_sql(S_ROWS)}), e AS (SELECT sqrt({_K1}) AS s0, sqrt(greatest({_K2}, 0)) AS s1 FROM m) SELECT CAST(0 AS INTEGER) AS idx, round(s0, 5) AS sigma, CAST(1.0 AS DOUBLE) AS sigma_norm, CAST(0.0 AS DOUBLE) AS idx_norm FROM e UNION ALL SELECT CAST(1 AS INTEGER), round(s1, 5), round(s1 / s0, 5), CAST(0.5 AS DOUBLE) FROM e")
def spectrum_supplier(spark, sf_dir):
    return _rounded(metrics.spectrum(supplier_rows(spark, sf_dir), D2), 5, "sigma", "sigma_norm")


_PROFILE = " UNION ALL ".join(
    f"SELECT '{kind}' AS kind, CAST({i} AS INTEGER) AS idx, round({value} + {more}, 5) AS eigenvalue FROM last"
    for kind, values, more in (("gram", (_K1, _K2), "0"), ("gram_penalty", (_K1, _K2), "2.0"), ("sketch_penalty", (_S1, _S2), "2.0"), ("robust_penalty", (_S1, _S2), "2.0 + removed / 2"))
    for i, value in enumerate(values)
)


@query(f"{REPLAY} {_PROFILE}")
def eigen_profile_supplier(spark, sf_dir):
    """Eigenvalues of the Gram matrix, with a penalty, and of what both sketches stand for."""
    gram, row, eye = _exact_gram(spark, sf_dir), collect_sketch(lossy(spark, sf_dir, "fd_ridge")), 2.0 * np.eye(2)
    kinds = {"gram": gram, "gram_penalty": gram + eye, "sketch_penalty": gram_of(row, False) + eye, "robust_penalty": gram_of(row, True) + eye}
    out = [(k, i, round(float(v), 5)) for k, m in kinds.items() for i, v in enumerate(np.linalg.eigvalsh(m)[::-1])]
    return spark.createDataFrame(out, "kind string, idx int, eigenvalue double")


@query(f"{REPLAY} SELECT round(greatest(abs({_D1}), abs({_D2})), 5) AS plain, round(greatest(abs({_D1} - removed / 2), abs({_D2} - removed / 2)), 5) AS robust FROM last")
def covariance_error_supplier(spark, sf_dir):
    gram, row = _exact_gram(spark, sf_dir), collect_sketch(lossy(spark, sf_dir, "fd_ridge"))
    return _one(spark, "plain robust", metrics.cov_error(gram, row, False), metrics.cov_error(gram, row, True))


_GE, _GL = cramer("a", "b", "d", "2.0"), cramer("g11", "g12", "g22", "2.0")
_GAP = f"x AS (SELECT {_GL[0]} - {_GE[0]} AS z0, {_GL[1]} - {_GE[1]} AS z1 FROM last)"


@query(f"{REPLAY}, {_GAP} SELECT CAST(k AS BIGINT) AS k, round(abs(p * z0 + q * z1), 6) AS gap FROM src, x")
def prediction_gap_supplier(spark, sf_dir):
    """How far each row's prediction is from the exact solution's."""
    rows = supplier_rows(spark, sf_dir)
    exact = solve(fit_sketch(rows, D2, "exact_ridge", 1), 2.0)
    gaps = metrics.prediction_gap(rows, solve(lossy(spark, sf_dir, "fd_ridge"), 2.0), exact, D2)
    return _rounded(gaps.select("k", "gap"), 6, "gap")


@query(f"""{REPLAY}, {_GAP}, e AS (SELECT removed / 2.0 * sqrt({_GE[0]} * {_GE[0]} + {_GE[1]} * {_GE[1]}) * sqrt({_K1}) AS bound FROM last)
SELECT CAST(count(*) AS BIGINT) AS n, round(sqrt(sum((p * z0 + q * z1) * (p * z0 + q * z1))), 5) AS gap_norm, round(max(abs(p * z0 + q * z1)), 5) AS gap_max, round(any_value(bound), 5) AS bound FROM src, x, e""")
def prediction_gap_block_supplier(spark, sf_dir):
    """The same over a block of points, and its bound from the certificate."""
    rows = supplier_rows(spark, sf_dir)
    approx, exact = solve(lossy(spark, sf_dir, "fd_ridge"), 2.0), solve(fit_sketch(rows, D2, "exact_ridge", 1), 2.0)
    block = metrics.prediction_gap_block(rows, approx, exact, D2)
    return _rounded(block, 5, "gap_norm", "gap_max", "bound")


@query(f"WITH m AS ({moments_sql(S_ROWS)}) SELECT CAST(k AS BIGINT) AS k, round(((d + 2.0) * p * p - 2 * b * p * q + (a + 2.0) * q * q) / ((a + 2.0) * (d + 2.0) - b * b), 6) AS leverage FROM m, ({S_ROWS})")
def leverage_scores_supplier(spark, sf_dir):
    rows = supplier_rows(spark, sf_dir)
    return _rounded(leverage_scores(rows, fit_sketch(rows, D2, "exact_ridge", 1), D2, 2.0).select("k", "leverage"), 6, "leverage")


@query(f"{REPLAY} SELECT round(0.36 * g11 + 0.96 * g12 + 0.64 * g22, 5) AS norm_sq, round(sqrt(g11 / (g11 + g22)), 5) AS first, round(sqrt(g22 / (g11 + g22)), 5) AS second FROM last")
def sketch_uses_supplier(spark, sf_dir):
    """Other answers of the same sketch: the norm of a product, and the top direction up to its sign."""
    row = collect_sketch(lossy(spark, sf_dir, "fd_ridge"))
    top = np.abs(metrics.low_rank(row, 1)[0])
    return _one(spark, "norm_sq first second", metrics.sketch_norm(row, np.array([0.6, 0.8])), *top)


@query(f"{REPLAY} {two_rows('(g11 * u + g12 * v) / ((g11 + g22) * (g11 + g22))', '(g12 * u + g22 * v) / ((g11 + g22) * (g11 + g22))', 'last')}")
def pcr_from_sketch_supplier(spark, sf_dir):
    """Principal component regression on the one direction that a sketch kept."""
    models = solve_pcr(lossy(spark, sf_dir, "fd_ridge"), 1).withColumn("gamma", F.lit(0.0))
    return _rounded(long_coefficients(models), 6, "coef").select("idx", "coef")


# ---------------------------------------------------------------- bounds

_TAIL = f"WITH m AS ({moments_sql(S_ROWS)}), t AS (SELECT a + d AS t0, {_K2} AS t1 FROM m)"


def _tail(spark, sf_dir) -> np.ndarray:
    return bounds.tail_energy(np.linalg.eigvalsh(_exact_gram(spark, sf_dir)))


@query(f"{_TAIL} SELECT round(least(t0 / 2, t1), 5) AS plain, round(least(t0 / 2, t1) / 2, 5) AS robust, round(least(t0 / 2, t1) / 4.0, 5) AS eps FROM t")
def covariance_bound_supplier(spark, sf_dir):
    """What two rows guarantee before any is read, and the error that follows at a penalty of 4."""
    tail = _tail(spark, sf_dir)
    return _one(spark, "plain robust eps", bounds.cov_bound(tail, 2), bounds.cov_bound(tail, 2, True), bounds.guaranteed_eps(tail, 2, 4.0))


@query(f"{_TAIL}, g AS (SELECT CAST(unnest([0.5, 16.0, 1e6]) AS DOUBLE) AS gamma) SELECT gamma, CAST(CASE WHEN gamma >= t0 THEN 0 WHEN gamma >= t1 THEN 1 ELSE 2 END AS INTEGER) AS k FROM t, g")
def regime_supplier(spark, sf_dir):
    """Directions after which a penalty exceeds the tail."""
    tail = np.round(_tail(spark, sf_dir), 9)
    return spark.createDataFrame([(g, bounds.regime(tail, g)) for g in (0.5, 16.0, 1e6)], "gamma double, k int")


@query(f"{REPLAY} SELECT round(a + d, 5) AS beyond_none, round(greatest(a + d - (g11 + g22), 0), 5) AS beyond_one FROM last")
def tail_bound_from_sketch_supplier(spark, sf_dir):
    """Upper bounds of the tails without a second pass: the exact norm less the kept directions."""
    row = collect_sketch(lossy(spark, sf_dir, "fd_ridge"))
    return _one(spark, "beyond_none beyond_one", *bounds.tail_upper_bound(row.frob_sq, row.sigma)[:2])


_ERR = f"sqrt(({_GL[0]} - {_GE[0]}) * ({_GL[0]} - {_GE[0]}) + ({_GL[1]} - {_GE[1]}) * ({_GL[1]} - {_GE[1]})) / sqrt({_GE[0]} * {_GE[0]} + {_GE[1]} * {_GE[1]})"


@query(f"{REPLAY} SELECT round({_ERR}, 5) AS error, round(greatest(abs({_D1}), abs({_D2})) / (greatest({_S2}, 0) + 2.0), 5) AS bound, round(removed / 2.0, 5) AS certificate FROM last")
def coefficient_bound_supplier(spark, sf_dir):
    """The error, its bound for any approximation of the Gram matrix, and the sketch's own."""
    gram, row = _exact_gram(spark, sf_dir), collect_sketch(lossy(spark, sf_dir, "fd_ridge"))
    exact = collect_sketch(fit_sketch(supplier_rows(spark, sf_dir), D2, "exact_ridge", 1))
    error = metrics.coef_error(coefficients(row, 2.0), coefficients(exact, 2.0))
    least = max(0.0, float(np.linalg.eigvalsh(gram_of(row))[0]))
    return _one(spark, "error bound certificate", error, bounds.coefficient_bound(metrics.cov_error(gram, row), least, 2.0), row.shrink_total / 2.0)


# ---------------------------------------------------------------- risk

def _risk_sql(x: str, y: str, z: str, gamma: str) -> str:
    """bias_sq and variance for H = ([[x, y], [y, z]] + gamma I)^-1, truth (0.7, -0.3), noise 0.5."""
    return f"""h AS (SELECT a, b, d, ({z} + {gamma}) / det AS p, -{y} / det AS q, ({x} + {gamma}) / det AS r FROM (SELECT *, ({x} + {gamma}) * ({z} + {gamma}) - {y} * {y} AS det FROM last)),
k AS (SELECT *, p * a + q * b AS k11, p * b + q * d AS k12, q * a + r * b AS k21, q * b + r * d AS k22 FROM h),
z AS (SELECT *, (k11 - 1) * 0.7 + k12 * -0.3 AS z0, k21 * 0.7 + (k22 - 1) * -0.3 AS z1 FROM k),
risk AS (SELECT a * z0 * z0 + 2 * b * z0 * z1 + d * z1 * z1 AS bias_sq, 0.25 * (k11 * k11 + 2 * k12 * k21 + k22 * k22) AS variance FROM z)"""


def _sketch_risk(name: str, method: str, gamma: str) -> None:
    def f(spark, sf_dir):
        row, gram = collect_sketch(lossy(spark, sf_dir, method)), _exact_gram(spark, sf_dir)
        r = risk(gram, gram_of(row, False), np.array([0.7, -0.3]), 0.5, effective_penalty(row, 2.0))
        return _one(spark, "bias_sq variance risk", r.bias_sq, r.variance, r.risk)

    f.__name__ = name
    query(f"{REPLAY}, {_risk_sql('g11', 'g12', 'g22', gamma)} SELECT round(bias_sq, 5) AS bias_sq, round(variance, 5) AS variance, round(bias_sq + variance, 5) AS risk FROM risk")(f)


_sketch_risk("risk_of_plain_sketch_supplier", "fd_ridge", "2.0")
_sketch_risk("risk_of_robust_sketch_supplier", "robust_fd_ridge", "(2.0 + removed / 2)")


@query(f"{REPLAY}, f AS (SELECT {_K1} AS top, {_K1} * greatest(abs({_D1}), abs({_D2})) / 1e4 AS t FROM last) SELECT round((1 + t) * (1 + t), 5) AS safe, round(1 + t * t, 5) AS printed, round((1 + top / 100.0) * (1 + top / 100.0), 5) AS variance FROM f")
def risk_factors_supplier(spark, sf_dir):
    """Factors that bound the sketched solution's bias and variance, at a penalty of 100."""
    gram, row = _exact_gram(spark, sf_dir), collect_sketch(lossy(spark, sf_dir, "fd_ridge"))
    safe, printed = risk_factors(gram, gram_of(row), 100.0), risk_factors(gram, gram_of(row), 100.0, "printed")
    return _one(spark, "safe printed variance", safe[0], printed[0], safe[1])
