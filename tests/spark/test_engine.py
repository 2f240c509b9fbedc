"""Fitting, solving, streaming and sources on Spark, against NumPy."""

import glob
import uuid

import numpy as np
import pytest
from pyspark.sql import functions as F

from spectral_ridge import RidgeSpec, fit_sketch, merge_sketches, predict, solve
from spectral_ridge import workloads as wl
from spectral_ridge.operators import features as ft
from spectral_ridge.operators import relational as rel
from spectral_ridge.operators.fit import collect_sketch, fit_sparse, partial_sketches
from spectral_ridge.operators.leverage import leverage_sample_ridge, leverage_scores
from spectral_ridge.operators.predict import prediction_error
from spectral_ridge.operators.solve import coefficients, long_coefficients, solve_pcr
from spectral_ridge.plans import gamma as gm
from spectral_ridge.plans import metrics, planner
from spectral_ridge.sketch import METHODS
from spectral_ridge.sources import tables
from spectral_ridge.sources.generators import generate_ridge_rows, rows_block
from spectral_ridge.streaming import sketches as st

SPEC = RidgeSpec("features", "target", "row_id")


def reference(a, b, gamma):
    lam, v = np.linalg.eigh(a.T @ a)
    return v @ ((v.T @ (a.T @ b)) / (lam + gamma))


@pytest.fixture(scope="module")
def rows(spark, sf):
    out = wl.workload_high_rank(spark, sf).cache()
    out.count()
    return out


@pytest.fixture(scope="module")
def dense(rows):
    return wl.dense(rows, 10_000)


def coefs(solution):
    return np.array(solution.first()["coefficients"])


@pytest.mark.parametrize("method", METHODS)
def test_fit_on_partitions(rows, dense, method):
    a, b = dense
    split = rows.repartition(7)
    sketch = fit_sketch(split, SPEC, method, 64, merge_fan_in=3)
    row = collect_sketch(sketch)
    assert row.n_rows == len(a) and row.frob_sq == pytest.approx((a**2).sum())
    assert np.allclose(row.cross[:, 0], a.T @ b)
    x = coefs(solve(sketch, 50.0))
    if method in ("fd_ridge", "robust_fd_ridge", "truncated_svd_ridge", "exact_ridge"):
        assert np.allclose(x, reference(a, b, 50.0), atol=1e-8)
    assert x.shape == (64,) and np.isfinite(x).all()


def test_lossy_fit_stays_in_its_certificate(rows, dense):
    a, b = dense
    sketch = fit_sketch(rows.repartition(6), SPEC, "fd_ridge", 12)
    for robust in (False, True):
        for r in solve(sketch, [5.0, 50.0, 500.0], robust=robust).collect():
            error = metrics.coef_error(np.array(r["coefficients"]), reference(a, b, r["gamma"]))
            assert error <= r["certificate"] * (1 + 1e-9)


def test_deterministic_order_gives_equal_bits(rows):
    one, two = (collect_sketch(fit_sketch(r, SPEC, "robust_fd_ridge", 8, deterministic_order=True, partitions=3)) for r in (rows.repartition(2), rows.orderBy(F.desc("target"))))
    assert one.sigma.tobytes() == two.sigma.tobytes() and one.basis.tobytes() == two.basis.tobytes()
    with pytest.raises(ValueError):
        fit_sketch(rows, RidgeSpec("features", "target"), "fd_ridge", 4, deterministic_order=True)


def test_groups_and_sites(spark, rows, dense):
    a, b = dense
    grouped = rows.withColumn("g", F.pmod("row_id", F.lit(3)))
    spec = RidgeSpec("features", "target", "row_id", ("g",))
    sketches = fit_sketch(grouped.repartition(5), spec, "exact_ridge", 1)
    by = {r["g"]: np.array(r["coefficients"]) for r in solve(sketches, 9.0, by=["g"]).collect()}
    ids = np.array(sorted(r[0] for r in rows.select("row_id").collect()))
    for g in range(3):
        assert np.allclose(by[g], reference(a[ids % 3 == g], b[ids % 3 == g], 9.0), atol=1e-8)
    merged = merge_sketches(sketches.withColumn("part_id", F.col("g")), (), 2)
    assert np.allclose(coefs(solve(merged, 9.0)), reference(a, b, 9.0), atol=1e-8)
    many = grouped.withColumn("g", F.col("row_id"))
    assert fit_sketch(many, spec, "count_sketch_ridge", 4).count() == len(a)


def test_invalid_rows(spark):
    data = [(1, [1.0, 2.0], 1.0), (2, [float("nan"), 1.0], 2.0), (3, None, 3.0), (4, [3.0, float("inf")], 4.0), (5, [2.0, 5.0], None), (6, [4.0, 1.0], 6.0), (7, [None, 1.0], 1.0)]
    df = spark.createDataFrame(data, "row_id long, features array<double>, target double")
    row = collect_sketch(fit_sketch(df, RidgeSpec("features", "target", "row_id", on_invalid="skip"), "exact_ridge", 1))
    assert (row.n_rows, row.n_skipped) == (2, 5)
    zero = collect_sketch(fit_sketch(df, RidgeSpec("features", "target", "row_id", on_invalid="zero"), "fd_ridge", 2))
    assert zero.n_rows == 7
    with pytest.raises(Exception, match="null, NaN or infinity"):
        fit_sketch(df, SPEC, "exact_ridge", 1).collect()
    with pytest.raises(Exception, match="features; 2 expected"):
        fit_sketch(df.where("row_id in (1, 6)").union(spark.createDataFrame([(9, [1.0], 1.0)], df.schema)), RidgeSpec("features", "target", "row_id", n_features=2), "exact_ridge", 1).collect()
    with pytest.raises(ValueError):
        RidgeSpec("features", "target", on_invalid="ignore")
    assert fit_sketch(df.limit(0), SPEC, "fd_ridge", 2).count() == 0
    assert solve(fit_sketch(df.limit(0), SPEC, "fd_ridge", 2), 1.0).count() == 0


def test_column_types(spark):
    df = spark.sql("SELECT id AS k, cast(id AS decimal(10,2)) AS dec, id % 2 = 0 AS flag, timestamp'2024-01-01' + make_interval(0, 0, 0, id) AS at, cast(id * 2 AS float) AS y FROM range(20)")
    spec = RidgeSpec(["dec", "flag"], "y", "k", fit_intercept=True)
    a = np.array([[i, float(i % 2 == 0), 1.0] for i in range(20)])
    assert np.allclose(coefs(solve(fit_sketch(df, spec, "fd_ridge", 3), 1.0)), reference(a, 2.0 * np.arange(20), 1.0))
    assert fit_sketch(df, RidgeSpec(["at"], "y", "k"), "exact_ridge", 1).first()["n_rows"] == 20
    with pytest.raises(TypeError):
        fit_sketch(df.withColumn("s", F.lit("x")), RidgeSpec(["s"], "y"), "fd_ridge", 1)


def test_many_targets(rows, dense):
    a, b = dense
    spec = RidgeSpec("features", ["target", "twice"], "row_id")
    x = coefs(solve(fit_sketch(rows.withColumn("twice", 2 * F.col("target")), spec, "fd_ridge", 64), 3.0)).reshape(2, -1)
    assert np.allclose(x[1], 2 * x[0]) and np.allclose(x[0], reference(a, b, 3.0))


def test_predictions_and_selection(rows, dense):
    a, b = dense
    models = solve(fit_sketch(rows, SPEC, "exact_ridge", 1), [1.0, 100.0])
    scored = {(r["row_id"], r["gamma"]): r["prediction"] for r in predict(rows, models, SPEC).collect()}
    ids = sorted({k for k, _ in scored})
    assert np.allclose([scored[i, 100.0] for i in ids], a @ reference(a, b, 100.0))
    mse = {r["gamma"]: r["pred_mse"] for r in prediction_error(rows, models, SPEC).collect()}
    assert mse[1.0] == pytest.approx(np.mean((a @ reference(a, b, 1.0) - b) ** 2))
    x = reference(a, b, 1.0)
    objective = {r["gamma"]: r["objective"] for r in metrics.objective(rows, models, SPEC).collect()}
    assert objective[1.0] == pytest.approx(((a @ x - b) ** 2).sum() + (x**2).sum())
    train, test = ft.train_test(rows, "row_id")
    assert train.join(test, "row_id").count() == 0 and train.count() + test.count() == len(a)
    best = gm.select_gamma(train, test, SPEC).first()
    losses = {r["gamma"]: r["residual_norm"] for r in gm.gamma_losses(train, test, SPEC).collect()}
    assert losses[best["gamma"]] == min(losses.values()) and len(losses) == 21
    from spectral_ridge.experiments import mean_gamma_losses

    low, high = (min(mean_gamma_losses(rows.sparkSession, "/root/testdata/sf0.1", w).collect(), key=lambda r: r["residual_norm"])["gamma"] for w in (wl.workload_low_rank, wl.workload_high_rank))
    assert 1 < low <= high < 2**20


def test_relational_twins(spark, rows, dense, sf):
    a, b = dense
    gram = np.zeros((64, 64))
    for r in rel.gram_from_arrays(rows, "features").collect():
        gram[r["i"], r["j"]] = gram[r["j"], r["i"]] = r["value"]
    assert np.allclose(gram, a.T @ a)
    two = rows.select("row_id", F.col("features")[0].alias("p"), F.col("features")[1].alias("q"), "target")
    x = rel.ridge_2d(rel.moments_2d(two, F.col("p"), F.col("q"), F.col("target")), 5.0).first()
    assert np.allclose([x["x0"], x["x1"]], reference(a[:, :2], b, 5.0))
    assert rel.count_sketch(two, F.col("row_id"), [F.col("p")], F.col("target"), 8).count() == 8


def test_spark_library_agrees(rows, dense):
    from pyspark.ml.functions import array_to_vector
    from pyspark.ml.regression import LinearRegression

    a, b = dense
    gamma = 7.0
    df = rows.select(array_to_vector("features").alias("features"), F.col("target").alias("label"))
    model = LinearRegression(solver="normal", fitIntercept=False, standardization=False, regParam=gamma * float(np.std(b)) / len(b), elasticNetParam=0.0).fit(df)
    assert np.allclose(model.coefficients.toArray(), coefs(solve(fit_sketch(rows, SPEC, "exact_ridge", 1), gamma)), atol=1e-8)
    vectors = fit_sketch(df, RidgeSpec("features", "label"), "exact_ridge", 1)
    assert np.allclose(coefs(solve(vectors, gamma)), reference(a, b, gamma))


def test_estimator(rows, dense):
    from pyspark.ml import Pipeline
    from pyspark.ml.evaluation import RegressionEvaluator
    from pyspark.ml.tuning import CrossValidator, ParamGridBuilder

    from spectral_ridge.ml import SketchRidgeRegression

    a, b = dense
    est = SketchRidgeRegression(labelCol="target", method="fd_ridge", ell=64, gamma=4.0)
    model = Pipeline(stages=[est]).fit(rows)
    assert np.allclose(model.stages[0].coefficients, reference(a, b, 4.0), atol=1e-8)
    got = [r["prediction"] for r in model.transform(rows).orderBy("row_id").collect()]
    assert np.allclose(got, a @ reference(a, b, 4.0))
    grid = ParamGridBuilder().addGrid(est.gamma, [256.0, 1e-3]).build()
    cv = CrossValidator(estimator=est, estimatorParamMaps=grid, evaluator=RegressionEvaluator(labelCol="target"), numFolds=2, seed=1).fit(rows)
    assert cv.bestModel.getOrDefault("gamma") == 256.0


def test_leverage_and_components(rows, dense):
    a, b = dense
    sketch = fit_sketch(rows, SPEC, "exact_ridge", 1)
    inverse = np.linalg.inv(a.T @ a + 20 * np.eye(64))
    got = [r["leverage"] for r in leverage_scores(rows, sketch, SPEC, 20.0).orderBy("row_id").collect()]
    assert np.allclose(got, np.einsum("ij,jk,ik->i", a, inverse, a))
    for deterministic in (False, True):
        assert leverage_sample_ridge(rows, SPEC, 20.0, 150, deterministic).count() == 64
    lam, v = np.linalg.eigh(a.T @ a)
    top = v[:, ::-1][:, :3]
    assert np.allclose(coefs(solve_pcr(sketch, 3)), top @ ((top.T @ (a.T @ b)) / lam[::-1][:3]))


def test_sparse_text_sketch(spark, sf):
    rows = wl.workload_text_hash(spark, sf, 128).cache()
    data = rows.collect()
    a = np.zeros((len(data), 128))
    for i, r in enumerate(data):
        np.add.at(a[i], list(r["sparse"]["indices"]), list(r["sparse"]["values"]))
    b = np.array([r["target"] for r in data])
    row = collect_sketch(fit_sparse(rows, 128, 40))
    assert np.allclose(row.cross[:, 0], a.T @ b) and row.n_rows == len(data)
    error = metrics.coef_error(coefficients(row, 1e4)[:, 0], reference(a, b, 1e4))
    assert error <= (row.shrink_total + row.dropped_total) / 1e4


def test_generator_source(spark):
    df = generate_ridge_rows(spark, 300, 16, 0.5, seed=3, block=100)
    a, b = wl.dense(df, 1000)
    want = [rows_block(s, 100, 16, 8, 3, 2.0) for s in (0, 100, 200)]
    assert np.allclose(a, np.concatenate([w[0] for w in want])) and np.allclose(b, np.concatenate([w[1] for w in want]))
    assert df.rdd.getNumPartitions() == 3


def test_workloads(spark, sf):
    assert wl.workload_event_shingles(spark, "/root/testdata/sf0.01").count() == 695
    shingle = wl.workload_event_shingles(spark, sf).orderBy("row_id").limit(2).collect()
    assert shingle[0]["features"][1:] == shingle[1]["features"][:-1] and shingle[0]["target"] == shingle[1]["features"][-1]
    for d in (8, 16, 40):
        star = wl.workload_star(spark, sf, d)
        assert star.select(F.size("features")).distinct().collect()[0][0] == d
    assert wl.workload_adversarial(spark, 100).count() == 100
    assert ft.sample_rows(spark.range(50), "id", 7).distinct().count() == 7
    sizes = metrics.spectrum(wl.workload_low_rank(spark, sf), SPEC).orderBy("idx").collect()
    assert sizes[0]["sigma_norm"] == 1.0 and sizes[20]["sigma_norm"] < 0.01


def test_feature_functions(spark):
    df = spark.createDataFrame([([1.0, 2.0, 3.0],), ([4.0, None, 6.0],), (None,), ([float("nan"), 1.0, 1.0],)], "x array<double>")
    got = df.select(ft.valid_rows(F.col("x")).alias("ok"), ft.polynomial(F.col("x")).alias("p"), ft.interactions(F.col("x")).alias("i")).collect()
    assert [bool(r["ok"]) for r in got] == [True, False, False, False]
    assert got[0]["p"] == [1, 2, 3, 1, 4, 9] and got[0]["i"] == [2, 3, 6]
    hashed = ft.hash_features(spark.createDataFrame([("a", 1), ("b", 2)], "s string, n int"), ["s", "n"], 8)
    assert all(len(r["features"]) == 8 and sum(map(abs, r["features"])) in (0, 2) for r in hashed.collect())
    assert spark.createDataFrame([("b",), (None,)], "s string").select(ft.one_hot("s", ["a", "b"]).alias("h")).collect()[1]["h"] == [0.0, 0.0]
    normal = spark.range(4000).select(F.avg(ft.hash_normal(F.col("id"), 1)), F.stddev(ft.hash_normal(F.col("id"), 1))).first()
    assert abs(normal[0]) < 0.06 and abs(normal[1] - 1) < 0.05


def test_planner(rows):
    plan = planner.plan_fit(rows.repartition(40), SPEC, 8)
    assert plan.method == "robust_fd_ridge" and plan.partitions == 40 and plan.rounds >= 1
    assert planner.plan_fit(rows, SPEC, 64).method == "exact_ridge"
    assert "merge rounds" in planner.explain_fit(rows, SPEC, 8)


def test_plan_shuffles_only_sketches(spark, sf):
    li = tables.load_table(spark, sf, "lineitem")
    spec = RidgeSpec(["l_quantity", "l_discount"], "l_extendedprice", n_features=2)
    partial = partial_sketches(li, spec, "fd_ridge", 2)
    plan = partial._jdf.queryExecution().executedPlan().toString()
    assert "Exchange" not in plan and "l_comment" not in plan and "l_shipdate" not in plan.split("ReadSchema")[-1]


# ---------------------------------------------------------------- streams

def _stream_dir(spark, tmp_path, rows, parts=3):
    path = f"{tmp_path}/in"
    rows.repartition(parts).write.parquet(path)
    return path


def test_stream_equals_batch_and_replays_change_nothing(spark, rows, dense, tmp_path):
    a, b = dense
    path = _stream_dir(spark, tmp_path, rows)
    stream = tables.read_stream(spark, path, schema="row_id long, features array<double>, target double", maxFilesPerTrigger=1)
    ledger, seen = st.SketchLedger(spark, f"file://{tmp_path}/ledger"), []
    st.stream_sketch(stream, SPEC, "fd_ridge", 64, ledger, f"{tmp_path}/ck", lambda i, s: seen.append((i, s.first()["n_rows"]))).awaitTermination()
    assert [n for _, n in seen] == sorted(n for _, n in seen) and seen[-1][1] == len(a) and len(seen) == 3
    assert np.allclose(coefs(st.anytime_solution(ledger, 5.0)), reference(a, b, 5.0), atol=1e-8)
    again = fit_sketch(rows, SPEC, "fd_ridge", 64)
    assert ledger.commit(seen[-1][0], again, (), "fd_ridge") is False
    assert ledger.current().first()["n_rows"] == len(a) and len(glob.glob(f"{tmp_path}/ledger/*")) == ledger.keep
    assert st.anytime_solution(st.SketchLedger(spark, f"file://{tmp_path}/none"), 1.0) is None


def test_keyed_state(spark, rows, tmp_path):
    path = _stream_dir(spark, tmp_path, rows.withColumn("g", F.pmod("row_id", F.lit(2))))
    stream = tables.read_stream(spark, path, schema="row_id long, features array<double>, target double, g long", maxFilesPerTrigger=1)
    name = f"keyed_{uuid.uuid4().hex}"
    q = st.keyed_state_sketches(stream, SPEC, "robust_fd_ridge", 8, "g", 64).writeStream.outputMode("update").format("memory").queryName(name).option("checkpointLocation", f"{tmp_path}/ck").trigger(availableNow=True).start()
    q.awaitTermination()
    last = spark.table(name).groupBy("g").agg(F.max("n_rows").alias("n")).collect()
    counts = {r["g"]: r["count"] for r in rows.groupBy(F.pmod("row_id", F.lit(2)).alias("g")).count().collect()}
    assert {r["g"]: r["n"] for r in last} == counts


def test_windows_and_sessions(spark):
    data = [(i, f"2024-01-01 {i // 60:02d}:{i % 60:02d}:00", float(i % 5), float(i % 3), i % 2) for i in range(0, 600, 7)]
    df = spark.createDataFrame(data, "k long, at string, p double, t double, user int").withColumn("at", F.to_timestamp("at"))
    spec = RidgeSpec(["p"], "t", "k")
    tumbling = st.windowed_sketches(df, spec, "exact_ridge", 1, "at", "1 hour").collect()
    want = {r["h"]: r["n"] for r in df.groupBy(F.date_trunc("hour", "at").alias("h")).agg(F.count("*").alias("n")).collect()}
    assert {r["window_start"]: r["n_rows"] for r in tumbling} == want
    sliding = {r["window_start"]: r["n_rows"] for r in st.windowed_sketches(df, spec, "exact_ridge", 1, "at", "2 hours", "1 hour").collect()}
    native = {r["s"]: r["n"] for r in df.groupBy(F.window("at", "2 hours", "1 hour").alias("w")).agg(F.count("*").alias("n")).select(F.col("w.start").alias("s"), "n").collect()}
    assert sliding == native
    sessions = st.session_sketches(df, spec, "exact_ridge", 1, "at", "10 minutes", "user")
    assert sum(r["n_rows"] for r in sessions.collect()) == len(data)
    assert sessions.count() == df.groupBy("user", F.session_window("at", "10 minutes")).count().count()


def test_stream_helpers(spark, tmp_path, sf):
    with pytest.raises(Exception, match="only insertions"):
        st.reject_retractions(spark.createDataFrame([(1, "delete")], "k int, op string"), "op").collect()
    assert st.reject_retractions(spark.createDataFrame([(1, "insert")], "k int, op string"), "op").count() == 1
    rows = spark.range(100).select(F.col("id").alias("k"), (F.col("id") % 7).cast("double").alias("p"), F.lit(1.0).alias("t"))
    rows.write.parquet(f"{tmp_path}/cs")
    stream = tables.read_stream(spark, f"{tmp_path}/cs", schema="k long, p double, t double")
    name = f"cs_{uuid.uuid4().hex}"
    st.streaming_count_sketch(stream, "k", ["p"], "t", 4).writeStream.outputMode("complete").format("memory").queryName(name).trigger(availableNow=True).start().awaitTermination()
    got = {r["bucket"]: (r["f0"], r["t"]) for r in spark.table(name).collect()}
    assert got == {r["bucket"]: (r["f0"], r["t"]) for r in rel.count_sketch(rows, F.col("k"), [F.col("p")], F.col("t"), 4).collect()}
    events = tables.read_stream(spark, sf, schema=tables.SCHEMAS["events"], pathGlobFilter="events.parquet")
    assert dict(events.dtypes)["ts"] == "timestamp" and st.dedup_stream(events, "event_id", "ts").isStreaming


# ---------------------------------------------------------------- sources, sinks, functions

def test_sources_and_sinks(spark, rows, tmp_path, sf):
    sketch = fit_sketch(rows, SPEC, "fd_ridge", 8)
    tables.write_sketch(sketch, f"file://{tmp_path}/s", "v1")
    tables.write_sketch(sketch, f"file://{tmp_path}/s", "v1")
    assert tables.read_sketch(spark, f"file://{tmp_path}/s", "v1").count() == 1
    with open(f"{tmp_path}/a.svm", "w") as f:
        f.write("1.5 1:2 3:4.5\n-1 2:1\n\n0\n")
    svm = tables.read_libsvm(spark, f"file://{tmp_path}/a.svm", 3).collect()
    assert [(r["target"], list(r["sparse"]["indices"]), list(r["sparse"]["values"])) for r in svm] == [(1.5, [0, 2], [2.0, 4.5]), (-1.0, [1], [1.0]), (0.0, [], [])]
    tables.write_predictions(spark.createDataFrame([(1, "a"), (2, "b")], "k int, g string"), f"file://{tmp_path}/p", ("g",))
    assert tables.read_rows(spark, f"file://{tmp_path}/p").count() == 2
    spark.range(3).createOrReplaceTempView("three")
    assert tables.read_rows(spark, table="three").count() == 3


def test_sql_functions(spark, rows, dense):
    from spectral_ridge.functions.udfs import register

    a, b = dense
    register(spark)
    fit_sketch(rows, SPEC, "fd_ridge", 64).createOrReplaceTempView("sk")
    spark.sql("SELECT struct(*) AS s FROM sk").createOrReplaceTempView("packed")
    x = spark.sql("SELECT solve_ridge(s, 5.0D) AS x FROM packed").first()["x"]
    assert np.allclose(x, reference(a, b, 5.0), atol=1e-8)
    assert spark.sql("SELECT dot(array(1D, 2D), array(3D, 4D)) AS d, axpy(2D, array(1D), array(1D)) AS y").first()[:] == (11.0, [3.0])
    assert spark.sql("SELECT vector_norm(array(3D, 4D)) AS n").first()["n"] == 5.0
    rows.select("features", "target", F.pmod("row_id", F.lit(3)).alias("g")).createOrReplaceTempView("design")
    partial = spark.sql("SELECT * FROM ridge_fit(TABLE(design) PARTITION BY (g), 'fd_ridge', 64)")
    merged = merge_sketches(partial.withColumn("part_id", F.monotonically_increasing_id() % 7), (), 16, 7)
    assert np.allclose(coefs(solve(merged, 5.0)), reference(a, b, 5.0), atol=1e-8)
    assert long_coefficients(solve(merged, [1.0, 2.0])).count() == 128


def test_monte_carlo_risk_covers_every_row(spark, sf, tmp_path, monkeypatch):
    from spectral_ridge import experiments

    base = spark.read.parquet(f"{sf}/embeddings.parquet")
    more = base.crossJoin(spark.range(6).withColumnRenamed("id", "copy")).withColumn("vec_id", (base["vec_id"] + 100_000 * F.col("copy")).cast(base.schema["vec_id"].dataType)).drop("copy")
    more.coalesce(1).write.parquet(f"{tmp_path}/embeddings.parquet")
    a, _ = wl.dense(wl.workload_high_rank(spark, str(tmp_path)), 10_000)
    assert len(a) > 2000
    used, plain = [], experiments.risk
    monkeypatch.setattr(experiments, "risk", lambda gram, *rest: used.append(gram) or plain(gram, *rest))
    got = experiments.measure_monte_carlo_risk(spark, str(tmp_path)).first()
    assert np.allclose(used[0], a.T @ a)
    assert abs(got.monte_carlo - got.risk) <= 0.1 * got.risk


def test_building_a_fit_starts_no_job(spark):
    sc = spark.sparkContext
    left = spark.range(0, 4000, 1, 7).select("id", (F.col("id") % 13 / 13.0).alias("p"))
    right = spark.range(0, 4000, 1, 5).select(F.col("id").alias("other"), (F.col("id") % 7 / 7.0).alias("q"))
    sc.setJobGroup("lazy", "")
    joined = left.join(right.hint("merge"), F.col("id") == F.col("other")).withColumn("t", F.col("p") - F.col("q"))
    spec = RidgeSpec(["p", "q"], "t", "id")
    sketch = fit_sketch(joined, spec, "fd_ridge", 2)
    solution = solve(sketch, 1.0)
    assert not sc.statusTracker().getJobIdsForGroup("lazy")
    sc.setJobGroup("run", "")
    assert solution.count() == 1 and sketch.first()["n_rows"] == 4000


@pytest.mark.parametrize("parts", [1, 3, 40])
def test_one_sketch_under_any_splitting(spark, parts):
    """More partitions than the tree was planned for still give one row."""
    rows = spark.range(0, 500, 1, parts).select("id", (F.col("id") / 500.0).alias("p"), F.lit(1.0).alias("q"), F.col("id").cast("double").alias("t"))
    spec = RidgeSpec(["p", "q"], "t", "id")
    partial = partial_sketches(rows, spec, "fd_ridge", 2)
    for width in (1, 2, 300):
        merged = merge_sketches(partial, (), 2, width, "fd_ridge").collect()
        assert len(merged) == 1 and merged[0]["n_rows"] == 500


def test_errors_of_wide_models_by_product(spark, monkeypatch):
    rows = generate_ridge_rows(spark, 300, 24, 0.5, block=100)
    spec = RidgeSpec("features", "target", "row_id")
    models = solve(fit_sketch(rows, spec, "exact_ridge", 1), [1.0, 50.0]).cache()
    plain = {r["gamma"]: r["pred_mse"] for r in prediction_error(rows, models, spec).collect()}
    monkeypatch.setattr("spectral_ridge.operators.predict.WIDE", 8)
    wide = {r["gamma"]: r["pred_mse"] for r in prediction_error(rows, models, spec).collect()}
    assert wide.keys() == plain.keys() and all(abs(wide[g] / plain[g] - 1) < 1e-9 for g in plain)


def test_sliding_windows_keep_the_options_of_the_fit(spark):
    rows = spark.range(240).select(F.timestamp_seconds(F.col("id") * 3600).alias("ts"), F.col("id").alias("k"), F.sin("id").alias("p"), F.cos("id").alias("q"), F.lit(1.0).alias("t"))
    spec = RidgeSpec(["p", "q"], "t", "k")
    sketches = st.windowed_sketches(rows, spec, "two_level_ridge", 7, "ts", "2 days", "1 day", k=2, seed=3)
    assert sketches.count() == 11 and {r["ell"] for r in sketches.collect()} == {7}
