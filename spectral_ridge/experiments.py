"""The experiments: errors, times, penalties and spectra over methods, rows, features and workloads."""

from __future__ import annotations

import time
from collections.abc import Iterable, Sequence

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import workloads as wl
from .operators import features as ft
from .operators.design import RidgeSpec
from .operators.fit import SketchPlan, collect_sketch, fit_many, fit_sketch
from .operators.solve import certificate, coefficients, full_gram, gram_of, solve, solve_components
from .plans import bounds, metrics
from .plans.gamma import POWERS_OF_TWO, gamma_losses
from .plans.risk import held_out_risk, moments_risk, noise_moments, risk
from .queries import EMB, query
from .runtime import materialise
from .sketch import SketchRow
from .sources.generators import generate_ridge_rows, planted

COMPARED = ("fd_ridge", "robust_fd_ridge", "truncated_svd_ridge", "two_level_ridge", "sign_projection_ridge", "count_sketch_ridge", "exact_ridge")
RANDOMISED = ("two_level_ridge", "sign_projection_ridge", "count_sketch_ridge", "srht_ridge")
#: One row of a comparison: means over the repeats, and deviations of the error and training time.
RESULT = ", ".join([
    "workload string, method string, n long, d int, ell int, gamma double, repeats int",
    "train_s double, query_s double, total_s double, amortised_s double, coef_err double, cov_err double",
    "pred_mse_train double, pred_mse_test double, coef_err_sd double, train_sd double",
    "sketch_bytes long, n_svd int, certificate double",
])


def ell_grid(d: int, low: int = 16) -> list[int]:
    """Powers of two from ``low`` to just past the number of features."""
    out, k = [], low
    while k <= 2 * d:
        out.append(k)
        k *= 2
    return out


def _loss(row: SketchRow, x: np.ndarray) -> float:
    """Mean squared residual over the rows of an exact sketch, from its moments."""
    total = x @ full_gram(row) @ x - 2 * x @ row.cross[:, 0] + row.target_sq
    return float(max(total, 0.0) / max(1, row.n_rows))


def compare(name: str, train: DataFrame, test: DataFrame | None, gamma: float, methods: Iterable[str], grid: Sequence[int], repeats: int, spec: RidgeSpec = EMB) -> list[tuple]:
    """Errors and times of each method and sketch size on one workload.

    All sketches come from one pass over ``train``, all errors on ``test`` from its moments, in one
    more; only sketches reach the driver. Training time is what all tasks spent in a sketch, merges
    included; a query is one solution. The exact method queries as often as the sketch it stands
    beside, once every ``ell`` rows.
    """
    plans = [SketchPlan("exact_ridge", 1)]
    for method in methods:
        if method != "exact_ridge":
            plans += [SketchPlan(method, ell, seed) for ell in grid for seed in range(repeats if method in RANDOMISED else 1)]
    found = {r["plan"]: SketchRow.from_dict(r.asDict()) for r in fit_many(train, spec, plans).collect()}
    if not found:
        return []
    exact = found[0]
    gram, n, d = full_gram(exact), exact.n_rows, exact.n_features
    held = None if test is None else [SketchRow.from_dict(r.asDict()) for r in fit_sketch(test, spec, "exact_ridge", 1).collect()]
    best = coefficients(exact, gamma)[:, 0]

    def cell(row: SketchRow) -> tuple:
        began = time.perf_counter()
        x = coefficients(row, gamma)[:, 0]
        asked = time.perf_counter() - began
        return row.train_ns / 1e9, asked, metrics.coef_error(x, best), metrics.cov_error(gram, row), _loss(exact, x), _loss(held[0], x) if held else None

    def line(method: str, ell: int, rows: list[SketchRow], cells: list[tuple]) -> tuple:
        mean = [float(np.mean(c)) if c[0] is not None else None for c in zip(*cells, strict=True)]
        train_s, query_s = mean[:2]
        spent = metrics.amortised_seconds(train_s, query_s, n, ell)
        spread = [float(np.std([c[k] for c in cells])) for k in (2, 0)]
        cost = metrics.space_report(rows[0])["bytes"], rows[0].n_svd, certificate(rows[0], gamma)
        return (name, method, n, d, ell, gamma, len(cells), train_s, query_s, train_s + query_s, spent, *mean[2:], *spread, *cost)

    out = []
    for method in methods:
        if method == "exact_ridge":
            cells = [cell(exact)]
            out += [line(method, ell, [exact], cells) for ell in grid]
            continue
        for ell in grid:
            rows = [found[k] for k, p in enumerate(plans) if (p.method, p.ell) == (method, ell)]
            out.append(line(method, ell, rows, [cell(r) for r in rows]))
    return out


def error_frontier(spark: SparkSession, sets: dict[str, tuple], methods: Iterable[str] = COMPARED, grid: Sequence[int] = (8, 16, 32, 64), repeats: int = 10) -> DataFrame:
    """The comparison on several workloads. ``sets``: name -> (train rows, test rows, penalty)."""
    out = [row for name, (train, test, gamma) in sets.items() for row in compare(name, train, test, gamma, methods, grid, repeats)]
    return spark.createDataFrame(out, RESULT)


def _split(rows: DataFrame, label: str) -> tuple[DataFrame, DataFrame]:
    return ft.train_test(materialise(rows, label), "row_id")


def _generated(spark: SparkSession, n: int, d: int, rank_frac: float, n_test: int = 0) -> tuple[DataFrame, DataFrame | None]:
    rows = materialise(generate_ridge_rows(spark, n + n_test, d, rank_frac, block=min(256, n)), "generated-rows")
    return rows.where(F.col("row_id") < n), rows.where(F.col("row_id") >= n) if n_test else None


#: Penalties that the reference reports for its low-rank and high-rank sets.
PUBLISHED_GAMMA = {"low_rank": (0.1, 4096.0), "high_rank": (0.5, 32768.0)}


def series_shingles(spark: SparkSession, sf_dir: str, n: int, d: int, seed: int = 0) -> DataFrame:
    """``n`` shingles of ``d`` differences of the hourly event series, drawn without replacement."""
    return ft.sample_rows(wl.workload_event_shingles(spark, sf_dir, d), "row_id", n, seed)


def published_size(spark: SparkSession, sf_dir: str, grid: Sequence[int] = (16, 32, 64, 128, 256), repeats: int = 10, n: int = 8192, d: int = 2048, n_test: int = 2048, series_d: int = 256) -> DataFrame:
    """The comparison on three sets at the published size and penalties: 8192 training and 2048 test
    rows of 2048 features. The series is as long as the events table lets it be."""
    sets = {name: (*_generated(spark, n, d, frac, n_test), gamma) for name, (frac, gamma) in PUBLISHED_GAMMA.items()}
    series = materialise(series_shingles(spark, sf_dir, n + n_test, series_d), "series-rows")
    sets["series"] = (*ft.train_test(series, "row_id"), PUBLISHED_GAMMA["high_rank"][1])
    return error_frontier(spark, sets, COMPARED, grid, repeats)


@query()
def experiment_published(spark, sf_dir):
    """The published comparison at an eighth of its rows and features, penalties to scale; the bench
    can run the whole."""
    n, d = 1024, 256
    sets = {name: (*_generated(spark, n, d, frac, 256), gamma / 8) for name, (frac, gamma) in PUBLISHED_GAMMA.items()}
    series = materialise(series_shingles(spark, sf_dir, n, 64), "series-rows")
    sets["series"] = (*ft.train_test(series, "row_id"), 512.0)
    return error_frontier(spark, sets, COMPARED, (16, 32, 64, 128), 10)


@query()
def experiment_error_frontier(spark, sf_dir):
    """Errors against rows on the low-rank, high-rank and series stand-ins."""
    kinds = {"low_rank": (wl.workload_low_rank, 64.0), "high_rank": (wl.workload_high_rank, 512.0), "events": (wl.workload_event_shingles, 512.0)}
    return error_frontier(spark, {name: (*_split(rows(spark, sf_dir), "frontier-rows"), gamma) for name, (rows, gamma) in kinds.items()})


@query()
def experiment_small_ell(spark, sf_dir):
    """Very few rows: the robust method's bonus against the plain one."""
    sets = {"high_rank": (*_split(wl.workload_high_rank(spark, sf_dir), "few-rows"), 512.0)}
    return error_frontier(spark, sets, ("fd_ridge", "robust_fd_ridge", "truncated_svd_ridge", "two_level_ridge"), (4, 8, 16, 32))


def mean_gamma_losses(spark: SparkSession, sf_dir: str, workload, repeats: int = 5) -> DataFrame:
    """(gamma, residual_norm): held-out residual of every penalty, the mean over noise draws: one
    draw of a few hundred test rows is a nearly flat curve."""
    out = None
    for seed in range(repeats):
        train, test = ft.train_test(materialise(workload(spark, sf_dir, seed), "gamma-rows"), "row_id")
        part = gamma_losses(train, test, EMB)
        out = part if out is None else out.unionByName(part)
    return out.groupBy("gamma").agg(F.avg("residual_norm").alias("residual_norm"))


@query()
def experiment_gamma(spark, sf_dir):
    """Held-out residual of every penalty on the two planted workloads."""
    low, high = (mean_gamma_losses(spark, sf_dir, w).withColumn("workload", F.lit(n)) for n, w in (("low_rank", wl.workload_low_rank), ("high_rank", wl.workload_high_rank)))
    return low.unionByName(high)


@query()
def experiment_gamma_from_sketch(spark, sf_dir):
    """The same choice from a robust sketch and a stored test set."""
    train, test = ft.train_test(materialise(wl.workload_high_rank(spark, sf_dir), "gamma-rows"), "row_id")
    return gamma_losses(train, test, EMB, method="robust_fd_ridge", ell=16)


def gamma_by_noise(spark: SparkSession, n: int = 8192, d: int = 2048, n_test: int = 2048) -> DataFrame:
    """(workload, rank, noise_sd, gamma, gap_sq): expected held-out gap of every penalty on the
    generated sets, with 2 and with 4 as the standard deviation of the noise. The best penalty is
    near noise variance times rank, whatever the number of rows."""
    out = []
    for name, (frac, _) in PUBLISHED_GAMMA.items():
        rank = max(1, int(frac * d))
        train, test = (metrics.gram_matrix(rows, EMB) for rows in _generated(spark, n, d, frac, n_test))
        x = ft.cosine_matrix(d) @ planted(d, rank, 0)
        for noise_sd in (2.0, 4.0):
            gaps = held_out_risk(train, test, x, noise_sd, POWERS_OF_TWO)
            out += [(name, rank, noise_sd, g, float(gap)) for g, gap in zip(POWERS_OF_TWO, gaps, strict=True)]
    return spark.createDataFrame(out, "workload string, rank int, noise_sd double, gamma double, gap_sq double")


@query()
def experiment_gamma_noise(spark, sf_dir):
    """Why the published penalties exceed ours: the same curves at an eighth of the features."""
    return gamma_by_noise(spark, 1024, 256, 256)


def _times(spark: SparkSession, cells: Sequence[tuple[int, int, Sequence[int]]], methods: Iterable[str] = COMPARED) -> list[tuple]:
    """Comparison rows of generated data, by (rows, features, sketch sizes)."""
    return [row for n, d, grid in cells for row in compare("generated", _generated(spark, n, d, 0.5)[0], None, 512.0, methods, grid, 1)]


#: (rows, features, sketch sizes) of the timed runs. Sketches go past the number of features.
BY_ELL = [(1024, 256, (16, 32, 64, 128, 256, 300, 512))]
BY_FEATURES = [(256, d, (64,)) for d in (64, 128, 256, 512, 1024, 2048)]
BY_ROWS = [(n, 512, (64,)) for n in (512, 1024, 2048, 4096)]


@query()
def experiment_time_vs_rows(spark, sf_dir):
    return spark.createDataFrame(_times(spark, BY_ELL), RESULT)


@query()
def experiment_time_vs_dim(spark, sf_dir):
    return spark.createDataFrame(_times(spark, BY_FEATURES), RESULT)


@query()
def experiment_time_vs_n(spark, sf_dir):
    return spark.createDataFrame(_times(spark, BY_ROWS), RESULT)


@query()
def experiment_slopes(spark, sf_dir):
    """(method, query_by_features, train_by_rows): powers with which the time of one query grows
    with the features, from 256 on, and that of training with the rows."""
    column = {c.split()[0]: k for k, c in enumerate(RESULT.split(", "))}
    queries, trains = _times(spark, BY_FEATURES[2:]), _times(spark, BY_ROWS)
    out = []
    for method in COMPARED:
        mine = lambda rows: [r for r in rows if r[1] == method]  # noqa: B023, E731
        by_d = metrics.log_slope([r[column["d"]] for r in mine(queries)], [r[column["query_s"]] for r in mine(queries)])
        by_n = metrics.log_slope([r[column["n"]] for r in mine(trains)], [r[column["train_s"]] for r in mine(trains)])
        out.append((method, by_d, by_n))
    return spark.createDataFrame(out, "method string, query_by_features double, train_by_rows double")


@query()
def experiment_spectrum(spark, sf_dir):
    """Normalised singular values of the workloads."""
    out = None
    for name, rows in (("low_rank", wl.workload_low_rank(spark, sf_dir)), ("high_rank", wl.workload_high_rank(spark, sf_dir)), ("events", wl.workload_event_shingles(spark, sf_dir))):
        part = metrics.spectrum(rows, EMB).withColumn("workload", F.lit(name))
        out = part if out is None else out.unionByName(part)
    return out


@query()
def experiment_eigen_profile(spark, sf_dir):
    """Sorted eigenvalues of the Gram matrix, with a penalty, and of the two sketches."""
    rows = materialise(wl.workload_high_rank(spark, sf_dir), "profile-rows")
    row, gram, gamma = collect_sketch(fit_sketch(rows, EMB, "fd_ridge", 16)), metrics.gram_matrix(rows, EMB), 512.0
    eye = np.eye(len(gram))
    kinds = {"gram": gram, "gram_penalty": gram + gamma * eye, "sketch_penalty": gram_of(row, False) + gamma * eye, "robust_penalty": gram_of(row, True) + gamma * eye}
    return spark.createDataFrame([(k, i, float(v)) for k, m in kinds.items() for i, v in enumerate(np.linalg.eigvalsh(m)[::-1])], "kind string, idx int, eigenvalue double")


@query()
def experiment_adversarial(spark, sf_dir):
    """Strong axes, then a long weak tail that carries the target: truncation misses it."""
    rows = materialise(wl.workload_adversarial(spark), "adversarial-rows")
    return error_frontier(spark, {"adversarial": (rows, None, 64.0)}, ("fd_ridge", "robust_fd_ridge", "truncated_svd_ridge"), (8, 16), 1)


@query()
def experiment_pcr(spark, sf_dir):
    """Principal component regression against ridge, each from the exact Gram matrix and from a
    sketch: with near-equal top singular values the first is unstable, the second is not."""
    rows = materialise(wl.workload_flat(spark, sf_dir), "pcr-rows")
    gram, row = metrics.gram_matrix(rows, EMB), collect_sketch(fit_sketch(rows, EMB, "fd_ridge", 32))
    out = []
    for k in (2, 4, 8):
        exact, approx = solve_components(gram, row.cross, k)[:, 0], solve_components(gram_of(row), row.cross, k)[:, 0]
        out.append(("pcr", k, metrics.coef_error(approx, exact)))
    g = float(np.trace(gram)) / 8
    exact = np.linalg.solve(gram + g * np.eye(len(gram)), row.cross)[:, 0]
    out.append(("ridge", 0, metrics.coef_error(coefficients(row, g)[:, 0], exact)))
    return spark.createDataFrame(out, "method string, k int, coef_err double")


@query()
def experiment_required_rows(spark, sf_dir):
    """Rows that guarantee an error, plain, robust and for random transforms, on both workloads."""
    out = []
    for name, rows, gamma in (("low_rank", wl.workload_low_rank(spark, sf_dir), 64.0), ("high_rank", wl.workload_high_rank(spark, sf_dir), 512.0)):
        tail = bounds.tail_energy(np.linalg.eigvalsh(metrics.gram_matrix(rows, EMB)))
        for eps in (0.5, 0.2, 0.1, 0.05):
            plain, robust = bounds.required_rows(tail, gamma, eps), bounds.required_rows(tail, gamma, eps, True)
            out.append((name, eps, plain[0], robust[0], bounds.random_rows_for(eps), bounds.guaranteed_eps(tail, plain[0], gamma), bounds.regime(tail, gamma)))
    return spark.createDataFrame(out, "workload string, eps double, plain int, robust int, random int, guaranteed double, regime_k int")


@query()
def experiment_star_join(spark, sf_dir):
    """Tall data: order lines with their dimensions, one pass for all methods, errors on held-out rows."""
    rows = materialise(wl.workload_star(spark, sf_dir, 32), "star-rows")
    train, test = ft.train_test(rows.withColumn("key", F.pmod("row_id", F.lit(1_000_003))), "key")
    spec = RidgeSpec("features", "target", "row_id", n_features=32)
    methods = ("exact_ridge", "robust_fd_ridge", "fd_ridge", "truncated_svd_ridge", "sign_projection_ridge", "count_sketch_ridge")
    return spark.createDataFrame(compare("star", train, test, 64.0, methods, (16,), 3, spec), RESULT)


@query()
def experiment_daily_series(spark, sf_dir):
    """Longer series, more features: daily orders and daily prices."""
    sets = {f"{table}_{d}": (*_split(wl.workload_daily_shingles(spark, sf_dir, table, d), "daily-rows"), 64.0) for table in ("orders", "lineitem") for d in (64, 128, 256)}
    return error_frontier(spark, sets, ("fd_ridge", "robust_fd_ridge", "sign_projection_ridge", "exact_ridge"), (16, 32))


@query()
def measure_prediction_gap(spark, sf_dir):
    """Each row's prediction gap of the robust sketch, and the bound from its certificate."""
    rows = materialise(wl.workload_high_rank(spark, sf_dir), "gap-rows")
    approx, exact = (solve(fit_sketch(rows, EMB, m, 16), 512.0) for m in ("robust_fd_ridge", "exact_ridge"))
    eps = approx.first()["certificate"]
    x_norm = float(np.linalg.norm(exact.first()["coefficients"]))
    norm = F.sqrt(F.aggregate("features", F.lit(0.0), lambda s, v: s + v * v))
    return metrics.prediction_gap(rows, approx, exact, EMB).select("row_id", "gap", (F.lit(eps * x_norm) * norm).alias("bound"))


@query()
def measure_covariance_error(spark, sf_dir):
    """Spectral error of each sketch against its a-priori bound, and the bound from the sketch alone."""
    rows = materialise(wl.workload_high_rank(spark, sf_dir), "cov-rows")
    gram, out = metrics.gram_matrix(rows, EMB), []
    tail = bounds.tail_energy(np.linalg.eigvalsh(gram))
    for ell in (4, 8, 16, 32):
        row = collect_sketch(fit_sketch(rows, EMB, "fd_ridge", ell))
        upper = bounds.tail_upper_bound(row.frob_sq, row.sigma)
        for name, robust in (("plain", False), ("robust", True)):
            out.append((name, ell, metrics.cov_error(gram, row, robust), bounds.cov_bound(tail, ell, robust), bounds.cov_bound(upper, ell, robust), row.shrink_total))
    return spark.createDataFrame(out, "form string, ell int, cov_error double, bound double, bound_from_sketch double, shrink_total double")


@query()
def measure_space(spark, sf_dir):
    """Rows, numbers and bytes that each method keeps for the same data."""
    rows, out = materialise(wl.workload_high_rank(spark, sf_dir), "space-rows"), []
    for method in COMPARED:
        report = metrics.space_report(collect_sketch(fit_sketch(rows, EMB, method, 16)))
        out.append((method, report["rows"], report["floats"], report["bytes"]))
    return spark.createDataFrame(out, "method string, sketch_rows int, floats int, bytes int")


@query()
def measure_monte_carlo_risk(spark, sf_dir):
    """Risk of the robust sketch by its closed form and by repeated noise; one sketch serves all draws."""
    rows = materialise(wl.workload_high_rank(spark, sf_dir), "risk-rows")
    x, gram, gamma = ft.cosine_matrix(64) @ planted(64, 32, 0), metrics.gram_matrix(rows, EMB), 512.0
    approx = gram_of(collect_sketch(fit_sketch(rows, EMB, "robust_fd_ridge", 16)))
    closed = risk(gram, approx, x, 2.0, gamma)
    drawn = moments_risk(gram, noise_moments(rows, 64, 400), lambda c: np.linalg.solve(approx + gamma * np.eye(64), c), x, 2.0)
    return spark.createDataFrame([(closed.bias_sq, closed.variance, closed.risk, drawn)], "bias_sq double, variance double, risk double, monte_carlo double")
