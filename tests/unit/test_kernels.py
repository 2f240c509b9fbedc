"""Sketch kernels, solvers, bounds and risk against an independent dense reference."""

import numpy as np
import pytest

from spectral_ridge.operators.features import cosine_matrix
from spectral_ridge.operators.solve import certificate, coefficients, gram_of, solve_components, solve_dual, solve_pinv, solve_primal, solve_rows, solve_spectral
from spectral_ridge.plans import bounds, metrics
from spectral_ridge.plans.planner import choose_fan_in, choose_method, choose_solver, rows_for_target
from spectral_ridge.plans.risk import held_out_risk, monte_carlo, risk, risk_factors, robust_printed_factors
from spectral_ridge.sketch import METHODS, SPECTRAL, SketchRow, make_sketcher
from spectral_ridge.sketch.base import hash_uniform
from spectral_ridge.sketch.spectral import SparseSpectralSketcher, factor
from spectral_ridge.sketch.two_level import residual_rows
from spectral_ridge.sources.generators import rows_block

EXACT_CROSS = (*SPECTRAL, "two_level_ridge", "exact_ridge")


def reference(a, b, gamma):
    """Ridge by the Gram matrix's eigenvalues: not the engine's code."""
    lam, v = np.linalg.eigh(a.T @ a)
    return v @ ((v.T @ (a.T @ b)) / (lam + gamma))


def data(n=600, d=24, frac=0.5, seed=0):
    return rows_block(0, n, d, max(1, int(frac * d)), seed, 2.0)


def fold(method, a, b, ell, parts=1, **options):
    rows = []
    for k in range(parts):
        s = make_sketcher(method, ell, a.shape[1], 1, 0, **options)
        s.update(a[k::parts], b[k::parts], np.arange(len(a))[k::parts])
        rows.append(s.finish(k))
    if parts == 1:
        return rows[0]
    out = make_sketcher(method, ell, a.shape[1], 1, 0, **options)
    out.merge(rows)
    return out.finish()


@pytest.mark.parametrize("parts", [1, 4])
@pytest.mark.parametrize("ell", [1, 4, 9, 23])
def test_shrinkage_bounds(ell, parts):
    a, b = data()
    gram = a.T @ a
    tail = bounds.tail_energy(np.linalg.eigvalsh(gram))
    row = fold("fd_ridge", a, b, ell, parts)
    lost = np.linalg.eigvalsh(gram - gram_of(row, False))
    assert lost[0] > -1e-8 * gram.trace() and lost[-1] <= row.shrink_total * (1 + 1e-9)
    robust = np.linalg.eigvalsh(gram - gram_of(row, True))
    assert np.abs(robust).max() <= row.shrink_total / 2 * (1 + 1e-9)
    for k in range(ell):
        assert row.shrink_total <= tail[k] / (ell - k) * (1 + 1e-9)
    assert (ell + 1) * row.shrink_total <= row.frob_sq - (row.sigma**2).sum() + 1e-6 * row.frob_sq
    assert np.allclose(row.basis @ row.basis.T, np.eye(len(row.basis)), atol=1e-9)
    assert (np.diff(row.sigma) <= 1e-12).all() and (row.sigma >= 0).all() and len(row.sigma) <= ell


def test_shrink_conventions():
    a, b = data()
    at_ell = fold("fd_ridge", a, b, 8, shrink_at="ell")
    assert len(at_ell.sigma) <= 7
    lost = np.linalg.eigvalsh(a.T @ a - gram_of(at_ell, False))
    assert lost[0] > -1e-6 and lost[-1] <= at_ell.shrink_total * (1 + 1e-9)
    with pytest.raises(ValueError):
        fold("fd_ridge", a, b, 8, shrink_at="nowhere")


@pytest.mark.parametrize("method", METHODS)
def test_cross_moments_are_exact_for_any_split(method):
    a, b = data()
    for parts in (1, 3, 7):
        row = fold(method, a, b, 6, parts)
        assert np.allclose(row.cross[:, 0], a.T @ b, rtol=1e-9)
        assert row.n_rows == len(a) and row.frob_sq == pytest.approx((a**2).sum()) and row.target_sq == pytest.approx(b @ b)


@pytest.mark.parametrize("method", EXACT_CROSS)
def test_full_rank_sketches_are_exact(method):
    rng = np.random.default_rng(1)
    a = rng.normal(size=(300, 5)) @ rng.normal(size=(5, 20))
    b = rng.normal(size=300)
    for ell in (5, 6, 20, 40):
        if method == "two_level_ridge" and 3 * max(1, ell // 4) < 5:
            continue
        for parts in (1, 4):
            x = coefficients(fold(method, a, b, ell, parts), 3.0)[:, 0]
            assert np.allclose(x, reference(a, b, 3.0), atol=1e-7)


@pytest.mark.parametrize("svd", ["direct", "row_gram"])
@pytest.mark.parametrize("batch", [1, 5, 64])
def test_batches_and_factorisations(svd, batch):
    a, b = data(200, 40)
    row = fold("fd_ridge", a, b, 10, batch_rows=batch, svd=svd)
    lost = np.linalg.eigvalsh(a.T @ a - gram_of(row, False))
    assert lost[0] > -1e-6 and lost[-1] <= row.shrink_total * (1 + 1e-6)
    assert row.n_svd == -(-200 // batch)


def test_factor_orthonormal():
    rng = np.random.default_rng(0)
    m = rng.normal(size=(12, 50)) * np.geomspace(1, 1e-6, 12)[:, None]
    for how in ("direct", "row_gram"):
        s, v = factor(m, how)
        assert np.allclose(v @ v.T, np.eye(len(v)), atol=1e-7) and np.allclose((s[:, None] * v).T @ (s[:, None] * v), m.T @ m, atol=1e-8)


def test_solution_formula_and_forms():
    a, b = data(100, 30)
    row = fold("fd_ridge", a, b, 7)
    dense = np.linalg.solve(gram_of(row, False) + 2.5 * np.eye(30), a.T @ b)
    assert np.allclose(solve_spectral(row.sigma, row.basis, row.cross[:, 0], 2.5), dense, atol=1e-9)
    assert np.allclose(coefficients(row, 2.5, robust=True), solve_spectral(row.sigma, row.basis, row.cross, 2.5 + row.shrink_total / 2))
    assert np.allclose(coefficients(fold("robust_fd_ridge", a, b, 7), 2.5), coefficients(row, 2.5, robust=True))
    wide = a[:12]
    assert np.allclose(solve_dual(wide, b[:12], 2.0), reference(wide, b[:12], 2.0))
    assert np.allclose(solve_primal(wide.T @ wide, wide.T @ b[:12], 2.0), reference(wide, b[:12], 2.0))
    assert np.allclose(solve_rows(wide, wide.T @ b[:12], 2.0), reference(wide, b[:12], 2.0))
    assert np.allclose(a @ solve_pinv(a.T @ a, a.T @ b), a @ np.linalg.lstsq(a, b, rcond=None)[0])
    assert np.allclose(solve_components(a.T @ a, a.T @ b, 30), np.linalg.lstsq(a, b, rcond=None)[0], atol=1e-6)
    with pytest.raises(ValueError):
        coefficients(row, -1.0)


def test_many_targets_share_a_sketch():
    a, b = data(200, 10)
    y = np.column_stack([b, 2 * b, -b])
    s = make_sketcher("fd_ridge", 4, 10, 3)
    s.update(a, y)
    x = coefficients(s.finish(), 5.0)
    assert np.allclose(x[:, 1], 2 * x[:, 0]) and np.allclose(x[:, 2], -x[:, 0])


@pytest.mark.parametrize("method", ["fd_ridge", "robust_fd_ridge", "truncated_svd_ridge"])
def test_certificate_covers_the_error(method):
    for seed in range(5):
        a, b = data(400, 20, seed=seed)
        for ell in (2, 5, 10):
            row = fold(method, a, b, ell, 1 + seed % 3)
            for gamma in (5.0, 100.0, 1000.0):
                error = metrics.coef_error(coefficients(row, gamma)[:, 0], reference(a, b, gamma))
                assert error <= certificate(row, gamma) * (1 + 1e-9) + 1e-12


def test_certificates_elsewhere():
    a, b = data()
    assert certificate(fold("exact_ridge", a, b, 1), 1.0) == 0
    assert certificate(fold("count_sketch_ridge", a, b, 8), 1.0) is None
    assert certificate(fold("fd_ridge", a, b, 8), 0.0) is None


def test_structural_bound_and_tightness():
    rng = np.random.default_rng(5)
    for _ in range(50):
        a, c = rng.normal(size=(20, 6)), rng.normal(size=(20, 6))
        k, h, v, g = a.T @ a, c.T @ c, rng.normal(size=6), rng.random() * 10 + 0.1
        x, y = np.linalg.solve(k + g * np.eye(6), v), np.linalg.solve(h + g * np.eye(6), v)
        bound = bounds.coefficient_bound(np.linalg.norm(k - h, 2), np.linalg.eigvalsh(h)[0], g)
        assert np.linalg.norm(x - y) <= bound * np.linalg.norm(x) * (1 + 1e-9)
    t = bounds.tightness_example(5, 2.0, 1.0, 3.0)
    v = rng.normal(size=5)
    x, y = np.linalg.solve(t.gram + 3 * np.eye(5), v), np.linalg.solve(t.approx + 3 * np.eye(5), v)
    assert metrics.coef_error(y, x) == pytest.approx(t.error)
    for wrong in (lambda: bounds.tightness_example(2, -1, 1, 1), lambda: bounds.coefficient_bound(1.0, 0.0, 0.0)):
        with pytest.raises(ValueError):
            wrong()


def test_required_rows_reach_the_target():
    a, b = data(800, 30)
    tail = bounds.tail_energy(np.linalg.eigvalsh(a.T @ a))
    for gamma in (50.0, 400.0):
        for eps in (0.5, 0.1):
            for robust, method in ((False, "fd_ridge"), (True, "robust_fd_ridge")):
                ell, k = bounds.required_rows(tail, gamma, eps, robust)
                assert ell >= k + 1 or ell == np.count_nonzero(tail)
                x = coefficients(fold(method, a, b, ell), gamma)[:, 0]
                assert metrics.coef_error(x, reference(a, b, gamma)) <= eps
                need = bounds.required_gamma(tail, 8, eps, robust)
                assert bounds.guaranteed_eps(tail, 8, need, robust) == pytest.approx(eps)
    assert bounds.required_rows(tail, 50.0, 0.2, True)[0] <= bounds.required_rows(tail, 50.0, 0.2)[0]
    assert bounds.regime(tail, 1e9) == 0 and bounds.regime(tail, 0.0) is None
    assert bounds.random_rows_for(0.1) == 100 and bounds.per_row_penalty(2.0, 5) == 10.0


def test_tails_from_a_sketch_are_upper_bounds():
    a, b = data()
    row = fold("fd_ridge", a, b, 12)
    tail, upper = bounds.tail_energy(np.linalg.eigvalsh(a.T @ a)), bounds.tail_upper_bound(row.frob_sq, row.sigma)
    assert (upper >= tail[: len(upper)] - 1e-6).all()
    assert rows_for_target(upper, 400.0, 0.1) >= bounds.required_rows(tail, 400.0, 0.1, True)[0]


def test_held_out_risk_against_drawn_noise():
    (a, _), (other, _) = data(n=200, d=10), data(n=80, d=10, seed=1)
    x, rng = np.random.default_rng(4).standard_normal(10), np.random.default_rng(5)
    targets = (a @ x)[:, None] + 1.5 * rng.standard_normal((200, 4000))
    for gamma, expected in zip((1.0, 64.0), held_out_risk(a.T @ a, other.T @ other, x, 1.5, (1.0, 64.0))):
        found = np.linalg.solve(a.T @ a + gamma * np.eye(10), a.T @ targets)
        assert ((other @ (found - x[:, None])) ** 2).sum(axis=0).mean() == pytest.approx(expected, rel=0.05)


def test_risk_forms():
    a, b = data(300, 12)
    x = np.random.default_rng(2).normal(size=12)
    gram, gamma = a.T @ a, 40.0
    exact = risk(gram, gram, x, 1.5, gamma)
    assert exact.bias_sq == pytest.approx(gamma**2 * np.linalg.norm(a @ np.linalg.solve(gram + gamma * np.eye(12), x)) ** 2)
    h = a @ np.linalg.inv(gram + gamma * np.eye(12)) @ a.T
    assert exact.variance == pytest.approx(1.5**2 * np.linalg.norm(h) ** 2) and not exact.rank_deficient
    row = fold("robust_fd_ridge", a, b, 5)
    approx = gram_of(row)
    sketched = risk(gram, approx, x, 1.5, gamma)
    bias, variance = risk_factors(gram, approx, gamma)
    assert sketched.bias_sq <= bias * exact.bias_sq and sketched.variance <= variance * exact.variance
    mean = monte_carlo(a, lambda c: np.linalg.solve(approx + gamma * np.eye(12), c), x, 1.5, 4000)
    assert mean == pytest.approx(sketched.risk, rel=0.05)
    assert robust_printed_factors(gram, 0.1, gamma)[0] > 1


def test_printed_bias_factor_can_fail():
    one = np.ones((1, 1))
    exact, sketched = risk(one, one, np.ones(1), 0.0, 1.0), risk(one, 1.1 * one, np.ones(1), 0.0, 1.0)
    assert sketched.bias_sq == pytest.approx((1.1 / 2.1) ** 2)
    assert sketched.bias_sq > risk_factors(one, 1.1 * one, 1.0, "printed")[0] * exact.bias_sq
    assert sketched.bias_sq <= risk_factors(one, 1.1 * one, 1.0)[0] * exact.bias_sq
    a = np.array([(5, -1, -7), (7, 0, 5), (1, -7, 2), (-1, 7, -1), (-2, 0, 0)], dtype=float)
    row = fold("robust_fd_ridge", a, np.zeros(5), 1, batch_rows=1)
    x, gram = np.array([0.1318, 0.99, -0.0506]), a.T @ a
    ratio = risk(gram, gram_of(row), x, 0.0, 200.0).bias_sq / risk(gram, gram, x, 0.0, 200.0).bias_sq
    eps = np.linalg.norm(gram - gram_of(row), 2) / 200.0
    assert (round(robust_printed_factors(gram, eps, 200.0)[0], 4), round(ratio, 4), round(risk_factors(gram, gram_of(row), 200.0)[0], 4)) == (1.0501, 1.1011, 1.2364)


@pytest.mark.parametrize("method", ["sign_projection_ridge", "count_sketch_ridge", "srht_ridge"])
def test_random_transforms_are_unbiased(method):
    a, b = data(120, 6)
    gram, runs = a.T @ a, []
    for seed in range(250):
        s = make_sketcher(method, 8, 6, 1, seed)
        s.update(a, b)
        runs.append(gram_of(s.finish()))
    mean, error = np.mean(runs, axis=0), np.std(runs, axis=0) / np.sqrt(len(runs))
    assert (np.abs(mean - gram) <= 6 * error + 1e-9).all()


def test_printed_sign_scale_blows_up():
    a, b = data(200, 6)
    good = make_sketcher("sign_projection_ridge", 64, 6)
    bad = make_sketcher("sign_projection_ridge", 64, 6, scale="printed")
    for s in (good, bad):
        s.update(a, b)
    trace = np.trace(a.T @ a)
    assert 0.5 < np.trace(gram_of(good.finish())) / trace < 1.6
    assert np.trace(gram_of(bad.finish())) / trace > 64**2 / 2


@pytest.mark.parametrize("method", ["sign_projection_ridge", "count_sketch_ridge"])
def test_row_hashes_make_projections_independent_of_the_split(method):
    a, b = data()
    assert np.allclose(fold(method, a, b, 16).payload, fold(method, a, b, 16, 5).payload)
    row = fold(method, a, b, 16)
    assert np.allclose(coefficients(row, 9.0, query="dual"), coefficients(row, 9.0, query="primal"))
    assert coefficients(row, 9.0, use_exact_cross=True).shape == (24, 1)


def test_two_level_residual_is_unbiased():
    a, b = data(200, 8)
    gram, runs = a.T @ a, []
    for seed in range(300):
        s = make_sketcher("two_level_ridge", 6, 8, 1, seed, k=1)
        s.update(a, b)
        row = s.finish()
        q = residual_rows(row)
        runs.append(gram_of(row))
        assert np.trace(q.T @ q) == pytest.approx(row.residual_mass)
    mean, error = np.mean(runs, axis=0), np.std(runs, axis=0) / np.sqrt(len(runs))
    assert (np.abs(mean - gram) <= 6 * error + 1e-6).all()
    assert residual_rows(fold("two_level_ridge", a, b, 16, k=4)).shape[0] == 0


def test_sparse_sketch_bounds():
    rng = np.random.default_rng(3)
    dense = rng.normal(size=(400, 30)) * (rng.random((400, 30)) < 0.1) * np.exp(-np.arange(30) / 8)
    b = rng.normal(size=400)
    at, col = np.nonzero(dense)
    s = SparseSpectralSketcher("fd_ridge", 12, 30, 1, 0)
    for lo in range(0, 400, 100):
        keep = (at >= lo) & (at < lo + 100)
        s.update_sparse(np.bincount(at[keep] - lo, minlength=100), col[keep], dense[at[keep], col[keep]], b[lo : lo + 100])
    row = s.finish()
    assert np.allclose(row.cross[:, 0], dense.T @ b) and row.n_rows == 400
    lost = np.linalg.eigvalsh(dense.T @ dense - gram_of(row, False))
    assert lost[0] > -1e-8 and lost[-1] <= row.shrink_total + row.dropped_total + 1e-9
    assert metrics.coef_error(coefficients(row, 50.0)[:, 0], reference(dense, b, 50.0)) <= certificate(row, 50.0)


def test_truncation_fails_on_the_adversarial_stream():
    rng = np.random.default_rng(0)
    strong, d, n = 8, 32, 4096
    a = np.zeros((n, d))
    a[: 4 * strong][np.arange(4 * strong), np.arange(4 * strong) % strong] = 10
    a[4 * strong :, strong] = 0.5 + 0.1 * rng.normal(size=n - 4 * strong)
    b = a[:, strong] + 0.1 * rng.normal(size=n)
    gram, cut, kept = a.T @ a, fold("truncated_svd_ridge", a, b, strong, batch_rows=8), fold("robust_fd_ridge", a, b, strong, batch_rows=8)
    assert metrics.cov_error(gram, cut) > 2 * metrics.cov_error(gram, kept)
    assert metrics.coef_error(coefficients(cut, 64.0)[:, 0], reference(a, b, 64.0)) > 2 * metrics.coef_error(coefficients(kept, 64.0)[:, 0], reference(a, b, 64.0))


def test_ranking_at_the_selected_penalty():
    """Spectral sketches beat random ones by far; the robust one beats the plain one."""
    a, b = data(2048, 128, 0.5)
    exact, err = reference(a, b, 4096.0), {}
    for method in ("fd_ridge", "robust_fd_ridge", "truncated_svd_ridge", "two_level_ridge", "sign_projection_ridge", "count_sketch_ridge"):
        err[method] = metrics.coef_error(coefficients(fold(method, a, b, 16), 4096.0)[:, 0], exact)
    assert max(err[m] for m in ("fd_ridge", "robust_fd_ridge", "truncated_svd_ridge", "two_level_ridge")) < 0.5 * min(err["sign_projection_ridge"], err["count_sketch_ridge"])
    assert err["robust_fd_ridge"] < err["fd_ridge"]
    more = [metrics.coef_error(coefficients(fold("fd_ridge", a, b, ell), 4096.0)[:, 0], exact) for ell in (8, 16, 32, 64, 128)]
    assert all(y <= x + 1e-9 for x, y in zip(more, more[1:])) and more[-1] < 1e-6


def test_limits_rotation_and_order():
    a, b = data(300, 16)
    row = fold("fd_ridge", a, b, 6)
    assert np.allclose(coefficients(row, 1e12)[:, 0] * 1e12, a.T @ b, rtol=1e-4)
    norms = [np.linalg.norm(coefficients(row, g)) for g in (1.0, 10.0, 100.0, 1e4)]
    assert all(x >= y for x, y in zip(norms, norms[1:]))
    r = cosine_matrix(16)
    assert np.allclose(r @ r.T, np.eye(16))
    assert np.allclose(coefficients(fold("fd_ridge", a @ r.T, b, 6), 8.0)[:, 0], r @ coefficients(row, 8.0)[:, 0], atol=1e-8)
    assert fold("fd_ridge", a, b, 6).sigma.tobytes() == row.sigma.tobytes()


def test_edges():
    for method in METHODS:
        s = make_sketcher(method, 4, 3)
        s.update(np.zeros((2, 3)), np.zeros(2))
        assert np.allclose(coefficients(s.finish(), 1.0), 0)
        empty = make_sketcher(method, 4, 3).finish()
        merged = make_sketcher(method, 4, 3)
        merged.merge([empty, s.finish()])
        assert merged.finish().n_rows == 2
        again = SketchRow.from_dict(s.finish().to_dict())
        assert again.n_rows == 2 and again.cross.shape == (3, 1)
    with pytest.raises(ValueError, match="unknown method"):
        make_sketcher("nothing", 4, 3)
    with pytest.raises(ValueError):
        make_sketcher("fd_ridge", 0, 3)
    with pytest.raises(ValueError, match="features"):
        make_sketcher("fd_ridge", 2, 3).update(np.zeros((1, 4)), np.zeros(1))
    with pytest.raises(ValueError, match="cannot merge"):
        make_sketcher("fd_ridge", 2, 3).merge([make_fold("exact_ridge")])
    a = np.repeat(np.arange(6.0).reshape(2, 3), 5, axis=0)
    assert np.allclose(coefficients(fold("fd_ridge", a, np.ones(10), 2), 1.0)[:, 0], reference(a, np.ones(10), 1.0))
    one = make_sketcher("fd_ridge", 1, 3)
    one.update(np.ones((1, 3), np.float32), [1.0])
    assert np.allclose(coefficients(one.finish(), 2.0)[:, 0], 0.2)


def make_fold(method):
    s = make_sketcher(method, 2, 3)
    s.update(np.ones((1, 3)), np.ones(1))
    return s.finish()


def test_measures_and_planner():
    a, b = data(400, 20)
    row = fold("fd_ridge", a, b, 5)
    assert metrics.space_report(row)["rows"] == 5 and metrics.space_report(row)["floats"] <= 5 * 20 + 5 + 20
    v = np.random.default_rng(0).normal(size=20)
    assert metrics.sketch_norm(row, v) == pytest.approx(v @ gram_of(row) @ v)
    assert metrics.low_rank(row, 3).shape == (3, 20)
    assert metrics.log_slope([1, 2, 4, 8], [3, 12, 48, 192]) == pytest.approx(2)
    assert metrics.amortised_seconds(1.0, 0.5, 100, 10) == 6.0
    x, y = coefficients(row, 100.0)[:, 0], reference(a, b, 100.0)
    eps = certificate(row, 100.0)
    gap = np.abs(a @ (x - y))
    assert (gap <= bounds.prediction_gap_bound(eps, np.linalg.norm(y), 1.0) * np.linalg.norm(a, axis=1) + 1e-9).all()
    assert np.linalg.norm(a @ (x - y)) <= bounds.prediction_gap_bound(eps, np.linalg.norm(y), np.linalg.norm(a, 2))
    assert choose_method(4, 16)[0] == "exact_ridge" and choose_method(2048, 64)[0] == "robust_fd_ridge"
    assert choose_solver(5, 10) == "dual" and 2 <= choose_fan_in(256, 1 << 16) <= 64
    u = hash_uniform(np.arange(5000), 2, 1)
    assert 0 < u.min() and u.max() < 1 and abs(u.mean() - 0.5) < 0.02
