"""Baselines and the second phase on blocks that stay in Spark, against their array forms and closed forms."""

import numpy as np
import pytest

from featgreedy.baselines import sparse, spread
from featgreedy.functions.families import LOGIT
from featgreedy.operators import layout, moments
from featgreedy.operators.greedy import rga
from featgreedy.operators.model import SRGConfig, fit
from featgreedy.operators.moments import ArrayMoments, GramMoments
from featgreedy.operators.refit import required_iters


@pytest.fixture(scope="module")
def scalar(spark):
    rng = np.random.default_rng(50)
    x = rng.standard_normal((120, 8))
    y = x[:, :2] @ np.array([3.0, -2.0]) + 0.3 * rng.standard_normal(120)

    def frames(y, width=1, seg=50):
        wide = spark.createDataFrame([(i, r.tolist(), [float(z)]) for i, (r, z) in enumerate(zip(x, y, strict=True))], "t long, f array<double>, y array<double>")
        return layout.to_blocks(wide, [width] * (8 // width), seg).cache(), layout.to_segments(wide, seg).cache()

    return x, y, frames


def test_coordinate_descent_on_blocks(scalar):
    x, y, frames = scalar
    b, losses, ledger = spread.coord_descent(*frames(y, 2), 0.05, 0.5, 2.0, 6, nodes=3)
    want, errs, led = sparse.coord_descent(x, y, 0.05, 0.5, 3, 6, damp=2.0)
    assert np.allclose(b, want) and np.allclose(losses, errs) and ledger.total() == led.total()


def test_penalised_logit_on_blocks(scalar):
    x, y, frames = scalar
    z = (y > 0).astype(float)
    b, losses = spread.l1_glm(*frames(z, 4), LOGIT, 0.05, 12, 0.6)
    assert all(a >= c - 1e-12 for a, c in zip(losses, losses[1:], strict=False))
    own = np.zeros(8)
    for _ in range(12):
        own = sparse.soft(own + x.T @ (z - LOGIT.mean(x @ own)) / 120 / 0.6, 0.05 / 0.6)
    assert np.allclose(b, own)


def test_sharing_on_blocks(scalar):
    x, y, frames = scalar
    assert np.allclose(spread.sharing_admm(*frames(y), 0.02, nodes=3, rounds=4), sparse.sharing_admm(x, y, 0.02, nodes=3, rounds=4), atol=1e-6)


def test_row_batches_and_sketched_dual(scalar):
    x, y, frames = scalar
    b = spread.row_sgd(*frames(y), epochs=3, rate=1.0)
    assert ((y - x @ b) ** 2).mean() < 0.7 * (y * y).mean()
    got, sent = spread.sketch_ridge(*frames(y, 4, 200), 0.1, 2, 40)
    assert np.allclose(got, np.linalg.solve(x.T @ x + 12 * np.eye(8), x.T @ y), atol=1e-6) and sent > 0


def test_second_phase_in_rows_equals_inner_products(spark, monkeypatch):
    rng = np.random.default_rng(51)
    x = rng.standard_normal((90, 12))
    y = x[:, :3] @ rng.standard_normal((3, 2)) * 4 + x[:, 6:9] @ rng.standard_normal((3, 2)) + rng.standard_normal((90, 2))
    wide = spark.createDataFrame([(i, r.tolist(), z.tolist()) for i, (r, z) in enumerate(zip(x, y, strict=True))], "t long, f array<double>, y array<double>")
    b, s = layout.to_blocks(wide, [3] * 4, 45), layout.to_segments(wide, 45)
    config = SRGConfig(radius=50.0, threshold=0.02, cap=4, refit_iters=5, refit_tol=0.0)
    held = fit(b, s, config)
    monkeypatch.setattr(moments, "GRAM_BYTES", 100)
    rows = fit(b, s, config)
    assert [(r["k"], r["j"]) for r in rows.phase2.trace] == [(r["k"], r["j"]) for r in held.phase2.trace]
    assert held.support == rows.support and all(np.allclose(held.coef[j], rows.coef[j]) for j in held.coef)


def test_array_moments_take_the_same_path():
    rng = np.random.default_rng(52)
    x, y = rng.standard_normal((60, 20)), rng.standard_normal((60, 3))
    g = GramMoments(range(5), [4] * 5, x.T @ x, x.T @ y, (y * y).sum(), 60)
    a = ArrayMoments(x, y, 4)
    one, two = rga(g, 20.0, 12), rga(a, 20.0, 12)
    assert [(r["j"], round(r["loss"], 10)) for r in one.trace] == [(r["j"], round(r["loss"], 10)) for r in two.trace]
    assert np.allclose(a.only([1, 3]).g, g.only([1, 3]).g)


def test_required_steps_reach_the_noise_floor():
    """The bound's steps bring phase two within the noise of its limit."""
    from featgreedy.operators.refit import refit

    rng = np.random.default_rng(53)
    x, noise = rng.standard_normal((200, 12)), rng.standard_normal((200, 4))
    y = x[:, :3] @ (5 * np.outer(rng.standard_normal(3), rng.standard_normal(4))) + noise
    m = GramMoments(range(4), [3] * 4, x.T @ x, x.T @ y, (y * y).sum(), 200)
    xi = float(np.linalg.norm(x[:, :3].T @ noise, 2))
    k = required_iters({0: 3}, 4, 1, xi, 200, tau=20)
    short, long = refit(m.only([0]), {0: 1}, 200.0, k, 0.0), refit(m.only([0]), {0: 1}, 200.0, 20 * k, 0.0)
    gap = np.linalg.norm(short.coef()[0] - long.coef()[0])
    assert gap <= xi / 200


def test_sketched_ridge_over_many_rows_and_segments(spark):
    """No matrix of rows by rows; several row segments give the ridge of one."""
    from featgreedy.baselines import lowrank

    rng = np.random.default_rng(2)
    for n, k in ((9, 4), (4, 9)):
        s, r = rng.standard_normal((n, k)), rng.standard_normal(n)
        assert np.allclose(lowrank.ridge_inverse(s, 0.7)(r), np.linalg.solve(s @ s.T + 0.7 * np.eye(n), r))
    x = rng.standard_normal((40_000, 6))
    y = x @ np.arange(6.0) + rng.standard_normal(len(x))
    b, _ = lowrank.dual_sketch_ridge(x, y, 0.1, 1, nodes=3, iters=30)
    assert np.allclose(b, np.linalg.solve(x.T @ x + 0.1 * len(x) * np.eye(6), x.T @ y), atol=1e-6)
    wide = spark.createDataFrame([(i, x[i].tolist(), [float(y[i])]) for i in range(300)], "t long, f array<double>, y array<double>")
    got, _ = spread.sketch_ridge(layout.to_blocks(wide, [3, 3], 128), layout.to_segments(wide, 128), 0.1, 2, 30)
    assert np.allclose(got, np.linalg.solve(x[:300].T @ x[:300] + 30 * np.eye(6), x[:300].T @ y[:300]), atol=1e-6)


def test_row_batches_meet_all_segments_in_one_pass(spark):
    """jobs don't grow with the segments; the steps are those of plain arrays, also with more columns than rows in a segment."""
    from featgreedy.functions.draws import py_unif

    rng = np.random.default_rng(60)
    x = rng.standard_normal((100, 6))
    y = x @ np.arange(6.0) + rng.standard_normal(100)
    wide = spark.createDataFrame([(i, x[i].tolist(), [float(y[i])]) for i in range(100)], "t long, f array<double>, y array<double>")

    def plain(seg, epochs):
        count = -(-100 // seg)
        top, b = (x * x).sum() / count, np.zeros(6)
        for e in range(epochs):
            for h in sorted(range(count), key=lambda h: py_unif(f"sgd|{e}|{h}")):
                i = slice(h * seg, (h + 1) * seg)
                b = b + 0.5 / (1 + e) / top * (x[i].T @ (y[i] - x[i] @ b) - 0.1 * b)
        return b

    def spent(seg, epochs):
        frames = layout.to_blocks(wide, [3, 3], seg).cache(), layout.to_segments(wide, seg).cache()
        spark.sparkContext.setJobGroup(f"rows{seg}", "row mini-batches")
        got = spread.row_sgd(*frames, lam=0.1, epochs=epochs)
        jobs = len(spark.sparkContext.statusTracker().getJobIdsForGroup(f"rows{seg}"))
        spark.sparkContext.setLocalProperty("spark.jobGroup.id", None)
        assert np.allclose(got, plain(seg, epochs), atol=1e-10)
        return jobs

    assert spent(7, 2) <= 40  # 15 segments, each met twice
    spent(50, 1)
    small = layout.to_blocks(wide, [3, 3], 4), layout.to_segments(wide.filter("t < 12"), 4)
    got = spread.row_sgd(small[0].filter("h < 3").cache(), small[1].cache(), epochs=1)
    x, y = x[:12], y[:12]
    b, top = np.zeros(6), (x * x).sum() / 3
    for h in sorted(range(3), key=lambda h: py_unif(f"sgd|0|{h}")):
        i = slice(4 * h, 4 * h + 4)
        b = b + 0.5 / top * x[i].T @ (y[i] - x[i] @ b)
    assert np.allclose(got, b, atol=1e-10)


def test_coordinate_rounds_and_sketched_dual_from_moments():
    """the same rounds, errors, coefficients and bytes from inner products as from the rows."""
    from featgreedy.baselines import lowrank

    rng = np.random.default_rng(61)
    x = rng.standard_normal((150, 12))
    y = x[:, 0] * 2 - x[:, 5] + 0.2 * rng.standard_normal(150)
    m = GramMoments(range(12), [1] * 12, x.T @ x, x.T @ y[:, None], y @ y, 150)
    truth = rng.standard_normal(12)
    for options in ({"damp": 2.0}, {}, {"accel": True, "damp": 16.0}, {"damp": 2.0, "truth": truth}):
        b, errs, led = sparse.coord_descent(x, y, 0.05, 0.5, 3, 30, **options)
        got, found, sent = sparse.coord_descent(m, None, 0.05, 0.5, 3, 30, **options)
        assert np.allclose(b, got) and np.allclose(errs, found) and led.total() == sent.total()
    for k, iters in ((2, 8), (2, 60), (9, 20)):
        b, sent = lowrank.dual_sketch_ridge(x, y, 0.1, k, 3, iters)
        got, again = lowrank.dual_sketch_ridge(m, None, 0.1, k, 3, iters)
        assert np.allclose(b, got) and sent == again


def test_communication_holds_no_rows_on_the_driver(spark, monkeypatch):
    """moments drawn chunk by chunk in tasks are those of the whole fixture; the query brings no predictors to the driver."""
    import __spark_entry__
    from featgreedy.sources import planted

    d = "/root/testdata/sf0.001"
    x = planted.local(planted.predictors(spark, d, 192))
    monkeypatch.setattr(planted, "TAIL_BYTES", 8 * 192 * 70)
    coef = np.full((8, 1), 3.0)
    got = planted.heavy_moments(planted.predictors(spark, d, 192), len(x), (100, 192), "comm|0", "comm|noise", coef)
    for p, m in got.items():
        f = planted.plant_scalar(x[:, :p], "comm|0", train=None)
        want = planted.Planted(f.x, f.x[:, :8] @ coef + planted.t_noise("comm|noise", len(f.x), 1), f.x_test, f.y_test, {}, 1).moments()
        assert m.n == want.n and np.isclose(m.yy, want.yy) and m.ids == want.ids
        assert np.allclose(m.g, want.g) and np.allclose(m.c0, want.c0) and np.allclose(m.sums, want.sums)

    def held(wide):
        raise AssertionError("the predictors came to the driver")

    monkeypatch.setattr(planted, "local", held)
    rows = {(r["columns"], r["method"]): r["bytes"] for r in __spark_entry__.queries()["workload_communication"](spark, d).collect()}
    assert len(rows) == 15 and rows[192, "two_phase_state"] % (375 * 8 * 4) == 0
