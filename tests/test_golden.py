"""Published worked examples and formulas, and kernels against loops."""

import random

import numpy as np
import pytest

from lowrank_spark import config as C
from lowrank_spark.operators import cost, kernel, signhash, steps, theory, train
from lowrank_spark.plans import planner


def test_worked_hash_example():
    sums, code = signhash.hash_of_example([3, 4, 5], [[0, 0, 1], [0, 1, 0], [1, 0, 0]])
    assert sums == [-2.0, -4.0, -6.0] and code == [0, 0, 0]


def test_zero_sum_is_one():
    assert signhash.hash_of_example([2, 2], [[1], [0]]) == ([0.0], [1])


@pytest.mark.parametrize("n, graph, hash100, hash200", [(17770, 1204.578, 20.336, 40.672), (10677, 434.869, 12.219, 24.438), (12658, 611.209, 14.486, 28.972)])
def test_space(n, graph, hash100, hash200):
    mib = lambda b: b / 2**20
    assert mib(cost.space_bytes("graph", n)) == pytest.approx(graph, abs=2e-3)
    assert mib(cost.space_bytes("hash", n, 3, 100)) == pytest.approx(hash100, abs=1e-3)
    assert mib(cost.space_bytes("hash", n, 3, 200)) == pytest.approx(hash200, abs=1e-3)


def test_graph_cost_adds_up():
    for n, k in ((100, 5), (17770, 32)):
        c = cost.graph_ops(n, k)
        assert c["total"] == c["build"] + c["all_queries"] == n * (n - 1) + n * c["query"]


def test_published_ratios():
    assert 782.64 / 17.66 == pytest.approx(44.3, abs=0.05) and 17.66 / 0.09 == pytest.approx(196.22, abs=0.01)


def test_rotation_of_three():
    assert [(r, c) for s, w, r, c in train.plan(3) if s == 2] == [(2, 1), (3, 2), (1, 3)]
    for d in (1, 2, 3, 5):
        p = train.plan(d)
        assert len({(r, c) for _, _, r, c in p}) == d * d
        for s in range(1, d + 1):
            now = [(r, c) for a, _, r, c in p if a == s]
            assert len({r for r, _ in now}) == len({c for _, c in now}) == d


def test_collision_moves():
    assert theory.pair_probability(0.3, 3, 100) < theory.pair_probability(0.3, 2, 100)
    assert theory.pair_probability(0.3, 3, 200) > theory.pair_probability(0.3, 3, 100)
    p, q = theory.plan_pq(0.9, 0.5, 0.99, 0.2)
    assert theory.pair_probability(0.9, p, q) >= 0.99 and theory.pair_probability(0.5, p, q) <= 0.2


def test_planner():
    s = planner.Sizes(10**6, 10**5, 10**8, row_degree_sq=10**12, task_bytes=1 << 30)
    assert planner.choose_topk(s, 10**9) == "hash" and planner.choose_topk(s, 10**13) == "exact"
    many = planner.Sizes(10**9, 10**9, 40 * 10**9, task_bytes=1 << 34)
    assert planner.choose_sgd(many, 32, 32, 8) == "rotation" and planner.choose_sgd(many, 32, 32, 1000) == "gather"


def test_step_schedule():
    assert steps.rate(0.04, 0.3, 0) == 0.04 and steps.rate(0.04, 0.3, 4) == pytest.approx(0.04 / (1 + 0.3 * 8))


def _block(seed=0, m=12, n=9, f=3, k=4, e=60):
    rng = np.random.default_rng(seed)
    pairs = rng.permutation(m * n)[:e]
    ex = rng.random((e, k)) < 0.5
    res = np.where(ex, rng.normal(0, 1, (e, k)), 0)
    return kernel.Block(pairs // n, pairs % n, rng.integers(1, 6, e).astype(float), rng.normal(0, 0.1, m), rng.normal(0, 0.1, (m, f)), rng.normal(0, 0.1, n), rng.normal(0, 0.1, (n, f)), rng.normal(0, 0.1, (n, k)), rng.normal(0, 0.1, (n, k)), res, ex.astype(float), (~ex).astype(float))


def test_waves_equal_a_serial_loop():
    cfg = C.blend_config(0.02, 0.01, 0.01, 0.05, F=3, K=4)
    x, y = _block(), _block()
    kernel.sgd(x, 3.0, cfg, 2)
    g = {p: kernel.rate(getattr(cfg.alpha, p), cfg.beta, 2) for p in ("b", "bh", "u", "v", "w", "c")}
    for s in kernel.waves(y.rows, y.cols):
        for e in s:
            i, j = y.rows[e], y.cols[e]
            n_ex, n_im = y.is_ex[e].sum(), y.is_im[e].sum()
            sx, si = (n_ex**-0.5 if n_ex else 0), (n_im**-0.5 if n_im else 0)
            pred = 3.0 + y.b[i] + y.bh[j] + sx * sum(y.res[e] * y.w[j]) + si * sum(y.is_im[e] * y.c[j]) + sum(y.u[i] * y.v[j])
            err = y.r[e] - pred
            u, v = y.u[i].copy(), y.v[j].copy()
            y.b[i] += g["b"] * (err - cfg.lam.b * y.b[i])
            y.bh[j] += g["bh"] * (err - cfg.lam.bh * y.bh[j])
            for k in range(4):
                if y.is_ex[e, k]:
                    y.w[j, k] += g["w"] * (sx * err * y.res[e, k] - cfg.lam.w * y.w[j, k])
                else:
                    y.c[j, k] += g["c"] * (si * err - cfg.lam.c * y.c[j, k])
            y.u[i] = u + g["u"] * (err * v - cfg.lam.u * u)
            y.v[j] = v + g["v"] * (err * u - cfg.lam.v * v)
    for name in ("b", "bh", "u", "v", "w", "c"):
        np.testing.assert_allclose(getattr(x, name), getattr(y, name), atol=1e-12)


def test_update_follows_the_gradient():
    cfg = C.blend_config(1e-5, 1e-5, 0.0, 0.0, F=3, K=4).but(beta=0.0)
    for loss_kind in ("squared", "logistic"):
        c = cfg.but(loss=loss_kind)
        x = _block(3, e=1)
        x.r[:] = 1.0

        def loss(b):
            s = kernel.predict_entries(b, np.array([0]), 0.5, c)[0]
            return 0.5 * (b.r[0] - s) ** 2 if loss_kind == "squared" else np.log1p(np.exp(-s))

        y = _block(3, e=1)
        y.r[:] = 1.0
        kernel.sgd(y, 0.5, c, 0)
        for name in ("b", "bh", "u", "v", "w", "c"):
            at = np.argwhere(getattr(x, name) != getattr(y, name))
            for a in map(tuple, at[:3]):
                z = _block(3, e=1)
                z.r[:] = 1.0
                h = 1e-6
                getattr(z, name)[a] += h
                up = loss(z)
                getattr(z, name)[a] -= 2 * h
                slope = (up - loss(z)) / (2 * h)
                assert (getattr(y, name)[a] - getattr(x, name)[a]) / 1e-5 == pytest.approx(-slope, rel=1e-3, abs=1e-6)


def test_waves_cover_once_without_conflicts():
    rng = random.Random(4)
    r, c = np.array([rng.randrange(7) for _ in range(80)]), np.array([rng.randrange(5) for _ in range(80)])
    seen = []
    for s in kernel.waves(r, c):
        assert len(set(r[s])) == len(s) == len(set(c[s]))
        seen += s.tolist()
    assert sorted(seen) == list(range(80))


def test_ridge_rows():
    rng = np.random.default_rng(1)
    own, r, v = rng.integers(0, 5, 40), rng.normal(size=40), rng.normal(size=(40, 3))
    ids, sol = kernel.ridge_rows(own, r, v, 0.3, weighted=False)
    for i, x in zip(ids, sol, strict=True):
        a = v[own == i]
        np.testing.assert_allclose(x, np.linalg.solve(a.T @ a + 0.3 * np.eye(3), a.T @ r[own == i]), atol=1e-10)
