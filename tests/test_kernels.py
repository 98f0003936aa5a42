import math

import numpy as np
import pytest

from corrsentry.functions import kernels as K
from corrsentry.functions import special as S


def test_gamma_family():
    x = np.array([0.01, 0.3, 1.0, 2.5, 10.0, 300.0])
    assert np.allclose(S.lgamma(x), [math.lgamma(v) for v in x], atol=1e-10)
    assert abs(S.digamma(1.0) - S.PSI_ONE) < 1e-10
    assert np.allclose(S.digamma(x + 1) - S.digamma(x), 1 / x)
    assert np.allclose(S.trigamma(x) - S.trigamma(x + 1), 1 / x**2)
    assert np.allclose(S.digamma(S.inv_digamma(S.digamma(x))), S.digamma(x))
    for v in x:
        assert S.digamma1(v) == pytest.approx(float(S.digamma(v))) and S.trigamma1(v) == pytest.approx(float(S.trigamma(v))) and S.inv_digamma1(S.digamma1(v)) == pytest.approx(v, rel=1e-6)
    grid = (np.arange(20000) + 0.5) / 20000
    assert np.exp(S.beta_logpdf(grid, 2.5, 1.7)).mean() == pytest.approx(1, abs=1e-3)


def matrix(n, k, mu=0.2, inner=0.85, seed=0, noise=0.05):
    rng = np.random.default_rng(seed)
    m = np.full((n, n), mu)
    m[:k, :k] = inner
    e = rng.uniform(-noise, noise, (n, n))
    p = np.clip(m + np.triu(e, 1) + np.triu(e, 1).T, 0, 1)
    np.fill_diagonal(p, 1)
    return p


def test_lanczos_is_the_largest_eigenvalue_also_of_indefinite_matrices():
    rng = np.random.default_rng(1)
    for n in (1, 2, 5, 60):
        p = K.correlations(rng.normal(size=(n, 6)))
        lam, q, _ = K.lanczos(p)
        assert lam == pytest.approx(np.linalg.eigvalsh(p)[-1]) and np.allclose(p @ q, lam * q, atol=1e-5)
        assert 1 / n - 1e-12 <= lam / n <= 1 + 1e-12 and p.sum(1).min() / n - 1e-9 <= lam / n <= p.sum(1).max() / n + 1e-9
        assert K.lanczos(p, start=q)[0] == pytest.approx(lam)


def test_worked_example_and_invariances():
    a, b = np.array([1, 0, 2, 2, 0, 1.0]), np.array([0, 0, 1, 2, 1, 1.0])
    assert K.pearson(np.stack([a, b]))[0, 1] == pytest.approx(0.5941, abs=1e-4) == K.pearson(np.stack([a, 10 * b]))[0, 1]
    x = np.random.default_rng(2).normal(size=(20, 9))
    s = K.principal(K.correlations(x))[0]
    assert K.principal(K.correlations(x * np.arange(1, 21)[:, None]))[0] == pytest.approx(s)
    assert K.principal(K.correlations(x[::-1]))[0] == pytest.approx(s)
    assert (K.in_mode(np.array([[-0.4]]), "negative"), K.in_mode(np.array([[-0.4]]), "positive")) == (0.4, 0)


def test_repeats_in_a_sample_are_counted_without_copies():
    x = np.random.default_rng(3).normal(size=(8, 12))
    mult = np.array([0, 1, 2, 3, 0, 1, 0, 1])
    wide = np.repeat(x, mult, axis=0)
    p = np.abs(np.corrcoef(wide))
    s = K.sampled_score(x, mult)
    assert s.lam == pytest.approx(np.linalg.eigvalsh(p)[-1]) and s.score == pytest.approx(s.lam / 8)
    own = K.correlations(x)
    lam, q, _ = K.principal(own)
    full = K.sampled_score(x, np.ones(8, int))
    assert np.allclose(full.loading, K.loadings(own, q, lam))


def test_systematic_draws_add_up_and_follow_the_weights():
    rng = np.random.default_rng(4)
    w = rng.integers(1, 10**7, 200)
    total = np.zeros(200)
    for u in np.linspace(0, 0.999, 200):
        c = K.systematic(w, 40, u)
        assert c.sum() == 40 and (np.abs(c - 40 * w / w.sum()) < 1.001).all()
        total += c
    assert np.allclose(total / 200, 40 * w / w.sum(), atol=0.02)
    assert K.systematic(np.zeros(3, np.int64), 2).sum() == 0


@pytest.mark.parametrize("phi,want", [(0.2, 0.2452), (0.5, 0.4533)])
def test_two_block_prediction(phi, want):
    n = 800
    p = matrix(n, int(phi * n))
    score = K.lanczos(p)[0] / n
    assert score == pytest.approx(want, abs=3 / math.sqrt(n) / 10) and p.mean() <= score + 1e-12


def test_beta_fit_recovers_shapes_and_keeps_limits():
    rng = np.random.default_rng(5)
    x = rng.beta(6, 2, 20000)
    a, b = K.fit_beta(np.log(x).mean(), np.log1p(-x).mean(), 3, 3, 0.5, 1, rounds=500)
    assert a == pytest.approx(6, rel=0.08) and b == pytest.approx(2, rel=0.08)
    a, b = K.fit_beta(np.log(x).mean(), np.log1p(-x).mean(), 3, 3, 0.9, 1)
    assert a / (a + b) == pytest.approx(0.9) and a + b >= 1
    assert min(K.project(0.3, 0.3, 0, 1, True)) >= 1 - 1e-9


@pytest.mark.parametrize("schedule", ["synchronous", "sequential"])
def test_block_model_finds_planted_groups(schedule):
    p = matrix(120, 20, mu=0.15, inner=0.9)
    p[40:60, 40:60] = np.maximum(p[40:60, 40:60], 0.88)
    z = np.zeros(120, np.int64)
    z[:5], z[40:44] = 1, 2
    m = K.block_model(p, z, K.BlockConfig(k=2, schedule=schedule))
    assert set(np.flatnonzero(m.z == 1)) == set(range(20)) and set(np.flatnonzero(m.z == 2)) == set(range(40, 60))
    assert all(b >= a - 1e-6 for a, b in zip(m.history, m.history[1:])) and m.a[1] / (m.a[1] + m.b[1]) >= 0.75 - 1e-9
    none = K.block_model(p, np.zeros(120, np.int64))
    assert not none.z.any()


def test_seeds():
    p = matrix(60, 12, mu=0.1, inner=0.9)
    assert set(np.flatnonzero(K.neighbourhoods(p, 0.7, 2))) == set(range(12))
    p2 = matrix(40, 10, mu=0.1, inner=0.9)
    p2[20:30, 20:30] = np.maximum(p2[20:30, 20:30], 0.85)
    z = K.farthest_first(p2, np.r_[0:10, 20:30], 3)
    assert len(set(z[:10])) == 1 and len(set(z[10:])) == 1 and z[0] != z[10]


def brute_density(w):
    n = len(w)
    best = 0
    for m in range(1, 1 << n):
        at = [i for i in range(n) if m >> i & 1]
        best = max(best, w[np.ix_(at, at)].sum() / 2 / len(at))
    return best


def test_peeling_is_within_half_of_the_best():
    rng = np.random.default_rng(6)
    for _ in range(10):
        w = np.triu(rng.random((8, 8)) * (rng.random((8, 8)) < 0.5), 1)
        w = w + w.T
        keep, d = K.peel_dense(w)
        assert d >= brute_density(w) / 2 - 1e-9 and w[np.ix_(keep, keep)].sum() / 2 / len(keep) == pytest.approx(d)
        i, j = np.nonzero(np.triu(w))
    assert len(K.peel_dense(matrix(50, 10), "first_drop")[0]) >= 45
    rows, cols, d = K.peel_bipartite(np.array([0, 0, 1, 1, 2, 3]), np.array([0, 1, 0, 1, 2, 3]), np.array([9, 9, 9, 9, 1, 1.0]))
    assert rows.tolist() == [0, 1] and cols.tolist() == [0, 1] and d == 9


def test_topics_are_probabilities():
    r = K.gaussian_topics(np.random.default_rng(7).normal(size=(50, 3)), 4)
    assert r.shape == (50, 4) and np.allclose(r.sum(1), 1)


def test_block_model_reads_only_columns_of_grouped_entities():
    """The cost of a round is bounded by the group's share times n squared, and a sampled background gives the same groups."""
    p = matrix(900, 60, mu=0.15, inner=0.9)
    z = np.zeros(900, np.int64)
    z[:8] = 1
    c = K.Columns(p=p)
    cfg = K.BlockConfig(k=1, pairs=20_000)
    m = K.block_model(c, z, cfg)
    assert set(np.flatnonzero(m.z)) == set(range(60)) == set(np.flatnonzero(K.block_model(p, z, K.BlockConfig(k=1, pairs=10**6)).z))
    assert c.have.sum() < 900 / 5 and m.touched <= m.rounds * 60 / 900 * 900**2
    x = np.random.default_rng(3).normal(size=(50, 9))
    u = x - x.mean(1, keepdims=True)
    some = K.Columns(u=u / np.linalg.norm(u, axis=1, keepdims=True))
    some.need(np.array([4, 7]))
    assert np.allclose(some.p[:, [4, 7]], K.correlations(x)[:, [4, 7]]) and some.have.sum() == 2
