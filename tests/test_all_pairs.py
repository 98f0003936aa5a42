"""The background of the block model is that of all pairs, and products of known sign are those of the matrix."""

import numpy as np
import pytest

from corrsentry.functions import folded as FO
from corrsentry.functions import kernels as K
from corrsentry.operators.detect import DetectConfig, find


def window(n=700, group=90, m=14, seed=2):
    rng = np.random.default_rng(seed)
    x = rng.poisson(0.6, (n, m)).astype(float)
    x[:, 0] += 1
    x[x.std(1) == 0, 1] += 2
    t = rng.gamma(0.4, 4.0, m) + 0.1
    return np.concatenate([x, np.rint(rng.uniform(3, 9, (group, 1)) * t * 10 + rng.normal(0, 3, (group, m))).clip(0)])


def test_background_is_of_all_pairs():
    """A window of more pairs than were sampled: its few like pairs are all counted."""
    x = window()
    p, z = K.correlations(x), np.zeros(len(x), np.int64)
    z[700:730] = 1
    z[730:760] = 2
    r = p[np.triu_indices(len(x), 1)]
    w = np.clip(r, 1e-3, 1 - 1e-3)
    got, t = FO.Folded(x).opened(z, 2, 0.75)
    assert len(r) > 2 * 40_000
    assert got.pairs == len(r) and got.near * len(r) == pytest.approx((r >= 0.75).sum(), abs=0.5 + (np.abs(r - 1) < 1e-9).sum())
    assert (got.s, got.s1, got.s2) == pytest.approx((w.sum(), np.log(w).sum(), np.log1p(-w).sum()))
    for g in (1, 2):
        want = [f(np.clip(p, 1e-3, 1 - 1e-3))[:, z == g].sum(1) for f in (np.log, lambda v: np.log1p(-v))]
        for o, x_, self_ in zip(t, want, (np.log(1 - 1e-3), np.log1p(-(1 - 1e-3)))):
            assert np.allclose(o[:, g], x_ - (z == g) * self_)
    m = K.block_model(FO.Folded(x), z, K.BlockConfig())
    assert (m.z == K.block_model(p, z, K.BlockConfig()).z).all() and K.BlockConfig().pairs is None and m.near == got.near


@pytest.mark.parametrize("mode", K.MODES)
def test_products_of_known_sign_are_those_of_the_matrix(mode, monkeypatch):
    monkeypatch.setattr(FO, "TILE", 16)
    x = window(200, 300)
    x[5] = 3.0  # constant: 1 with itself, 0 with others
    p, f = K.correlations(x, mode), FO.Folded(x, mode)
    v = np.random.default_rng(1).normal(size=len(x))
    w = FO.Weighted(f, np.arange(f.size), np.ones(f.size))
    known = ~np.isnan(w.factors)
    assert f.size == len(x) and known.mean() > 0.2 and np.allclose(w.plain(v), p @ v)
    some = np.random.default_rng(2).permutation(len(x))[:150]
    assert np.allclose(f.product(some, v[:150]), p[:, some] @ v[:150])


def test_a_large_group_of_distinct_rows_costs_few_tiles(monkeypatch):
    x, made = window(600, 6000), []
    real = FO.Folded.tile
    monkeypatch.setattr(FO.Folded, "tile", lambda self, a, b: made.append(len(a) * len(b)) or real(self, a, b))
    found = find(1, np.arange(len(x)), x, DetectConfig(detectors=("direct",)))
    assert found["steps"].iloc[0] > 2 and sum(made) < len(x) ** 2  # one product by tiles alone makes half of it, and each step is one
    assert len(np.unique(x, axis=0)) > 6000
