"""Windows with many entities: equal rows are kept once, products are made by tiles, and the results are those of all."""

import tracemalloc

import numpy as np
import pandas as pd
import pytest

from corrsentry.functions import folded as FO
from corrsentry.functions import kernels as K
from corrsentry.operators.corr import as_array, as_rows
from corrsentry.operators.detect import DetectConfig, find


def counts(n, m=12, kinds=40, seed=0):
    rng = np.random.default_rng(seed)
    x = rng.poisson(0.4, (kinds, m)).astype(float)
    x[:, 0] += 1
    x[x.std(1) == 0, 1] += 3
    return x[rng.integers(0, kinds, n)]


@pytest.mark.parametrize("mode", K.MODES)
def test_copies_count_as_often_as_they_are(mode, monkeypatch):
    monkeypatch.setattr(FO, "TILE", 7)
    monkeypatch.setattr(FO, "KEEP", 0)
    x = counts(150)
    p, f = K.correlations(x, mode), FO.Folded(x, mode)
    assert (f.size < 60) == (mode != "negative")
    lam, q, _ = K.principal(p)
    got, u, _ = f.all.principal()
    assert got == pytest.approx(lam) and np.allclose(f.all.loadings(u, got)[f.of], K.loadings(p, q, lam), atol=1e-6)
    at = np.arange(20, 90)
    assert f.inside(at) == pytest.approx((p[np.ix_(at, at)].sum() - len(at)) / 2)
    assert f.scored(at)[0] == pytest.approx(K.principal(p[np.ix_(at, at)])[0])
    if mode in ("abs", "positive"):
        c = K.Columns(p=p)
        assert (f.farthest_first(at, 3) == K.farthest_first(p, at, 3)).all() and (f.neighbourhoods(0.7, 3) == K.neighbourhoods(p, 0.7, 3)).all()
        c.need(np.arange(150))
        for a, b in zip(f.moved(at[:30], at[40:]), c.moved(at[:30], at[40:])):
            assert np.allclose(a, b)
        z = np.zeros(150, np.int64)
        z[:6], z[6:12] = 1, 2
        for schedule in ("synchronous", "sequential"):
            cfg = K.BlockConfig(schedule=schedule, max_iter=5)
            assert (K.block_model(FO.Folded(x, mode), z, cfg).z == K.block_model(p, z, cfg).z).all()


def test_sparse_rows_give_the_same_findings():
    rng = np.random.default_rng(4)
    row, col = rng.integers(0, 300, 3000), rng.integers(0, 900, 3000)
    cells = pd.DataFrame({"win_id": 1, "entity": row, "feature": [f"w{c}" for c in col], "x": rng.integers(1, 4, 3000)})
    e, x = as_array(cells)
    e2, s = as_rows(cells, dense=0)
    assert isinstance(s, FO.Sparse) and (e == e2).all() and (s.dense() == x).all()
    cfg = DetectConfig(detectors=("direct", "sampled", "block", "cascade", "peel"), loading_cut=0.1)
    a, b = (find(1, e, v, cfg).drop(columns=["seconds", "steps"]) for v in (x, s))
    pd.testing.assert_frame_equal(a, b, check_exact=False, atol=1e-9)


def test_a_large_window_is_judged_without_its_matrix():
    x = counts(6000, kinds=500)
    tracemalloc.start()
    found = find(1, np.arange(6000), x, DetectConfig(detectors=("direct", "sampled", "block", "cascade", "peel")))
    peak = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    assert set(found["n_used"]) == {6000} and peak < 150 << 20 < 6000**2 * 8
