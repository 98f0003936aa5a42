"""Windows that no task holds: products are made from blocks of distinct rows, and no table of pairs or tiles is written."""

import numpy as np
import pandas as pd
import pytest

from corrsentry.functions import kernels as K
from corrsentry.functions.folded import Folded
from corrsentry.operators import corr, detect
from corrsentry.plans import planner, spread
from corrsentry.plans.sampled_large import sampled_large


def cells_of(spark, x, win=1):
    i, j = np.nonzero(x)
    return spark.createDataFrame(pd.DataFrame({"win_id": win, "entity": i, "feature": np.char.add("f", (100 + j).astype(str)).astype(object), "x": x[i, j].astype(np.int64)}))


def rows(kinds=30, copies=5, m=9, seed=0):
    x = np.random.default_rng(seed).poisson(1.0, (kinds, m))
    x[:, 0] += 1
    x[x.std(1) == 0, 1] += 2
    return np.concatenate([x] * copies)


@pytest.mark.parametrize("mode", K.MODES)
def test_sums_of_spread_rows_are_those_of_one_task(spark, mode):
    x = rows()
    cols = spread.classes(corr.columns(cells_of(spark, x)), mode).cache()
    tiled = spread.row_tiles(cols.where("entity = rep").select("win_id", "entity", "x"), 8).cache()
    ids = cols.select("entity", "rep").toPandas().sort_values("entity")
    f, s = Folded(x.astype(float), mode), spread.Spread(tiled, ids["entity"].to_numpy(), ids["rep"].to_numpy(), mode, 1e-3)
    assert s.size == f.size == (30 if mode != "negative" else 150) and tiled.count() > 3
    some = np.arange(10, 90)
    assert s.all.principal()[0] == pytest.approx(f.all.principal()[0]) and s.scored(some)[0] == pytest.approx(f.scored(some)[0])
    assert s.inside(some) == pytest.approx(f.inside(some))
    if mode in ("abs", "positive"):
        for a, b in zip(s.moved(some[:20], some[50:]), f.moved(some[:20], some[50:])):
            assert np.allclose(a, b)
        p = K.correlations(x.astype(float), mode)
        # copies are 1 by a hair in p
        assert s.near(0.6) == pytest.approx((p[np.triu_indices(150, 1)] >= 0.6).mean())


def test_copies_add_no_tiles_and_change_no_finding(spark, monkeypatch):
    rng = np.random.default_rng(2)
    x = rows(40, 20, seed=1)
    group = np.rint(rng.uniform(20, 40, (60, 1)) * np.array([1, 0, 5, 0, 2, 0, 9, 0, 1])).astype(int)
    cells = cells_of(spark, np.concatenate([x, group, group])).cache()
    cfg, made = detect.DetectConfig(detectors=("direct", "sampled", "block", "cascade"), block=K.BlockConfig(k=1)), []
    real = spread.row_tiles
    monkeypatch.setattr(spread, "row_tiles", lambda cols, tile: made.append(cols.count()) or real(cols, tile))
    small, large = detect.detect(cells, cfg).cache(), planner.detect_any(cells, cfg, planner.Limits(exact=1, one_task=1), 32).cache()
    best = lambda f: {(r.win_id, r.detector): (round(r.score, 6), r.alert, r.n_members) for r in detect.best_scores(f).collect()}
    named = lambda f: {tuple(r) for r in detect.members(f, False).select("detector", "group_id", "entity").collect()}
    assert best(large) == best(small) and named(large) == named(small) and len(named(small)) > 100
    assert made[0] <= 100  # of 920 entities


def test_a_sampled_copy_is_held_once(spark):
    x = rows(12, 50)
    n = {(r.n_sample, round(r.score, 9), round(r.lambda1, 6)) for r in sampled_large(cells_of(spark, x), r=0.5).collect()}
    assert len(n) == 1
    assert 12 < next(iter(n))[0] <= 600  # entities drawn, not distinct rows


def test_findings_do_not_depend_on_the_path(spark):
    """Two groups, as many of the block model's groups, over 20,480 draws' worth of entities left uncut, and a limit of tiles passed."""
    rng = np.random.default_rng(6)
    one, two = np.array([9, 0, 0, 5, 0, 0, 2, 0, 0]), np.array([0, 8, 0, 0, 4, 0, 0, 0, 6])
    group = lambda t: np.rint(rng.uniform(20, 40, (15, 1)) * t + rng.normal(0, 1, (15, 9))).clip(0).astype(int)
    cells = cells_of(spark, np.concatenate([rows(40, 12, seed=1), group(one), group(two)])).cache()
    cfg = detect.DetectConfig(detectors=("direct", "sampled", "block", "cascade"), loading_cut=0.3, threshold=0.3)
    small, large = (f.cache() for f in (detect.detect(cells, cfg), planner.detect_any(cells, cfg, planner.Limits(exact=1, one_task=1, tiled=2), 64)))
    heads = lambda f: sorted((r.detector, r.group_id, round(r.score, 6), r.alert, r.n_members, round(r.strength, 6)) for r in detect.scores(f).collect())
    named = lambda f: {(r.detector, r.group_id, r.entity, round(r.loading, 5)) for r in detect.members(f, False).collect()}
    assert heads(large) == heads(small) and named(large) == named(small)
    assert {h[1] for h in heads(small) if h[0] == "block"} == {1, 2}


def test_a_share_is_drawn_whatever_the_number():
    x = np.tile(rows(40, 1, seed=3).astype(float), (600, 1))
    found = detect.find(1, np.arange(len(x)), x, detect.DetectConfig(detectors=("sampled",), weighting="uniform"))
    assert len(x) == 24_000 and found["sample"].iloc[0] == 4800
