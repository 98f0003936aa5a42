"""What a task's Python worker holds of a large window: distinct rows and one batch, not all entities' rows or findings."""

import tracemalloc

import numpy as np
import pandas as pd

from corrsentry.operators.corr import as_array, as_rows
from corrsentry.operators.detect import DetectConfig, detect, find

ALL = ("direct", "sampled", "block", "peel")


def batches(n, kinds, m=50, per=3, seed=3):
    """Cells of n entities, copies of `kinds` rows with `per` features each, in batches."""
    rng = np.random.default_rng(seed)
    used, x = np.argsort(rng.random((kinds, m)), 1)[:, :per], rng.integers(1, 3, (kinds, per))
    of = np.arange(n) % kinds
    cells = pd.DataFrame({"win_id": 1, "entity": np.repeat(np.arange(n), per), "feature": np.char.add("f", used[of].ravel().astype(str)).astype(object), "x": x[of].ravel()})
    return [cells.iloc[lo : lo + 10_000] for lo in range(0, len(cells), 10_000)]


def peak_of(f):
    tracemalloc.start()
    out = f()
    top = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    return out, top >> 20


def test_batches_give_the_window_of_their_cells():
    own = batches(700, 90)
    e, x = as_array(pd.concat(own))
    for dense in (0, 1 << 20):
        e2, y = as_rows(iter(own), dense=dense)
        assert (e == e2).all() and ((y if dense else y.dense()) == x).all()


def test_copies_are_folded_before_there_are_dense_rows():
    own = batches(80_000, 1300)
    found, mb = peak_of(lambda: find(1, *as_rows(pd.concat(own)), DetectConfig(detectors=ALL)))
    assert set(found["n_used"]) == {80_000} and mb < 80  # the array of all rows alone has 32 MB, and was copied several times


def test_few_tiles_are_kept():
    x = np.random.default_rng(5).poisson(3.0, (5500, 12)).astype(float)
    found, mb = peak_of(lambda: find(1, np.arange(5500), x, DetectConfig(detectors=("direct",))))
    assert found["n_used"].iloc[0] == 5500 and mb < 120  # all tiles of the upper triangle have more


def test_scores_need_no_member_rows(spark):
    cells = spark.createDataFrame(pd.concat(batches(300, 5)))
    cfg = DetectConfig(detectors=ALL, loading_cut=0.0)
    every, heads = detect(cells, cfg).drop("seconds").toPandas(), detect(cells, cfg, named=False).drop("seconds").toPandas()
    assert every["entity"].notna().any() and heads["entity"].isna().all()
    pd.testing.assert_frame_equal(every[every["entity"].isna()].reset_index(drop=True), heads)
