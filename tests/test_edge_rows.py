"""Pairs named together are summed by blocks of entities, without a row for each pair and window."""

import numpy as np
import pandas as pd
import pytest

from corrsentry.operators import alerts, corr


def test_summary_of_rows_is_that_of_pairs(spark, monkeypatch):
    rng = np.random.default_rng(3)
    x = rng.poisson(0.8, (4, 60, 9))
    x[1, 5] = 2  # does not vary
    w, e, f = np.nonzero(x)
    cells = spark.createDataFrame(pd.DataFrame({"win_id": w, "entity": e - 20, "feature": np.char.add("f", f.astype(str)).astype(object), "x": x[w, e, f].astype(float)}))
    named = [(int(win), int(ent) - 20) for win in range(3) for ent in rng.permutation(60)[:40]]  # nobody in the last window
    m = spark.createDataFrame(pd.DataFrame(named + named[:5], columns=["win_id", "entity"]))
    want = alerts.edge_summary(corr.pairs_among(cells, m), m, 0.4).toPandas().set_index(["i", "j"]).sort_index()
    assert want["windows"].max() == 3 and want["strong"].max() > 0
    rows, real = corr.pairs_among(cells, m, rows=True), alerts._edges_of_rows
    for tile in (7, 1024):
        monkeypatch.setattr(alerts, "_edges_of_rows", lambda r, cut, tile=tile: real(r, cut, tile))
        got = alerts.edge_summary(rows, m, 0.4).toPandas()
        assert (got["i"] < got["j"]).all() and len(got) == len(want)
        got = got.set_index(["i", "j"]).sort_index()
        assert (got[["windows", "strong"]] == want[["windows", "strong"]]).all().all() and got["mean_rho"].to_numpy() == pytest.approx(want["mean_rho"].to_numpy())
