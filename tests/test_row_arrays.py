"""Windows of series as arrays: the same rows and digests as by cells, and no row for each cell."""

import numpy as np
import pandas as pd

from corrsentry.operators import corr, matrix


def series(spark, seed=4):
    """Three entities with gaps or a late start among 40, copies among them."""
    x = np.random.default_rng(seed).integers(-4, 5, (20, 17))
    x = np.concatenate([x, x])
    rows = [(e, t, int(v)) for e, r in enumerate(x) for t, v in enumerate(r) if not (e == 3 and t == 6) and not (e == 7 and t < 9) and not (e == 8 and t > 2)]
    return spark.createDataFrame(pd.DataFrame(rows, columns=["entity", "period", "x"]))


def test_arrays_are_the_cells_rows(spark):
    c = series(spark)
    for length, step in ((5, 1), (4, 3), (17, 1), (18, 1)):
        want = {}
        for r in matrix.row_windows(c, length, step).collect():
            want.setdefault((r.win_id, r.entity), {})[int(r.feature)] = r.x
        got = {(r.win_id, r.entity): dict(enumerate(r.x, r.win_id)) for r in matrix.row_windows(c, length, step, arrays=True).collect()}
        assert got == want


def test_digests_are_those_of_cells(spark):
    c = series(spark)
    rows = matrix.row_windows(c, 6, 1, arrays=True)
    sort = lambda d: sorted(map(tuple, d.collect()))
    want = sort(corr.digest_dense(matrix.row_windows(c, 6, 1)))
    assert sort(corr.digest_dense(rows)) == want and len(want) == 12
    assert rows.count() * 6 == matrix.row_windows(c, 6, 1).count()
