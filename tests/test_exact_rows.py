"""The exact score of a window of many distinct rows does not hold their matrix."""

import tracemalloc

import numpy as np
import pytest

from corrsentry.functions import folded as FO
from corrsentry.functions import kernels as K
from corrsentry.operators.detect import DetectConfig, find


@pytest.mark.parametrize("mode", K.MODES)
def test_exact_is_exact(mode, monkeypatch):
    x = np.random.default_rng(1).poisson(1.0, (300, 11)).astype(float)
    p = K.correlations(x, mode)
    monkeypatch.setattr(FO, "EXACT", 20)
    lam, u, _ = FO.Weighted(FO.Folded(x, mode), np.arange(FO.Folded(x, mode).size), FO.Folded(x, mode).count).principal(1000)
    assert lam == pytest.approx(np.linalg.eigvalsh(p)[-1], rel=1e-12)


def test_memory_is_less_than_the_matrix():
    x = np.random.default_rng(5).gamma(1.0, 1.0, (6000, 12))
    tracemalloc.start()
    found = find(1, np.arange(6000), x, DetectConfig(detectors=("direct",), exact=100_000))
    peak = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    assert found["n_used"].iloc[0] == 6000 and peak < 6000**2 * 8 / 2
