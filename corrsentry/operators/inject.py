"""Correlated groups injected into ordinary windows, with their truth, in three regimes and a control.

big     a fifth to a half of all entities
strong  a twentieth to a fifth of the entities, of such magnitude that the sampled score should pass the threshold
hidden  20 to 200 entities (at most 15 % of a small window) of ordinary magnitude

Members follow one template over the features, scaled and disturbed so that their mutual correlation is near `inner`.
All randomness comes from the seed, the window and the regime.  Injected entities have negative ids.
"""

from __future__ import annotations

from collections.abc import Iterator
from typing import NamedTuple

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .corr import as_array

REGIMES = ("control", "big", "strong", "hidden")
CODES = len(REGIMES)
#: Rows that are handed over at once.
BATCH = 100_000
INJECTED = "win_id long, base_win long, regime string, entity long, feature string, x double, injected boolean"


class InjectConfig(NamedTuple):
    kind: str = "log"  # or "price": signed changes, signs may flip
    inner: float = 0.92
    strong_share: float = 0.85  # of the magnitude
    p: float = 1.4
    hidden_share: float = 0.0  # of the magnitude; 0: ordinary magnitude
    calibrate: float = 0.0  # big groups of the size that should lift the direct score just over this; 0: a fifth to a half
    seed: int = 11


def group_size(regime: str, n: int, rng: np.random.Generator) -> int:
    """Injected entities beside n ordinary ones."""
    if regime == "big":
        share = rng.uniform(0.2, 0.5)
    elif regime == "strong":
        share = rng.uniform(0.05, 0.2)
    else:
        k = int(rng.integers(20, 201))
        return max(3, min(k, int(0.15 * n)) if n < 1400 else k)
    return max(3, int(round(n * share / (1 - share))))


def needed_share(mu: float, inner: float, score: float) -> float:
    """Share of a group whose two-block mean matrix (mu outside, `inner` inside) has the score; at most 0.95."""
    lo, hi = 0.0, 0.95
    for _ in range(40):
        s = (lo + hi) / 2
        top = np.linalg.eigvalsh([[inner * s, mu * np.sqrt(s * (1 - s))], [mu * np.sqrt(s * (1 - s)), mu * (1 - s)]])[-1]
        lo, hi = (s, hi) if top < score else (lo, s)
    return hi


def members_of(template: np.ndarray, k: int, inner: float, rng: np.random.Generator, flip: bool) -> np.ndarray:
    """(k, M) scaled copies with noise; the noise level gives pairs the correlation `inner`."""
    t = template - template.mean()
    noise = t.std() * np.sqrt(max(1 / inner - 1, 0.0))
    scale = rng.uniform(0.6, 1.6, (k, 1))
    x = scale * (template + rng.normal(0, noise, (k, len(template))))
    return x * rng.choice([-1.0, 1.0], (k, 1)) if flip else x


def scaled(x: np.ndarray, base: np.ndarray, regime: str, cfg: InjectConfig) -> np.ndarray:
    """x brought to the regime's magnitude against the ordinary entities."""
    size = lambda a: (np.abs(a) ** cfg.p).sum(1) ** (1 / cfg.p)
    ordinary = size(base)
    if regime == "strong":
        goal = cfg.strong_share / (1 - cfg.strong_share) * ordinary.sum()
    elif regime == "hidden" and cfg.hidden_share > 0:
        goal = cfg.hidden_share / (1 - cfg.hidden_share) * ordinary.sum()
    else:
        goal = ordinary.mean() * len(x) * (1.5 if regime == "big" else 1.0)
    return x * goal / max(size(x).sum(), 1e-12)


def injected_window(win: int, e: np.ndarray, x: np.ndarray, regime: str, cfg: InjectConfig) -> tuple[np.ndarray, np.ndarray]:
    """(negative ids, rows) to add to a window."""
    if regime == "control" or len(e) < 3:
        return np.zeros(0, np.int64), np.zeros((0, x.shape[1]))
    rng = np.random.default_rng([cfg.seed, win % (1 << 32), REGIMES.index(regime)])
    k = group_size(regime, len(e), rng)
    if regime == "big" and cfg.calibrate:
        i = rng.integers(0, len(x), 2000)
        j = (i + rng.integers(1, len(x), 2000)) % len(x)
        c = x - x.mean(1, keepdims=True)
        c /= np.maximum(np.sqrt((c * c).sum(1, keepdims=True)), 1e-12)
        share = min(needed_share(float(np.abs((c[i] * c[j]).sum(1)).mean()), cfg.inner, cfg.calibrate) * rng.uniform(1.0, 1.1), 0.95)
        k = max(3, int(round(len(e) * share / (1 - share))))
    if cfg.kind == "price":
        template = rng.normal(0, max(x.std(), 1e-9), x.shape[1])
    else:  # a few features get most of the traffic
        template = rng.gamma(0.35, 1.0, x.shape[1]) + 0.01
    rows = scaled(members_of(template, k, cfg.inner, rng, cfg.kind == "price"), x, regime, cfg)
    if cfg.kind == "log":
        rows = np.maximum(rows, 0)
        # counts of ordinary magnitude are too coarse to correlate when rounded: keep tenths there
        rows = np.rint(rows) if rows.mean() > 2 else np.rint(rows * 10) / 10
    return -np.arange(1, k + 1), rows


def inject(cells: DataFrame, regimes: tuple[str, ...] = REGIMES, cfg: InjectConfig = InjectConfig()) -> DataFrame:  # noqa: B008
    """Every window once for each regime, as cells with `injected`; win_id is base_win * 4 + the regime's number."""

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        pdf = pd.concat(list(batches), ignore_index=True)
        win = int(pdf["win_id"].iloc[0])
        e, x = as_array(pdf)
        names = np.unique(pdf["feature"].to_numpy().astype(str))
        order = [c.split()[0] for c in INJECTED.split(", ")]
        for g in regimes:
            key = {"win_id": win * CODES + REGIMES.index(g), "base_win": win, "regime": g}
            for lo in range(0, len(pdf), BATCH):
                part = pdf.iloc[lo : lo + BATCH]
                yield pd.DataFrame({"entity": part["entity"], "feature": part["feature"], "x": part["x"].astype(float), "injected": False}).assign(**key)[order]
            ids, rows = injected_window(win, e, x, g, cfg)
            i, j = np.nonzero(rows)
            for lo in range(0, len(i), BATCH):
                a, b = i[lo : lo + BATCH], j[lo : lo + BATCH]
                yield pd.DataFrame({"entity": ids[a].astype(np.int64), "feature": names[b], "x": rows[a, b], "injected": True}).assign(**key)[order]

    return cells.select("win_id", "entity", "feature", "x").groupBy("win_id").applyInPandas(run, INJECTED)


def truth(injected: DataFrame) -> DataFrame:
    """win_id, base_win, regime, entity, injected."""
    return injected.groupBy("win_id", "base_win", "regime", "entity").agg(F.max("injected").alias("injected"))
