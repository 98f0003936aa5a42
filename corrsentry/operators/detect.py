"""All detectors over windows of cells: one task a window, one pass, findings as rows.

direct   principal score of the whole window
sampled  principal score of a norm-weighted sample, members from the whole window
block    beta block model from the sampled members, or from dense neighbourhoods if there are none
peel     densest remainder of the entity-feature graph (or of the correlation graph)
mixture  least likely groups under a mixture of Gaussian topics
cascade  sampled and block together: group 1 is the core (named by alerts of both), group 2 the suspicious (by one)

A window's folded rows (functions/folded.py: equal rows once, with their number) and draw are made once and shared by the
detectors that need them.  No detector but the dense peel holds a matrix of all entities.
"""

from __future__ import annotations

import time
from collections.abc import Iterator
from functools import cached_property
from typing import NamedTuple

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions import kernels as K
from ..functions.folded import Folded, Sparse
from .corr import as_rows, varying

FINDINGS = "win_id long, detector string, group_id int, entity long, loading double, n long, n_used long, n_constant long, lambda1 double, score double, alert boolean, strength double, n_members long, seconds double, steps int, rounds int, touched long, sample int"
_NAMES = [x.split()[0] for x in FINDINGS.split(", ")]
_KINDS = [{"long": "int64", "double": float, "boolean": bool}.get(x.split()[1]) if x.split()[0] not in ("entity", "touched") else None for x in FINDINGS.split(", ")]


class DetectConfig(NamedTuple):
    detectors: tuple[str, ...] = ("direct", "sampled", "block")
    threshold: float = 0.7
    loading_cut: float = 0.7
    min_strength: float = 0.001
    mode: str = "abs"
    p: float = 1.4
    r: float = 0.2
    u: float = 0.5
    scheme: str = "systematic"  # or random: with replacement by the weights; poisson: independent counts
    seed: int = 0
    weighting: str = "norm"
    dedupe: bool = False
    whole_labels: bool = True
    repeats: int = 1
    max_sample: int | None = None  # a cap of the draws; none: a share r of the entities, whatever their number
    seed_cut: float = 0.7
    fallback: bool = False  # where the sample names nobody: start the block model from the densest neighbourhoods
    min_group: int = 4  # of the block model's groups that may alert
    chance: float = 3.0  # and so many deviations above the entities that the background alone would correlate with one; 0: off
    block: K.BlockConfig = K.BlockConfig()
    peel_graph: str = "features"
    peel_stop: str = "full"
    col_weight: str = "unit"
    topics: int = 4
    exact: int = 0
    early_out: bool = False


class Window1:
    """One window's rows, and what detectors share."""

    def __init__(self, win: int, entity: np.ndarray, x: np.ndarray | Sparse, n_constant: int, weight: np.ndarray, cfg: DetectConfig) -> None:
        self.win, self.entity, self.x, self.n_constant, self.weight, self.cfg = win, entity, x, n_constant, weight, cfg
        self.start: np.ndarray | None = None  # first vector of the eigenvalue solver

    @cached_property
    def folded(self) -> Folded:
        return Folded(self.x, self.cfg.mode, self.cfg.block.clamp)

    @cached_property
    def first_draw(self) -> K.Sampled:
        return _draw(self, self.cfg)

    @cached_property
    def blocks(self) -> list[dict]:
        return _block(self, self.cfg)

    @cached_property
    def drawn(self) -> list[dict]:
        return _sampled(self, self.cfg)


def prepared(win: int, e: np.ndarray, x: np.ndarray | Sparse, cfg: DetectConfig) -> Window1:
    keep = varying(x)
    own = x if keep.all() else x.take(np.flatnonzero(keep)) if isinstance(x, Sparse) else x[keep]
    if cfg.weighting == "norm" and isinstance(x, Sparse):
        w = K.whole_weights(own.sums(cfg.p, absolute=True) ** (1 / cfg.p))
    else:
        w = K.whole_weights(K.norms(own, cfg.p)) if cfg.weighting == "norm" else np.ones(len(own), np.int64)
    return Window1(win, e[keep], own, int((~keep).sum()), w, cfg)


def _direct(w: Window1, cfg: DetectConfig) -> list[dict]:
    f, every = w.folded, w.folded.all
    if cfg.early_out and f.n:
        rows = every.plain(f.count.astype(float))
        if rows.max() / f.n <= cfg.threshold:
            return [{"score": float(f.count @ rows / f.n**2), "alert": False, "members": {}}]
    lam, u, steps = every.principal(cfg.exact, None if w.start is None else np.bincount(f.of, w.start, f.size))
    load = every.loadings(u, lam)[f.of] if f.n else np.zeros(0)
    at = np.flatnonzero(load >= cfg.loading_cut)
    return [{"lambda1": lam, "score": lam / max(f.n, 1), "steps": steps, "members": dict(zip(at.tolist(), load[at].tolist()))}]


def _mult(w: Window1, cfg: DetectConfig, m: int, repeat: int) -> np.ndarray:
    """How often each entity is drawn.  Random draws depend on the seed, the window and the repeat alone."""
    if cfg.scheme == "systematic":
        return K.systematic(w.weight, m, (cfg.u + repeat / max(cfg.repeats, 1)) % 1.0)
    share = w.weight / max(float(w.weight.sum()), 1.0)
    if share.sum() <= 0:
        return np.zeros(len(share), np.int64)
    rng = np.random.default_rng([cfg.seed, w.win % (1 << 32), repeat])
    if cfg.scheme == "random":
        return rng.multinomial(m, share / share.sum())
    if cfg.scheme == "poisson":
        return rng.poisson(m * share)
    raise ValueError("scheme must be systematic, random or poisson")


def _draw(w: Window1, cfg: DetectConfig, repeat: int = 0) -> K.Sampled:
    m = max(1, int(np.floor(len(w.x) * cfg.r + 0.5)))
    m = m if cfg.max_sample is None else min(m, cfg.max_sample)
    mult = _mult(w, cfg, m, repeat)
    return w.folded.sampled(np.minimum(mult, 1) if cfg.dedupe else mult, cfg.whole_labels, cfg.exact)


def _sampled(w: Window1, cfg: DetectConfig) -> list[dict]:
    """With repeats: the median score, an alert by majority, members by the first draw."""
    draws = [w.first_draw, *(_draw(w, cfg, i) for i in range(1, cfg.repeats))]
    s = draws[0]
    at = np.flatnonzero(s.loading >= cfg.loading_cut)
    scores = [d.score for d in draws if not np.isnan(d.score)]
    score = float(np.median(scores)) if scores else 0.0
    return [{"lambda1": s.lam, "score": score, "alert": sum(x > cfg.threshold for x in scores) * 2 > cfg.repeats, "steps": s.steps, "sample": len(s.drawn), "members": dict(zip(at.tolist(), s.loading[at].tolist()))}]


def _block(w: Window1, cfg: DetectConfig) -> list[dict]:
    """A group alerts if its score passes the threshold and it is larger than what the background would give: about n q
    entities correlate with any one at the mean floor, if a share q of the pairs does."""
    return block_groups(w.folded, np.flatnonzero(w.first_draw.loading >= cfg.loading_cut), cfg)


def block_groups(c: Folded, first: np.ndarray, cfg: DetectConfig) -> list[dict]:
    """_block of any Folded, from the entities the sample names."""
    n = c.n
    z = np.zeros(n, np.int64)
    if len(first) >= 2:
        z[first] = c.farthest_first(first, cfg.block.k)
    elif cfg.fallback:
        z = c.neighbourhoods(cfg.seed_cut, cfg.block.k)
    if not (z > 0).any():
        return [{"score": 0.0, "alert": False, "members": {}, "rounds": 0, "touched": 0}]
    m = K.block_model(c, z, cfg.block)
    by_chance = n * m.near
    least = max(cfg.min_group, 1 + by_chance + cfg.chance * np.sqrt(by_chance) if cfg.chance > 0 else 0)
    out = []
    for g in range(1, cfg.block.k + 1):
        at = np.flatnonzero(m.z == g)
        if len(at):
            lam, load, steps = c.scored(at, cfg.exact)
            out.append({"group_id": g, "lambda1": lam, "score": lam / len(at), "alert": lam / len(at) > cfg.threshold and len(at) >= least, "steps": steps, "rounds": m.rounds, "touched": m.touched, "members": dict(zip(at.tolist(), load.tolist()))})
    return out or [{"score": 0.0, "alert": False, "members": {}, "rounds": m.rounds, "touched": m.touched}]


def _cascade(w: Window1, cfg: DetectConfig) -> list[dict]:
    """The alerts of the sampled score and of the block model merged, from one draw.  A group that is empty is left out."""
    total = max(float(w.weight.sum()), 1.0)
    sides: list[dict[int, float]] = []
    best = 0.0
    for found in (w.drawn, w.blocks):
        own: dict[int, float] = {}
        for f in found:
            best = max(best, f["score"])
            at = list(f["members"])
            if f.get("alert", f["score"] > cfg.threshold) and w.weight[at].sum() / total >= cfg.min_strength:
                own |= f["members"]
        sides.append(own)
    core = sides[0].keys() & sides[1].keys()
    both = {i: max(s.get(i, 0.0) for s in sides) for i in sides[0].keys() | sides[1].keys()}
    groups = [(1, {i: v for i, v in both.items() if i in core}), (2, {i: v for i, v in both.items() if i not in core})]
    out = [{"group_id": g, "score": best, "alert": True, "strong": True, "members": m} for g, m in groups if m]
    return out or [{"score": best, "alert": False, "members": {}}]


def _set_score(w: Window1, at: np.ndarray, cfg: DetectConfig) -> dict:
    lam, load, steps = w.folded.scored(at, cfg.exact)
    return {"lambda1": lam, "score": lam / max(len(at), 1), "alert": len(at) > 1 and lam / len(at) > cfg.threshold, "steps": steps, "members": dict(zip(at.tolist(), load.tolist()))}


def _peel(w: Window1, cfg: DetectConfig) -> list[dict]:
    if cfg.peel_graph == "features":
        i, j, v = (w.x.row, w.x.idx, w.x.val) if isinstance(w.x, Sparse) else (*np.nonzero(w.x), w.x[np.nonzero(w.x)])
        rows, _, _ = K.peel_bipartite(i, j, np.abs(v), cfg.peel_stop, cfg.col_weight)
        at = np.asarray(rows, np.int64)
    else:
        f = w.folded
        at, _ = K.peel_dense(f.tile(f.of, f.of) if f.size == f.n else f.tile(np.arange(f.size), np.arange(f.size))[np.ix_(f.of, f.of)], cfg.peel_stop)
    return [_set_score(w, at, cfg)]


def attributes(x: np.ndarray) -> np.ndarray:
    """Per entity: log of the total, used features, mean of the used, largest share, entropy."""
    a = np.abs(x)
    total = np.maximum(a.sum(1), 1e-12)
    share = a / total[:, None]
    used = np.maximum((a > 0).sum(1), 1)
    return np.column_stack([np.log1p(total), used, total / used, share.max(1), -(share * np.log(np.maximum(share, 1e-12))).sum(1)])


def _mixture(w: Window1, cfg: DetectConfig) -> list[dict]:
    """Groups are stretches of about sqrt(n) entities of like magnitude; those of the least likely topic shares are
    anomalous: the lowest twentieth, one at least."""
    n = len(w.x)
    if n < 4:
        return [{"score": 0.0, "alert": False, "members": {}}]
    resp = K.gaussian_topics(attributes(w.x.dense() if isinstance(w.x, Sparse) else w.x), cfg.topics)
    groups = np.array_split(np.argsort(w.weight, kind="stable"), max(2, int(np.sqrt(n))))
    overall = np.log(np.maximum(resp.mean(0), 1e-9))
    fit = np.array([(resp[g].mean(0) * overall).sum() for g in groups])
    low = np.argsort(fit, kind="stable")[: max(1, len(groups) // 20)]
    return [_set_score(w, np.sort(np.concatenate([groups[i] for i in low])), cfg)]


KERNELS = {"direct": _direct, "sampled": lambda w, _: w.drawn, "block": lambda w, _: w.blocks, "cascade": _cascade, "peel": _peel, "mixture": _mixture}


#: Rows of findings that are handed over at once.
BATCH = 20_000


def findings(win: int, e: np.ndarray, x: np.ndarray | Sparse, cfg: DetectConfig, start: dict[int, float] | None = None, named: bool = True) -> Iterator[pd.DataFrame]:
    """find, bit by bit; named: with a row for each member."""
    began = time.perf_counter()
    w = prepared(win, e, x, cfg)
    del x
    if start:
        w.start = np.array([start.get(int(i), 0.0) for i in w.entity])
    shared = time.perf_counter() - began
    total = max(float(w.weight.sum()), 1.0)
    for d in cfg.detectors:
        began = time.perf_counter()
        found = KERNELS[d](w, cfg) if len(w.x) > 1 else [{"score": 0.0, "alert": False, "members": {}}]
        took = time.perf_counter() - began + shared
        for f in found:
            at = np.array(sorted(f["members"]), np.int64)
            share = float(w.weight[at].sum()) / total
            loud = bool(f.get("alert", f["score"] > cfg.threshold)) and (share >= cfg.min_strength or f.get("strong", False))
            base = {"win_id": win, "detector": d, "group_id": f.get("group_id", 1), "n": len(e), "n_used": len(w.x), "n_constant": w.n_constant, "lambda1": f.get("lambda1"), "score": f["score"], "alert": loud, "strength": share, "n_members": len(at), "seconds": took, "steps": f.get("steps"), "rounds": f.get("rounds"), "touched": f.get("touched"), "sample": f.get("sample")}
            yield _rows(base, [None], [None])
            for lo in range(0, len(at) if named else 0, BATCH):
                own = at[lo : lo + BATCH]
                yield _rows(base, w.entity[own].tolist(), [f["members"][i] for i in own.tolist()])


def _rows(base: dict, entity: list, loading: list) -> pd.DataFrame:
    """A row of findings for the group (entity None) or for each of some members."""
    out = pd.DataFrame({k: np.repeat(np.array([v], object), len(entity)) for k, v in base.items()} | {"entity": entity, "loading": loading}, columns=_NAMES)
    out = out.astype({c: kind for c, kind in zip(_NAMES, _KINDS) if kind})
    for c, kind in (("entity", "Int64"), ("steps", "Int32"), ("rounds", "Int32"), ("touched", "Int64"), ("sample", "Int32")):
        out[c] = out[c].astype(kind)
    return out


def find(win: int, e: np.ndarray, x: np.ndarray | Sparse, cfg: DetectConfig, start: dict[int, float] | None = None) -> pd.DataFrame:
    """Findings of one window: a row for each detector and group, and one for each member.  seconds: a detector that uses
    what another one made is charged for its own part alone; run it by itself to compare.  start: loadings of an earlier
    window, from which the direct score's solver begins."""
    return pd.concat(list(findings(win, e, x, cfg, start)), ignore_index=True)


def detect(cells: DataFrame, cfg: DetectConfig = DetectConfig(), named: bool = True) -> DataFrame:  # noqa: B008
    """Findings of every window that one task can hold; planner.detect_any also takes larger ones.  named: with a row for
    each member; scores need none."""

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        win: list[int] = []

        def seen() -> Iterator[pd.DataFrame]:
            for b in batches:
                win.append(int(b["win_id"].iloc[0]))
                yield b

        e, x = as_rows(seen())
        yield from findings(win[0], e, x, cfg, named=named)

    return cells.select("win_id", "entity", "feature", "x").groupBy("win_id").applyInPandas(run, FINDINGS)


def detect_warm(cells: DataFrame, earlier: DataFrame, cfg: DetectConfig = DetectConfig()) -> DataFrame:  # noqa: B008
    """As detect, each window's solver begun from earlier loadings.  earlier: win_id (of the window to judge), entity, loading."""

    def run(own: pd.DataFrame, before: pd.DataFrame) -> pd.DataFrame:
        if not len(own):
            return pd.DataFrame(columns=_NAMES)
        return find(int(own["win_id"].iloc[0]), *as_rows(own), cfg, dict(zip(before["entity"].tolist(), before["loading"].tolist())))

    return cells.select("win_id", "entity", "feature", "x").groupBy("win_id").cogroup(earlier.select("win_id", "entity", "loading").groupBy("win_id")).applyInPandas(run, FINDINGS)


def scores(findings: DataFrame) -> DataFrame:
    """A row for each window, detector and group."""
    return findings.where("entity is null").drop("entity", "loading")


def best_scores(findings: DataFrame) -> DataFrame:
    """A row for each window and detector: its best group's score, an alert if any group has one."""
    return scores(findings).groupBy("win_id", "detector").agg(F.max("score").alias("score"), F.max("alert").alias("alert"), F.max("strength").alias("strength"), F.max("n").alias("n"), F.sum("n_members").alias("n_members"), F.max("seconds").alias("seconds"))


def members(findings: DataFrame, alerted: bool = True) -> DataFrame:
    """A row for each named entity; alerted: only those of groups that raised an alert."""
    m = findings.where("entity is not null")
    return (m.where("alert") if alerted else m).select("win_id", "detector", "group_id", "entity", "loading", "score", "alert")
