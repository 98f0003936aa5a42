"""Correlations of a window's entities: sparse pairs by a self join, dense kernels, tiles, online updates, sign modes."""

from __future__ import annotations

from collections.abc import Iterable, Iterator
from itertools import chain

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions import kernels as K
from ..functions.folded import Folded, Sparse, equal_rows
from .matrix import col_stats

PAIRS = "win_id long, i long, j long, rho double"


def rho(m: Column, c: Column, si: Column, qi: Column, sj: Column, qj: Column) -> Column:
    """Pearson from integer sums; rounding is in the two roots, their product and the division only."""
    return (m * c - si * sj).cast("double") / (F.sqrt((m * qi - si * si).cast("double")) * F.sqrt((m * qj - sj * sj).cast("double")))


def pairs_sparse(cells: DataFrame, complete: bool = False) -> DataFrame:
    """win_id, i < j, rho (signed) of entities that share a feature; complete: of all, those without a common feature have
    a closed form.  Meant for windows whose features are used by few entities: planner.choose_path says when."""
    side = lambda e: cells.select("win_id", "feature", F.col("entity").alias(e), F.col("x").alias(f"x{e}"))
    dot = side("i").join(side("j"), ["win_id", "feature"]).where("i < j").groupBy("win_id", "i", "j").agg(F.sum(F.col("xi") * F.col("xj")).alias("c"))
    st = col_stats(cells).where(F.col("m") * F.col("ss") != F.col("s") * F.col("s"))
    end = lambda e: st.select("win_id", F.col("entity").alias(e), F.col("s").alias(f"s{e}"), F.col("ss").alias(f"q{e}"), F.col("m").alias(f"m{e}"))
    if complete:
        all_ = end("i").join(end("j"), "win_id").where("i < j")
        dot = all_.join(dot, ["win_id", "i", "j"], "left").withColumn("c", F.coalesce("c", F.lit(0)))
    else:
        dot = dot.join(end("i"), ["win_id", "i"]).join(end("j"), ["win_id", "j"])
    return dot.select("win_id", "i", "j", rho(F.col("mi"), F.col("c"), F.col("si"), F.col("qi"), F.col("sj"), F.col("qj")).alias("rho"))


def apply_mode(pairs: DataFrame, mode: str) -> DataFrame:
    """Signed pairs in a sign mode; self-correlations are 1 in every mode and not among the pairs."""
    r = F.col("rho")
    kinds = {"abs": F.abs(r), "positive": F.greatest(r, F.lit(0.0)), "negative": F.greatest(-r, F.lit(0.0)), "signed": r}
    if mode not in kinds:
        raise ValueError(f"mode must be one of {K.MODES}")
    return pairs.withColumn("rho", kinds[mode])


def as_array(cells: pd.DataFrame) -> tuple[np.ndarray, np.ndarray]:
    """(entities, x) of one window's cells, constant rows included; entities in order."""
    e, i, f, j = _places(cells)
    x = np.zeros((len(e), len(f)))
    np.add.at(x, (i, j), cells["x"].to_numpy(float))
    return e, x


def gathered(batches: Iterable[pd.DataFrame]) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """(entities, entity of each cell, features, feature of each cell, x) of one window's cells, entities and features in
    order.  Names of features are kept once: a batch's are let go with it."""
    ids, codes, values, names = [], [], [], {}
    for b in batches:
        j, f = pd.factorize(b["feature"])
        codes.append(np.array([names.setdefault(v, len(names)) for v in f], np.int32)[j])
        ids.append(b["entity"].to_numpy())
        values.append(b["x"].to_numpy(float))
    e, i = np.unique(np.concatenate(ids), return_inverse=True)
    f = np.array(list(names), object)
    order = np.argsort(f.astype(str), kind="stable")
    place = np.empty(len(f), np.int64)
    place[order] = np.arange(len(f))
    return e, i, f[order], place[np.concatenate(codes)], np.concatenate(values)


def _places(cells: pd.DataFrame) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    return gathered([cells])[:4]


def as_rows(cells: pd.DataFrame | Iterable[pd.DataFrame], dense: int = 1 << 18) -> tuple[np.ndarray, np.ndarray | Sparse]:
    """as_array, of cells or batches of them; rows stay sparse where the array would have more than `dense` entries, most
    of them 0."""
    e, i, f, j, v = gathered([cells] if isinstance(cells, pd.DataFrame) else cells)
    if len(e) * len(f) <= max(dense, 4 * len(v)):
        x = np.zeros((len(e), len(f)))
        np.add.at(x, (i, j), v)
        return e, x
    return e, Sparse(i, j, v, len(e), len(f))


def varying(x: np.ndarray | Sparse) -> np.ndarray:
    if isinstance(x, Sparse):
        return x.spread()
    return x.std(1) > 1e-12 if x.size else np.zeros(len(x), bool)


def _sums(x: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Rows of whole numbers, their sums, and the roots that _exact divides by."""
    s = x.sum(1)
    return x, s, np.sqrt(x.shape[1] * (x * x).sum(1) - s * s)


def _exact(sums: tuple[np.ndarray, np.ndarray, np.ndarray], at: slice, other: slice) -> np.ndarray:
    """Pearson of some rows with others, rounded as rho rounds it; constant rows are left out before."""
    x, s, root = sums
    return (x.shape[1] * (x[at] @ x[other].T) - np.outer(s[at], s[other])) / np.outer(root[at], root[other])


def _uneven(x: np.ndarray) -> np.ndarray:
    """Rows of whole numbers that are not constant."""
    s, q = x.sum(1), (x * x).sum(1)
    return x.shape[1] * q != s * s


def _window(batches: Iterator[pd.DataFrame]) -> tuple[int, np.ndarray, np.ndarray, bool]:
    """(win_id, entities, their rows, whether all cells are whole numbers), constant entities left out."""
    pdf = pd.concat(list(batches), ignore_index=True)
    whole = not np.issubdtype(pdf["x"].dtype, np.floating)
    e, x = as_array(pdf)
    keep = _uneven(x) if whole else varying(x)
    return int(pdf["win_id"].iloc[0]), e[keep], x[keep], whole


def _pair_rows(win: int, e: np.ndarray, x: np.ndarray, whole: bool, pick=None, size: int = 1 << 18) -> Iterator[pd.DataFrame]:  # noqa: ANN001
    """Pairs i < j about `size` at a time.  pick: of (rows, columns), which pairs to keep."""
    step = max(1, size // max(len(e), 1))
    sums, unit = (_sums(x), None) if whole else (None, Folded(x, "signed"))
    for lo in range(0, len(e) - 1, step):
        at, other = slice(lo, min(lo + step, len(e))), slice(lo + 1, len(e))
        p = _exact(sums, at, other) if whole else unit.tile(unit.of[at], unit.of[other])
        keep = np.triu(np.ones(p.shape, bool))  # column k is entity lo + 1 + k
        i, j = np.nonzero(keep if pick is None else keep & pick(at, other))
        yield pd.DataFrame({"win_id": win, "i": e[lo + i], "j": e[lo + 1 + j], "rho": p[i, j]})


def pairs_dense(cells: DataFrame) -> DataFrame:
    """As pairs_sparse(complete=True), by matrix products in one task for each window, which hands over its pairs bit by bit."""

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        yield from _pair_rows(*_window(batches))

    return cells.select("win_id", "entity", "feature", "x").groupBy("win_id").applyInPandas(run, PAIRS)


def pairs_sharing(cells: DataFrame) -> DataFrame:
    """As pairs_sparse, without a join: each window's task makes the pairs that have a feature in common."""

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        win, e, x, whole = _window(batches)
        used = (x != 0).astype(np.float32)
        yield from _pair_rows(win, e, x, whole, lambda a, b: used[a] @ used[b].T > 0)

    return cells.select("win_id", "entity", "feature", "x").groupBy("win_id").applyInPandas(run, PAIRS)


def pairs_among(cells: DataFrame, members: DataFrame, rows: bool = False) -> DataFrame:
    """pairs_dense of the members (win_id, entity) of each window alone; their rows have all features of the window.  rows: not
    the pairs but what they are products of, (win_id, entity, u), the varying members' unit rows."""
    if rows:
        return _rows_among(cells, members)

    def run(own: pd.DataFrame, named: pd.DataFrame) -> pd.DataFrame:
        if not len(own) or not len(named):
            return pd.DataFrame({c: [] for c in ("win_id", "i", "j", "rho")})
        f, last = np.unique(own["feature"].to_numpy().astype(str)), own["x"].iloc[:1]
        mine = own[own["entity"].isin(named["entity"])]
        pad = pd.DataFrame({"win_id": own["win_id"].iloc[0], "entity": mine["entity"].iloc[:1].repeat(len(f)).to_numpy(), "feature": f if len(mine) else f[:0], "x": np.zeros(len(f) if len(mine) else 0, last.dtype)})
        if not len(mine):
            return pd.DataFrame({c: [] for c in ("win_id", "i", "j", "rho")})
        return pd.concat(list(_pair_rows(*_window(iter([pd.concat([mine, pad])])))) or [pd.DataFrame({c: [] for c in ("win_id", "i", "j", "rho")})])

    named = members.select("win_id", "entity").distinct().toDF("win_id", "entity")  # columns of its own, as in tiles
    return cells.select("win_id", "entity", "feature", "x").groupBy("win_id").cogroup(named.groupBy("win_id")).applyInPandas(run, PAIRS)


def _rows_among(cells: DataFrame, members: DataFrame) -> DataFrame:
    named = members.select("win_id", "entity").distinct().select("win_id", "entity", F.lit(None).cast("string").alias("feature"), F.lit(None).cast("double").alias("x"))
    both = cells.select("win_id", "entity", "feature", F.col("x").cast("double").alias("x")).unionByName(named)

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        win, ids = [], [np.zeros(0, np.int64)]

        def own() -> Iterator[pd.DataFrame]:
            for b in batches:
                member = b["feature"].isna().to_numpy()
                ids.append(b["entity"].to_numpy()[member])
                if not member.all():
                    win.append(int(b["win_id"].iloc[0]))
                    yield b[~member]

        every = own()
        first = next(every, None)
        if first is None:
            return
        e, i, f, j, v = gathered(chain([first], every))
        keep = np.isin(e, np.concatenate(ids))
        place, at = np.cumsum(keep) - 1, keep[i]
        x = np.zeros((int(keep.sum()), len(f)))
        np.add.at(x, (place[i[at]], j[at]), v[at])
        ok = varying(x)
        e, x = e[keep][ok], x[ok]
        x -= x.mean(1, keepdims=True)
        x /= np.sqrt((x * x).sum(1, keepdims=True))
        for lo in range(0, len(e), 4096):
            yield pd.DataFrame({"win_id": win[0], "entity": e[lo : lo + 4096], "u": list(x[lo : lo + 4096])})

    return both.groupBy("win_id").applyInPandas(run, "win_id long, entity long, u array<double>")


DIGEST = "win_id long, pairs long, sum_u6 long, top_u6 long"


def _digest(win: int, x: np.ndarray, count: np.ndarray) -> tuple[int, int, int, int] | None:
    """Number of pairs, sum and greatest of their correlations in millionths, of distinct rows and how often each occurs."""
    pairs, total, top = 0, 0, None
    sums = _sums(x)
    for lo in range(0, len(x), 512):
        at = slice(lo, min(lo + 512, len(x)))
        u = np.floor(_exact(sums, at, slice(lo, len(x))) * 1000000 + 0.5).astype(np.int64)
        c = np.outer(count[at], count[lo:])
        own = np.arange(len(c))
        c[own, own] = count[at] * (count[at] - 1) // 2
        c = np.triu(c)
        pairs, total = pairs + int(c.sum()), total + int((u * c).sum())
        if c.any():
            top = max(int(u[c > 0].max()), top if top is not None else -(1 << 62))
    return (win, pairs, total, top) if pairs else None


def digest_dense(rows: DataFrame) -> DataFrame:
    """win_id, pairs, sum_u6, top_u6 of each window of whole numbers, every window from its own values; equal rows are made once
    and count as often as they are.  rows: cells, or (win_id, entity, x array)."""
    cells = "feature" in rows.columns

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        if cells:
            win, _, x, _ = _window(batches)
            first, of = equal_rows(x)
            x, count = x[first], np.bincount(of)
        else:
            parts = [(int(b["win_id"].iloc[0]), np.stack(b["x"].to_list()).astype(float), b["count"].to_numpy(np.int64)) for b in batches]
            win, x, count = parts[0][0], np.concatenate([p[1] for p in parts]), np.concatenate([p[2] for p in parts])
            keep = _uneven(x)
            x, count = x[keep], count[keep]
        found = _digest(win, x, count)
        yield pd.DataFrame([found] if found else [], columns=[c.split()[0] for c in DIGEST.split(", ")])

    own = rows.select("win_id", "entity", "feature", "x") if cells else rows.groupBy("win_id", "x").agg(F.count(F.lit(1)).alias("count"))
    return own.groupBy("win_id").applyInPandas(run, DIGEST)


def digest_online(changes: DataFrame, length: int, tile: int = 256) -> DataFrame:
    """The digest of all windows of `length` periods, step 1, by running sums: a slide adds one period's products and drops
    one's.  changes: (entity, period, x whole numbers), every entity with every period.  Entities with equal series are kept
    once with their number; a task takes the pairs of two blocks of series along all windows."""
    series = changes.groupBy("entity").agg(F.sort_array(F.collect_list(F.struct("period", "x"))).alias("s"))
    series = series.select("s.period", F.col("s.x").cast("array<long>").alias("x")).groupBy("period", "x").agg(F.count(F.lit(1)).alias("count"))
    n = series.agg(F.count(F.lit(1)).alias("n"))  # one row
    top = (F.ceil(F.col("n") / tile) - 1).cast("int")
    placed = series.crossJoin(F.broadcast(n)).withColumn("top", top).withColumn("b", F.pmod(F.xxhash64("x"), F.col("top") + 1).cast("int"))
    left = placed.select(F.col("b").alias("bi"), F.explode(F.sequence("b", "top")).alias("bj"), F.lit(True).alias("row"), "period", "x", "count")
    right = placed.select(F.explode(F.sequence(F.lit(0), "b")).alias("bi"), F.col("b").alias("bj"), F.lit(False).alias("row"), "period", "x", "count").where("bi < bj")

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        pdf = pd.concat(list(batches), ignore_index=True)
        a = pdf[pdf["row"]]
        diagonal = pdf["bi"].iloc[0] == pdf["bj"].iloc[0]
        b = a if diagonal else pdf[~pdf["row"]]
        if not len(a) or not len(b):
            return
        first = int(a["period"].iloc[0][0])
        xa, xb = (np.array(d["x"].to_list(), float) for d in (a, b))
        ca, cb = (d["count"].to_numpy(np.int64) for d in (a, b))
        pairs = np.outer(ca, cb)
        if diagonal:
            own = np.arange(len(a))
            pairs = np.triu(pairs)
            pairs[own, own] = ca * (ca - 1) // 2
        c, (sa, qa, sb, qb) = np.zeros((len(a), len(b))), (np.zeros(len(v)) for v in (xa, xa, xb, xb))
        out = []
        for t in range(xa.shape[1]):
            c += np.outer(xa[:, t], xb[:, t])
            sa, qa, sb, qb = sa + xa[:, t], qa + xa[:, t] ** 2, sb + xb[:, t], qb + xb[:, t] ** 2
            if t >= length:
                o = t - length
                c -= np.outer(xa[:, o], xb[:, o])
                sa, qa, sb, qb = sa - xa[:, o], qa - xa[:, o] ** 2, sb - xb[:, o], qb - xb[:, o] ** 2
            if t < length - 1:
                continue
            va, vb = length * qa - sa * sa, length * qb - sb * sb
            k = np.where(np.outer(va != 0, vb != 0), pairs, 0)
            if k.any():
                r = (length * c - np.outer(sa, sb)) / np.outer(np.sqrt(np.where(va, va, 1)), np.sqrt(np.where(vb, vb, 1)))
                u = np.floor(r * 1000000 + 0.5).astype(np.int64)
                out.append((first + t - length + 1, int(k.sum()), int((u * k).sum()), int(u[k > 0].max())))
        yield pd.DataFrame(out, columns=[x.split()[0] for x in DIGEST.split(", ")])

    part = left.unionByName(right).groupBy("bi", "bj").applyInPandas(run, DIGEST)
    return part.groupBy("win_id").agg(F.sum("pairs").alias("pairs"), F.sum("sum_u6").alias("sum_u6"), F.max("top_u6").alias("top_u6"))


def columns(cells: DataFrame) -> DataFrame:
    """win_id, entity, x array<double>: centred unit vectors over the window's features, in their order.  Constant
    entities are left out."""
    feats = cells.select("win_id", "feature").distinct().withColumn("f", (F.row_number().over(Window.partitionBy("win_id").orderBy("feature")) - 1).cast("int"))
    st = col_stats(cells).where(F.col("m") * F.col("ss") != F.col("s") * F.col("s"))
    mean, size = F.col("s") / F.col("m"), F.sqrt((F.col("m") * F.col("ss") - F.col("s") * F.col("s")) / F.col("m"))
    entries = cells.join(feats, ["win_id", "feature"]).groupBy("win_id", "entity").agg(F.map_from_entries(F.collect_list(F.struct("f", "x"))).alias("e"))
    full = F.transform(F.sequence(F.lit(0), (F.col("m") - 1).cast("int")), lambda f: (F.coalesce(F.element_at("e", f), F.lit(0)) - mean) / size)
    return entries.join(st, ["win_id", "entity"]).select("win_id", "entity", full.alias("x"))


def tiles(cols: DataFrame, tile: int = 2048) -> DataFrame:
    """win_id, bi <= bj, rows, cols (entity ids), p (row-major signed correlations) of every tile of the upper triangle.

    An entity's block is a hash of its id, so nothing is ranked; blocks hold about `tile` entities.  A block of columns is
    sent to each tile that needs it, and a task multiplies two blocks, so memory is about tile * (2 M + tile) doubles
    whatever the window's size."""
    n = cols.groupBy("win_id").agg((F.ceil(F.count(F.lit(1)) / tile) - 1).cast("int").alias("top"))
    wide = cols.join(F.broadcast(n), "win_id").withColumn("b", F.pmod(F.xxhash64("entity"), F.col("top") + 1).cast("int"))
    left = wide.withColumn("o", F.explode(F.sequence("b", "top"))).select("win_id", F.col("b").alias("bi"), F.col("o").alias("bj"), "entity", "x")
    right = wide.withColumn("o", F.explode(F.sequence(F.lit(0), "b"))).select("win_id", F.col("o").alias("bi"), F.col("b").alias("bj"), "entity", "x")

    def run(a: pd.DataFrame, b: pd.DataFrame) -> pd.DataFrame:
        a, b = a.sort_values("entity"), b.sort_values("entity")
        p = np.clip(np.stack(a["x"].to_list()) @ np.stack(b["x"].to_list()).T, -1, 1)
        return pd.DataFrame({"win_id": [a["win_id"].iloc[0]], "bi": [a["bi"].iloc[0]], "bj": [a["bj"].iloc[0]], "rows": [a["entity"].to_numpy()], "cols": [b["entity"].to_numpy()], "p": [p.ravel()]})

    keys = ["win_id", "bi", "bj"]
    right = right.toDF(*right.columns)  # columns of its own: both sides come from one table
    return left.groupBy(*keys).cogroup(right.groupBy(*keys)).applyInPandas(run, "win_id long, bi int, bj int, rows array<long>, cols array<long>, p array<double>")


def tile_pairs(tiled: DataFrame) -> DataFrame:
    """Pairs i < j of the tiles; one on the diagonal has each pair twice, any other once."""
    at = tiled.select("win_id", "bi", "bj", "rows", "cols", F.posexplode("p").alias("pos", "rho"))
    width = F.size("cols")
    i, j = F.element_at("rows", (F.floor(F.col("pos") / width) + 1).cast("int")), F.element_at("cols", (F.col("pos") % width + 1).cast("int"))
    return at.select("win_id", "bi", "bj", i.alias("i"), j.alias("j"), "rho").where("bi <> bj or i < j").select("win_id", F.least("i", "j").alias("i"), F.greatest("i", "j").alias("j"), "rho")


def recover_signs(members: DataFrame, pairs: DataFrame) -> DataFrame:
    """win_id, i, j, sign of the signed pairs inside each detected set."""
    end = lambda e: members.select("win_id", "group_id", F.col("entity").alias(e))
    return pairs.join(end("i"), ["win_id", "i"]).join(end("j"), ["win_id", "group_id", "j"]).select("win_id", "group_id", "i", "j", F.signum("rho").cast("int").alias("sign"))


def online_rows(changes: DataFrame, length: int) -> DataFrame:
    """(entity, period, x whole numbers) -> win_id, i, j, rho of every window of `length` periods, step 1: products are
    summed over a moving frame, so a slide adds one period and drops one instead of starting anew.  Entities must have
    every period."""
    side = lambda e: changes.select("period", F.col("entity").alias(e), F.col("x").alias(f"x{e}"))
    both = side("i").join(side("j"), "period").where("i < j")
    w = Window.partitionBy("i", "j").orderBy("period").rowsBetween(-(length - 1), 0)
    s = lambda c: F.sum(c).over(w)
    xi, xj = F.col("xi"), F.col("xj")
    run = both.select("i", "j", "period", F.count(F.lit(1)).over(w).alias("m"), s(xi * xj).alias("c"), s(xi).alias("si"), s(xi * xi).alias("qi"), s(xj).alias("sj"), s(xj * xj).alias("qj"))
    ok = (F.col("m") == length) & (F.col("m") * F.col("qi") != F.col("si") * F.col("si")) & (F.col("m") * F.col("qj") != F.col("sj") * F.col("sj"))
    return run.where(ok).select((F.col("period") - (length - 1)).alias("win_id"), "i", "j", rho(F.col("m"), F.col("c"), F.col("si"), F.col("qi"), F.col("sj"), F.col("qj")).alias("rho"))


def cross_sums(cells: DataFrame) -> DataFrame:
    """win_id, i <= j, c: sums of products of entities that share a feature; the state of online_counts."""
    side = lambda e: cells.select("win_id", "feature", F.col("entity").alias(e), F.col("x").alias(f"x{e}"))
    return side("i").join(side("j"), ["win_id", "feature"]).where("i <= j").groupBy("win_id", "i", "j").agg(F.sum(F.col("xi") * F.col("xj")).alias("c"))


def _moved(before: DataFrame, after: DataFrame, d: DataFrame, by: list[str]) -> DataFrame:
    """by, i <= j, t: what a slide adds to the cross sums.  x'_i x'_j - x_i x_j = d_i x'_j + x_i d_j, summed over features, so
    only pairs with a changed end are made."""
    end = lambda c, e, v: c.select(*by, "feature", F.col("entity").alias(e), F.col(v).alias(f"_{e}"))
    a = end(d, "i", "d").join(end(after, "j", "x"), [*by, "feature"])
    b = end(before, "i", "x").join(end(d, "j", "d"), [*by, "feature"])
    return a.unionByName(b).where("i <= j").groupBy(*by, "i", "j").agg(F.sum(F.col("_i") * F.col("_j")).alias("t"))


def online_counts(state: DataFrame, before: DataFrame, delta: DataFrame) -> DataFrame:
    """Cross sums after a slide of a count matrix.  state: i <= j, c of the old window; before: its cells (entity, feature,
    x); delta: changes of cells (entity, feature, d).  Only pairs with a changed end are touched; the others are kept."""
    d = delta.groupBy("entity", "feature").agg(F.sum("d").alias("d")).where("d <> 0")
    after = before.select("entity", "feature", "x").unionByName(d.withColumnRenamed("d", "x")).groupBy("entity", "feature").agg(F.sum("x").alias("x"))
    return state.join(_moved(before, after, d, []), ["i", "j"], "full").select("i", "j", (F.coalesce("c", F.lit(0)) + F.coalesce("t", F.lit(0))).alias("c")).where("c <> 0")


def online_count_windows(cells: DataFrame) -> DataFrame:
    """win_id, i <= j, c of every window: the first window's sums, then for each slide only what changed, added up along the
    windows.  A pair that no slide touches keeps its sum until one does."""
    own = cells.select("win_id").distinct()  # one row a window
    order = own.select("win_id", F.row_number().over(Window.orderBy("win_id")).alias("k"), F.count(F.lit(1)).over(Window.partitionBy()).alias("last"))
    placed = cells.join(order, "win_id")
    after = placed.select("k", "entity", "feature", "x")
    before = placed.where("k < last").select((F.col("k") + 1).alias("k"), "entity", "feature", "x")
    d = after.unionByName(before.withColumn("x", -F.col("x"))).groupBy("k", "entity", "feature").agg(F.sum("x").alias("d")).where("d <> 0")
    w = Window.partitionBy("i", "j").orderBy("k")
    run = _moved(before, after, d, ["k"]).select("i", "j", "k", F.sum("t").over(w).alias("c"), F.lead("k").over(w).alias("next")).where("c <> 0")
    held = run.join(order, "k").select("i", "j", "c", F.explode(F.sequence(F.col("k").cast("long"), F.coalesce(F.col("next") - 1, "last"))).alias("k"))
    return held.join(order, "k").select("win_id", "i", "j", "c")


def background(pairs: DataFrame, members: DataFrame) -> DataFrame:
    """win_id, mu and sigma of the pairs outside the member set, inner (mean inside) and n_inner.  pairs in the mode wanted."""
    end = lambda e: members.select("win_id", F.col("entity").alias(e), F.lit(1).alias(f"in_{e}")).distinct()
    both = pairs.join(end("i"), ["win_id", "i"], "left").join(end("j"), ["win_id", "j"], "left")
    inside = F.col("in_i").isNotNull() & F.col("in_j").isNotNull()
    return both.groupBy("win_id").agg(F.avg(F.when(~inside, F.col("rho"))).alias("mu"), F.stddev_pop(F.when(~inside, F.col("rho"))).alias("sigma"), F.avg(F.when(inside, F.col("rho"))).alias("inner"), F.count_if(inside).alias("n_inner"))


def background_cells(cells: DataFrame, members: DataFrame) -> DataFrame:
    """background of absolute correlations from cells of whole numbers, without a pair table: equal rows are made once, and each
    pair of them counts as often as it occurs inside and outside the member set."""

    def run(own: pd.DataFrame, named: pd.DataFrame) -> pd.DataFrame:
        cols = ["win_id", "mu", "sigma", "inner", "n_inner"]
        if not len(own):
            return pd.DataFrame(columns=cols)
        win, e, x, _ = _window(iter([own]))
        if len(e) < 2:
            return pd.DataFrame(columns=cols)
        first, of = equal_rows(x)
        x, member = x[first], np.isin(e, named["entity"] if len(named) else [])
        every, mine, sums = np.bincount(of), np.bincount(of[member], minlength=len(x)), _sums(x)

        def parts():  # noqa: ANN202
            """(|rho|, pairs outside, pairs inside) of rows of the upper triangle."""
            for lo in range(0, len(x), 512):
                at, other = slice(lo, min(lo + 512, len(x))), slice(lo, len(x))
                r, i = np.abs(_exact(sums, at, other)), np.arange(at.stop - lo)
                both = []
                for c in (every, mine):
                    k = np.outer(c[at], c[other])
                    k[i, i] = c[at] * (c[at] - 1) // 2
                    both.append(np.triu(k))
                yield r, both[0] - both[1], both[1]

        n_out = n_in = s_out = s_in = dev = 0
        for r, k, inside in parts():
            n_out, n_in, s_out, s_in = n_out + int(k.sum()), n_in + int(inside.sum()), s_out + (r * k).sum(), s_in + (r * inside).sum()
        mu = s_out / n_out if n_out else None
        if n_out:
            dev = sum(((r - mu) ** 2 * k).sum() for r, k, _ in parts())
        return pd.DataFrame([(win, mu, np.sqrt(dev / n_out) if n_out else None, s_in / n_in if n_in else None, n_in)], columns=cols)

    named = members.select("win_id", "entity").distinct().toDF("win_id", "entity")  # columns of its own, as in tiles
    return cells.select("win_id", "entity", "feature", "x").groupBy("win_id").cogroup(named.groupBy("win_id")).applyInPandas(run, "win_id long, mu double, sigma double, inner double, n_inner long")
