"""The sampled detector for windows that no task can hold: a capped sample in one place, all columns streamed past it."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions import kernels as K
from ..functions.folded import Folded, Weighted
from ..operators.corr import columns
from ..operators.sampled import draw

LABELS = "win_id long, entity long, loading double, score double, lambda1 double, n_sample long"
#: Columns that are held against the sample at once.
SLICE = 512


def sampled_large(cells: DataFrame, r: float = 0.2, p: float = 1.4, cap: int | None = 4096, mode: str = "abs", max_broadcast: int = 256 << 20, cols: DataFrame | None = None) -> DataFrame:
    """win_id, entity, loading, score, lambda1 of every varying entity.  cols: columns(cells), if they are made already.

    The sample has at most `cap` columns a window, if there is one, equal ones once with their number.  They are gathered, checked against
    max_broadcast bytes and broadcast; where they are more, windows are handled in several passes.  Columns stay where they
    are: no shuffle of the window, and a task holds the sample, one batch and a slice of their correlations."""
    cols = columns(cells) if cols is None else cols.select("win_id", "entity", "x")
    mult = draw(cells, r, p, most=cap)
    keys = ["win_id", "x", *(["entity"] if mode == "negative" else [])]
    picked = cols.join(mult, ["win_id", "entity"]).withColumn("id", F.col("entity")).groupBy(*keys).agg(F.min("id").alias("id"), F.sum("mult").alias("mult"), F.count(F.lit(1)).alias("drawn"))
    widths = picked.groupBy("win_id").agg(F.sum(F.size("x") * 8 + 16).alias("bytes")).orderBy("win_id").collect()
    passes: list[list[int]] = [[]]
    full = 0
    for row in widths:
        if full and full + row["bytes"] > max_broadcast:
            passes.append([])
            full = 0
        passes[-1].append(row["win_id"])
        full += row["bytes"]
    out = None
    for wins in passes:
        sample: dict[int, tuple] = {}
        own = picked.where(F.col("win_id").isin(wins)).toPandas() if wins else None
        for w, g in own.groupby("win_id") if wins else []:
            g = g.sort_values("id")
            x, c = np.stack(g["x"].to_list()), g["mult"].to_numpy(float)
            lam, u, _ = Weighted(Folded(x, mode), np.arange(len(x)), c).principal()
            sample[int(w)] = (g["id"].to_numpy(), x, np.sqrt(c) * u, lam, lam / c.sum(), int(g["drawn"].sum()))
        shared = cells.sparkSession.sparkContext.broadcast(sample)

        def run(batches: Iterator[pd.DataFrame], shared=shared) -> Iterator[pd.DataFrame]:  # noqa: ANN001
            for b in batches:
                for w, g in b.groupby("win_id"):
                    ids, x, v, lam, score, drawn = shared.value[int(w)]
                    for lo in range(0, len(g), SLICE):
                        part = g.iloc[lo : lo + SLICE]
                        own, y = np.stack(part["x"].to_list()), np.zeros(len(part))
                        for at in range(0, len(x), 8 * SLICE):
                            some = slice(at, at + 8 * SLICE)
                            c = K.in_mode(np.clip(own @ x[some].T, -1, 1), mode)
                            if mode == "negative":  # 1 with itself in every mode
                                c[np.equal.outer(part["entity"].to_numpy(), ids[some])] = 1.0
                            y += c @ v[some]
                        yield pd.DataFrame({"win_id": int(w), "entity": part["entity"], "loading": np.minimum(np.abs(y) / np.sqrt(lam), 1.0), "score": score, "lambda1": lam, "n_sample": drawn})

        part = cols.where(F.col("win_id").isin(wins)).mapInPandas(run, LABELS)
        out = part if out is None else out.unionByName(part)
    return out


def tiled_power(tiled: DataFrame, mode: str = "abs", iterations: int = 30) -> DataFrame:
    """win_id, n, lambda1, score of windows whose correlations are in tiles."""
    v = tiled_vector(tiled, mode, iterations)
    return v.groupBy("win_id").agg(F.count(F.lit(1)).alias("n"), F.max("lambda1").alias("lambda1")).withColumn("score", F.col("lambda1") / F.col("n"))


def tiled_vector(tiled: DataFrame, mode: str = "abs", iterations: int = 30) -> DataFrame:
    """win_id, entity, v (largest entry 1), lambda1 by power iteration over tiles: each round, a task multiplies one tile with the
    two pieces of the vector it needs, and the products are summed by entity.  The vector, one double an entity, is
    checkpointed; tiles should be a written table."""
    from ..operators.score import cut_lineage

    kinds = "win_id long, entity long, y double"
    ids = tiled.where("bi = bj").select("win_id", F.explode("rows").alias("entity"))
    v = cut_lineage(ids.withColumn("v", F.lit(1.0)))
    keys = ["win_id", "bi", "bj"]
    place = tiled.where("bi = bj").select("win_id", F.col("bi").alias("b"), F.explode("rows").alias("entity"))
    tops = tiled.select(*keys)

    def run(t: pd.DataFrame, part: pd.DataFrame) -> pd.DataFrame:
        if not len(t):
            return pd.DataFrame({"win_id": [], "entity": [], "y": []})
        rows, cols = np.asarray(t["rows"].iloc[0]), np.asarray(t["cols"].iloc[0])
        p = K.in_mode(np.asarray(t["p"].iloc[0]).reshape(len(rows), len(cols)), mode)
        at = dict(zip(part["entity"], part["v"]))
        vr, vc = np.array([at[e] for e in rows]), np.array([at[e] for e in cols])
        if t["bi"].iloc[0] == t["bj"].iloc[0]:
            p = p.copy()
            np.fill_diagonal(p, 1.0)
            e, y = rows, p @ vc
        else:
            e, y = np.concatenate([rows, cols]), np.concatenate([p @ vc, p.T @ vr])
        return pd.DataFrame({"win_id": t["win_id"].iloc[0], "entity": e, "y": y})

    for _ in range(iterations):
        pieces = place.join(v, ["win_id", "entity"])
        need = pieces.join(tops, "win_id").where((F.col("b") == F.col("bi")) | (F.col("b") == F.col("bj"))).select(*keys, "entity", "v").toDF(*keys, "entity", "v")
        y = tiled.groupBy(*keys).cogroup(need.groupBy(*keys)).applyInPandas(run, kinds).groupBy("win_id", "entity").agg(F.sum("y").alias("y"))
        top = F.max("y").over(Window.partitionBy("win_id"))
        v = cut_lineage(y.select("win_id", "entity", (F.col("y") / top).alias("v"), top.alias("lambda1")))
    return v
