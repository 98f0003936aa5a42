"""What is done with members and alerts: grading, merging, unique finds, history, networks, bursts, timelines."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .score import cut_lineage


def _of(members: DataFrame, detector: str) -> DataFrame:
    return members.where(F.col("detector") == detector).select("win_id", "entity").distinct()


def core(members: DataFrame, one: str = "sampled", other: str = "block") -> DataFrame:
    """win_id, entity found by both."""
    return _of(members, one).intersect(_of(members, other))


def suspicious(members: DataFrame, one: str = "sampled", other: str = "block") -> DataFrame:
    """win_id, entity, found_by: found by just one of both."""
    a, b = _of(members, one).withColumn("a", F.lit(True)), _of(members, other).withColumn("b", F.lit(True))
    both = a.join(b, ["win_id", "entity"], "full")
    return both.where("a is null or b is null").select("win_id", "entity", F.when(F.col("a"), one).otherwise(other).alias("found_by"))


def merge(members: DataFrame, one: str = "sampled", other: str = "block") -> DataFrame:
    """win_id, entity, grade, found_by of all found by either: core or suspicious."""
    own = members.where(F.col("detector").isin(one, other)).groupBy("win_id", "entity").agg(F.array_join(F.array_sort(F.collect_set("detector")), "+").alias("found_by"))
    return own.select("win_id", "entity", F.when(F.col("found_by").contains("+"), "core").otherwise("suspicious").alias("grade"), "found_by")


def unique(members: DataFrame) -> DataFrame:
    """win_id, detector, n_members, n_unique (entities no other detector named in the window), is_unique."""
    own = members.select("win_id", "detector", "entity").distinct()
    by = own.groupBy("win_id", "entity").agg(F.count(F.lit(1)).alias("k"))
    return own.join(by, ["win_id", "entity"]).groupBy("win_id", "detector").agg(F.count(F.lit(1)).alias("n_members"), F.count_if(F.col("k") == 1).alias("n_unique")).withColumn("is_unique", F.col("n_unique") > 0)


def history(members: DataFrame, back_seconds: int) -> DataFrame:
    """win_id, entity, seen: earlier windows of the last `back_seconds` in which the entity was named, this one left out."""
    own = members.select("win_id", "entity").distinct()
    w = Window.partitionBy("entity").orderBy("win_id").rangeBetween(-back_seconds, -1)
    return own.withColumn("seen", F.count(F.lit(1)).over(w))


def edge_summary(pairs: DataFrame, members: DataFrame, cut: float = 0.7) -> DataFrame:
    """i, j, windows together, mean |rho|, windows over the cut, of pairs named together by some detector.  pairs: a pair table,
    or the members' unit rows (corr.pairs_among with rows)."""
    if "u" in pairs.columns:
        return _edges_of_rows(pairs, cut)
    end = lambda e: members.select("win_id", F.col("entity").alias(e)).distinct()
    both = pairs.join(end("i"), ["win_id", "i"]).join(end("j"), ["win_id", "j"])
    a = F.abs("rho")
    return both.groupBy("i", "j").agg(F.count(F.lit(1)).alias("windows"), F.avg(a).alias("mean_rho"), F.count_if(a > cut).alias("strong"))


def _edges_of_rows(rows: DataFrame, cut: float, tile: int = 1024) -> DataFrame:
    """A task makes the pairs of two blocks of entities along all windows and hands over their sums: there is no row for a pair
    and window."""
    rows = cut_lineage(rows)
    top = rows.agg((F.ceil(F.count_distinct("entity") / tile) - 1).cast("int").alias("top"))  # one row
    placed = rows.crossJoin(F.broadcast(top)).withColumn("b", F.pmod(F.xxhash64("entity"), F.col("top") + 1).cast("int"))
    left = placed.select(F.col("b").alias("bi"), F.explode(F.sequence("b", "top")).alias("bj"), F.lit(True).alias("row"), "win_id", "entity", "u")
    right = placed.select(F.explode(F.sequence(F.lit(0), "b")).alias("bi"), F.col("b").alias("bj"), F.lit(False).alias("row"), "win_id", "entity", "u").where("bi < bj")

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        own: dict[tuple[int, bool], list[tuple[np.ndarray, np.ndarray]]] = {}
        diagonal = False
        for b in batches:
            diagonal = bool(b["bi"].iloc[0] == b["bj"].iloc[0])
            for (win, row), g in b.groupby(["win_id", "row"]):
                own.setdefault((int(win), bool(row)), []).append((g["entity"].to_numpy(), np.stack(g["u"].to_list())))
        ids = [np.unique(np.concatenate([e for (_, row), parts in own.items() if row == side for e, _ in parts] or [np.zeros(0, np.int64)])) for side in (True, False)]
        if diagonal:
            ids[1] = ids[0]
        shape = len(ids[0]), len(ids[1])
        windows, total, strong = np.zeros(shape, np.int32), np.zeros(shape), np.zeros(shape, np.int32)
        for win in sorted({w for w, _ in own}):
            a = own.pop((win, True), None)
            b = a if diagonal else own.pop((win, False), None)
            if a is None or b is None:
                continue
            (ea, ua), (eb, ub) = ((np.concatenate([e for e, _ in parts]), np.concatenate([u for _, u in parts])) for parts in (a, b))
            p = np.abs(np.clip(ua @ ub.T, -1, 1))
            at = np.ix_(np.searchsorted(ids[0], ea), np.searchsorted(ids[1], eb))
            windows[at] += 1
            total[at] += p
            strong[at] += p > cut
        for lo in range(0, shape[0], 128):
            part = slice(lo, lo + 128)
            i, j = np.nonzero(windows[part])
            k = (ids[0][lo + i] < ids[1][j]) if diagonal else np.ones(len(i), bool)
            i, j = i[k] + lo, j[k]
            a, b, n = ids[0][i], ids[1][j], windows[i, j]
            yield pd.DataFrame({"i": np.minimum(a, b), "j": np.maximum(a, b), "windows": n.astype(np.int64), "mean_rho": total[i, j] / n, "strong": strong[i, j].astype(np.int64)})

    return left.unionByName(right).groupBy("bi", "bj").applyInPandas(run, "i long, j long, windows long, mean_rho double, strong long")


def pair_frequency(pairs: DataFrame, category: DataFrame, cut: float = 0.7) -> DataFrame:
    """category, pairs of windows seen, strong ones: how often two entities of one category (entity, category) correlate."""
    end = lambda e: category.select(F.col("entity").alias(e), F.col("category").alias(f"c{e}"))
    both = pairs.join(end("i"), "i").join(end("j"), "j").where("ci = cj")
    return both.groupBy(F.col("ci").alias("category")).agg(F.count(F.lit(1)).alias("pairs"), F.count_if(F.abs("rho") > cut).alias("strong"))


def timeline(best: DataFrame, detectors: list[str]) -> DataFrame:
    """win_id and a score and an alert column for each detector."""
    out = best.groupBy("win_id").pivot("detector", detectors).agg(F.first("score").alias("score"), F.first("alert").alias("alert"))
    return out.orderBy("win_id")


def sizes(members: DataFrame) -> DataFrame:
    """win_id, detector, n_members, and the detector's mean over its windows."""
    own = members.groupBy("win_id", "detector").agg(F.count_distinct("entity").alias("n_members"))
    return own.withColumn("mean_members", F.avg("n_members").over(Window.partitionBy("detector")))


def bursts(alerts: DataFrame, gap: int) -> DataFrame:
    """detector, first, last window and number of alerts of each run of alert windows at most `gap` seconds apart."""
    own = alerts.select("detector", "win_id").distinct()
    w = Window.partitionBy("detector").orderBy("win_id")
    new = F.coalesce((F.col("win_id") - F.lag("win_id").over(w) > gap).cast("int"), F.lit(1))
    marked = own.withColumn("new", new).withColumn("burst", F.sum("new").over(w))
    return marked.groupBy("detector", "burst").agg(F.min("win_id").alias("first_win"), F.max("win_id").alias("last_win"), F.count(F.lit(1)).alias("n_alerts"))
