"""Sharding by K-d tree: cells of the metadata space are split at weighted medians along their widest dimension.

Rows weigh their bytes.  Rows of one group (equal texts) have one point in the space and stay together.  Groups that
are heavy against a shard are dealt first, the heaviest to the emptiest shard; a group over a whole shard is cut into
pieces by a hash of its rows' ids.  The tree then fills what the heavy groups left, so sizes come out near equal.

Every median is exact over all rows to the resolution of two nested histograms, which tasks make and Spark sums; what
reaches the driver grows with the number of shards and not with the rows: bins, and at most 4 * shards / heavy groups.

Edge cases: a null text has 16 bytes and groups with other nulls only; null dimensions count as 0 or ''; an empty
table gives an empty result; with fewer groups than shards some shards are empty; repeated rows all get a slot.
"""

from __future__ import annotations

import heapq
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import ranked, table, written

COARSE, FINE = 256, 1024


def points(rows: DataFrame, dims: list[str]) -> DataFrame:
    """Group rows (gkey, bytes, dims) with each dimension as a double in [0, 1]: numbers by their place between least and largest
    logarithm, strings by hash.  A thousandth of the range is a hash of the group, so that equal values can be split."""
    kinds = dict(rows.dtypes)
    numeric = [d for d in dims if kinds[d] != "string"]
    log = {d: F.signum(F.coalesce(F.col(d).cast("double"), F.lit(0.0))) * F.log1p(F.abs(F.coalesce(F.col(d).cast("double"), F.lit(0.0)))) for d in numeric}
    ends = rows.agg(F.count(F.lit(1)), *[f(log[d]) for d in numeric for f in (F.min, F.max)]).first()
    spread = F.pmod(F.xxhash64("gkey", F.lit(7)), F.lit(1 << 20)) / float(1 << 20)
    out = []
    for d in dims:
        if d in log:
            lo, hi = (ends[1 + 2 * numeric.index(d) + i] or 0.0 for i in (0, 1))
            at = (log[d] - lo) / (hi - lo) if hi > lo else F.lit(0.0)
            out.append((at * 0.999 + spread * 0.001).alias(f"c{len(out)}"))
        else:
            at = F.pmod(F.xxhash64(F.coalesce(F.col(d), F.lit(""))), F.lit(1000)) / 1000.0
            out.append((at + spread * 0.001).alias(f"c{len(out)}"))
    return rows.select("gkey", "bytes", *out)


def locate(x: np.ndarray, splits: dict[int, tuple[int, float]]) -> np.ndarray:
    """Node of each point; node k has children 2k + 1 (at or under the cut) and 2k + 2."""
    node = np.zeros(len(x), np.int64)
    for k in sorted(splits):
        d, cut = splits[k]
        here = node == k
        node[here] = np.where(x[here, d] <= cut, 2 * k + 1, 2 * k + 2)
    return node


def _histogram(pts: DataFrame, n: int, splits: dict, wanted: dict[int, list[tuple[int, float, float]]], bins: int) -> dict[tuple[int, int], np.ndarray]:
    """(node, dim) -> bytes in each bin of [lo, hi); tasks return their bins, which are summed by Spark."""
    names = [f"c{i}" for i in range(n)]

    def count(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        total: dict[tuple[int, int], np.ndarray] = {}
        for b in batches:
            x, w = b[names].to_numpy(), b["bytes"].to_numpy(np.float64)
            node = locate(x, splits)
            for k, ranges in wanted.items():
                here = node == k
                if here.any():
                    for d, lo, hi in ranges:
                        v = x[here, d]
                        inside = (v >= lo) & (v < hi)
                        at = np.minimum(((v[inside] - lo) / (hi - lo) * bins).astype(np.int64), bins - 1)
                        total[k, d] = total.get((k, d), 0) + np.bincount(at, w[here][inside], bins)
        for (k, d), h in total.items():
            full = np.flatnonzero(h)
            yield pd.DataFrame({"node": k, "dim": d, "bin": full, "w": h[full].astype(np.int64)})

    found: dict[tuple[int, int], np.ndarray] = {}
    summed = pts.mapInPandas(count, "node long, dim int, bin int, w long").groupBy("node", "dim", "bin").agg(F.sum("w").alias("w"))
    for r in summed.collect():
        found.setdefault((r["node"], r["dim"]), np.zeros(bins))[r["bin"]] = r["w"]
    return found


def tree(pts: DataFrame, dims: int, room: list[float]) -> tuple[dict[int, tuple[int, float]], dict[int, int]]:
    """(splits, leaf node -> shard).  room: the share of the bytes that each shard is to get."""
    splits: dict[int, tuple[int, float]] = {}
    leaves: dict[int, int] = {}
    level = {0: (0, len(room), [(0.0, 1.001)] * dims)}
    while level:
        for k in [k for k, (a, b, _) in level.items() if b - a == 1]:
            leaves[k] = level.pop(k)[0]
        if not level:
            break
        coarse = _histogram(pts, dims, splits, {k: [(d, *box[d]) for d in range(dims)] for k, (_, _, box) in level.items()}, COARSE)
        pick, fine = {}, {}
        for k, (a, b, box) in level.items():
            mid = (a + b) // 2
            want = sum(room[a:mid]) / max(sum(room[a:b]), 1e-300)
            width = {}
            for d in range(dims):
                full = np.flatnonzero(coarse.get((k, d), np.zeros(COARSE)))
                width[d] = (full[-1] - full[0] + 1) * (box[d][1] - box[d][0]) / COARSE if len(full) else 0.0
            d = max(width, key=lambda d: (width[d], -d))
            lo, hi = box[d]
            h = coarse.get((k, d), np.zeros(COARSE))
            goal = want * h.sum()
            at = min(int(np.searchsorted(np.cumsum(h), goal)), COARSE - 1)
            step = (hi - lo) / COARSE
            pick[k] = (d, goal - h[:at].sum(), lo + at * step, lo + (at + 1) * step)
            fine[k] = [(d, pick[k][2], pick[k][3])]
        close = _histogram(pts, dims, splits, fine, FINE)
        nxt = {}
        for k, (a, b, box) in level.items():
            d, rest, lo, hi = pick[k]
            c = np.concatenate([[0.0], np.cumsum(close.get((k, d), np.zeros(FINE)))])
            at = int(np.abs(c - rest).argmin())
            cut = float(np.nextafter(lo + at * (hi - lo) / FINE, -np.inf))
            splits[k] = (d, cut)
            mid = (a + b) // 2
            left, right = list(box), list(box)
            left[d], right[d] = (box[d][0], max(cut, box[d][0]) + 1e-12), (min(cut, box[d][1] - 1e-9), box[d][1])
            nxt[2 * k + 1], nxt[2 * k + 2] = (a, mid, left), (mid, b, right)
        level = nxt
    return splits, leaves


def kd_shards(rows: DataFrame, dims: list[str], n_shards: int | None = None, target_bytes: int | None = None, heavy: float = 1 / 32, by: str | None = None) -> DataFrame:
    """rows (written table with doc_id, gkey long, size long and the columns in dims) -> rows with shard int, slot long.

    by: a column with the numbers from 0 on, each once, by which the slots of a shard are numbered; None: by a hash of the ids.
    Shards: n_shards, or as many as target_bytes asks for.  A group's point has the least value of each dimension among its rows."""
    rows = rows.drop("shard", "slot", "piece", "pieces")
    whole = rows.agg(F.count(F.lit(1)).alias("n"), F.coalesce(F.sum("size"), F.lit(0)).alias("b")).first()
    n = n_shards or max(1, -(-whole["b"] // target_bytes))
    target = max(1.0, whole["b"] / n)
    groups = written(rows.groupBy("gkey").agg(F.sum("size").alias("bytes"), *[F.min(d).alias(d) for d in dims]), "groups")
    big = {r["gkey"]: r["bytes"] for r in groups.where(F.col("bytes") > target * heavy).select("gkey", "bytes").collect()}  # at most n / heavy
    cut = {k: int(2 * b // (target * heavy)) for k, b in big.items() if b > target}
    spark = rows.sparkSession
    few = F.broadcast(spark.createDataFrame([(k, cut.get(k, 1)) for k in big], "gkey long, pieces int"))
    piece = F.pmod(F.xxhash64("doc_id"), F.col("pieces")).cast("int")
    heavy_rows = rows.join(few, "gkey").withColumn("piece", piece).drop("pieces")
    pieces = [(r["bytes"], r["gkey"], r["piece"]) for r in heavy_rows.groupBy("gkey", "piece").agg(F.sum("size").alias("bytes")).collect()]
    load = [(0, s) for s in range(n)]
    where = []
    for b, k, p in sorted(pieces, reverse=True):
        full, s = heapq.heappop(load)
        where.append((k, p, s))
        heapq.heappush(load, (full + b, s))
    room = [0.0] * n
    for full, s in load:
        room[s] = max(0.0, target - full)
    if sum(room) <= 0:
        room = [1.0] * n
    light = groups.where(F.col("bytes") <= target * heavy)
    pts = written(points(light, dims), "points")
    splits, leaves = tree(pts, len(dims), room)
    names = [f"c{i}" for i in range(len(dims))]

    def assign(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for b in batches:
            node = locate(b[names].to_numpy(), splits)
            yield pd.DataFrame({"gkey": b["gkey"], "shard": np.array([leaves[k] for k in node], np.int32)})

    placed = pts.mapInPandas(assign, "gkey long, shard int")
    known = F.broadcast(spark.createDataFrame(where, "gkey long, piece int, shard int"))
    out = rows.join(placed, "gkey").unionByName(heavy_rows.join(known, ["gkey", "piece"]).drop("piece"))
    order = ["doc_id", "gkey"] if by is None else [by]
    return ranked(written(out, "placed"), ["shard"], order, "slot", whole["n"], place=None if by is None else F.col(by))


def text_key() -> Column:
    """Hash that equal texts share."""
    text = F.coalesce(F.col("text"), F.lit("")).cast("binary")
    return F.xxhash64("text", F.crc32(text), F.length(text))


def sized(docs: DataFrame) -> DataFrame:
    """The slim columns that sharding needs; texts are read once, here."""
    text = F.coalesce(F.col("text"), F.lit("")).cast("binary")
    return docs.select("doc_id", (F.length(text) + 16).cast("long").alias("size"), F.crc32(text).alias("text_crc32"), text_key().alias("gkey"), F.length("text").alias("chars"), "lang", "source")


def op1_kd_shards(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All documents in shards 0 to 39 by the law `bytes`: equal texts together, shards within a hundredth or so of equal bytes."""
    rows = written(sized(table(spark, sf_dir, "documents")), "sized")
    out = kd_shards(rows, ["chars", "lang", "source", "doc_id"], n_shards=40)
    return out.select("doc_id", "size", "text_crc32", F.lit("bytes").alias("law"), "shard", "slot", F.lit(None).cast("int").alias("grown_shard"))
