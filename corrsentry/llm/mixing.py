"""Mixing sources to target weights by Pfair scheduling.

Each source's documents form blocks.  The ideal mix serves all sources at once, each at a rate in proportion to its
weight, until it has run out; the others then share its part.  When every source has had v blocks for each unit of
weight, R(v) = sum of min(blocks, weight * v) slots have passed.  So block i of a source with weight w may run from slot
floor(R(i / w)) on and must run before slot ceil(R((i + 1) / w)); the released block with the earliest deadline runs in
each slot.  The ideal mix itself shows that this always fits, so at every slot each source is less than one block away
from its share by the weights as given: they are whole numbers of one unit, and nothing is rounded, however many slots.

The order is made by one task that holds a few numbers for each source and hands on a row for each block; that part
grows with the blocks (1/16 of the documents) and is not shortened by more machines.  The driver holds nothing.

`mixed` is the older form with weights rounded to quanta of 1/q, for which a schedule of q slots repeats: its sources
keep to the rounded weights only, and it takes at most MAX_SOURCES sources.  No query uses it.

Edge cases: a null source is a source of its own; unknown sources in the weights are ignored; sources without a weight,
or with weight 0, wait until the others have run out and then share equally; an empty table gives an empty result;
repeated rows each get a position.
"""

from __future__ import annotations

import heapq
from bisect import bisect_right
from collections.abc import Iterator
from fractions import Fraction
from itertools import accumulate
from math import lcm

import pyarrow as pa

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import ranked, table, written

Q = 1000
#: More sources than this are refused by `mixed`: its schedule would no longer be small.
MAX_SOURCES = 400


def quanta(weights: dict, q: int = Q) -> dict:
    """Whole quanta, at least one each, that add up to q, by largest remainder."""
    total = sum(weights.values())
    q = max(q, len(weights))
    spare = q - len(weights)
    exact = {s: spare * w / total for s, w in weights.items()}
    out = {s: 1 + int(x) for s, x in exact.items()}
    left = q - sum(out.values())
    for s in sorted(exact, key=lambda s: (int(exact[s]) - exact[s], str(s)))[:left]:
        out[s] += 1
    return out


def edf(k: dict) -> list:
    """Source of each slot of one round: earliest deadline first among the released blocks, ties by name.  sum(k) slots."""
    q = sum(k.values())
    releases: list[list] = [[] for _ in range(q + 1)]
    for s, n in k.items():
        for i in range(n):
            releases[i * q // n].append((-(-(i + 1) * q // n), str(s), i, s))
    ready: list = []
    out = []
    for t in range(q):
        for b in releases[t]:
            heapq.heappush(ready, b)
        deadline, _, _, s = heapq.heappop(ready)
        assert t < deadline
        out.append(s)
    return out


def schedule(blocks: dict, weights: dict, q: int = Q) -> tuple[list[tuple], list[tuple]]:
    """(phases, turns).  phases: (phase, source, first block, end block, first slot, quanta, slots a round);
    turns: (phase, source, turn, slot in the round)."""
    left = {s: n for s, n in blocks.items() if n > 0}
    done = dict.fromkeys(left, 0)
    phases, turns, slot, phase = [], [], 0, 0
    while left:
        k = quanta({s: weights[s] for s in left}, q)
        order = edf(k)
        size = len(order)
        at: dict = {s: [] for s in left}
        for t, s in enumerate(order):
            at[s].append(t)
        ends = {s: (n - 1) // k[s] * size + at[s][(n - 1) % k[s]] + 1 for s, n in left.items()}
        stop = min(ends.values())
        for s in left:
            ran = stop // size * k[s] + sum(t < stop % size for t in at[s])
            phases.append((phase, s, done[s], done[s] + ran, slot, k[s], size))
            turns += [(phase, s, j, t) for j, t in enumerate(at[s])]
            done[s] += ran
            left[s] -= ran
        left = {s: n for s, n in left.items() if n > 0}
        slot, phase = slot + stop, phase + 1
    return phases, turns


def mixed(rows: DataFrame, weights: dict | None = None, block: int = 16, temperature: float = 0.5, q: int = Q) -> DataFrame:
    """rows (written table: doc_id, source, extra columns) -> rows with block, slot, phase, release, deadline and pos, all long.

    weights: source -> target weight; None: each source's count to the power `temperature`.  block: documents in a block.
    release and deadline are slots within the phase.  pos is gapless from 0 over all rows in schedule order."""
    spark = rows.sparkSession
    rows = rows.drop("block", "slot", "phase", "release", "deadline", "pos").withColumn("_src", F.coalesce(F.col("source"), F.lit("\x00")))
    counts = {r["_src"]: r["n"] for r in rows.groupBy("_src").agg(F.count(F.lit(1)).alias("n")).limit(MAX_SOURCES + 1).collect()}
    if len(counts) > MAX_SOURCES:
        raise ValueError(f"more than {MAX_SOURCES} sources: group them before mixing")
    least = min((w for w in (weights or {}).values() if w > 0), default=1.0)
    target = {s: float(n) ** temperature if weights is None else max(weights.get(None if s == "\x00" else s, 0.0), least * 1e-6) for s, n in counts.items()}
    n_blocks = {s: -(-n // block) for s, n in counts.items()}
    phases, turns = schedule(n_blocks, target, q)
    p = F.broadcast(spark.createDataFrame(phases, "phase long, _src string, _from long, _to long, _slot0 long, _k long, _size long"))
    t = F.broadcast(spark.createDataFrame(turns, "phase long, _src string, _turn long, _at long"))
    df = ranked(rows, ["_src"], ["doc_id"], "_rank", sum(counts.values())).withColumn("block", F.floor(F.col("_rank") / block))
    df = df.join(p, (df["_src"] == p["_src"]) & (F.col("block") >= F.col("_from")) & (F.col("block") < F.col("_to"))).drop(p["_src"])
    i = F.col("block") - F.col("_from")
    df = df.withColumn("_round", F.floor(i / F.col("_k"))).withColumn("_turn", F.pmod(i, F.col("_k")))
    df = df.join(t, ["phase", "_src", "_turn"])
    df = df.withColumn("slot", F.col("_slot0") + F.col("_round") * F.col("_size") + F.col("_at"))
    short = {s: n_blocks[s] * block - n for s, n in counts.items() if n % block}
    last = {s: next((s0 + (n_blocks[s] - 1 - a) // k * size + [x[3] for x in turns if x[0] == ph and x[1] == s][(n_blocks[s] - 1 - a) % k]) for ph, src, a, b, s0, k, size in phases if src == s and a <= n_blocks[s] - 1 < b) for s in short}
    missing = F.lit(0)
    for s, gap in short.items():
        missing = missing + F.when(F.col("slot") > last[s], gap).otherwise(0)
    pos = F.col("slot") * block - missing + F.pmod(F.col("_rank"), F.lit(block))
    release, deadline = F.floor(i * F.col("_size") / F.col("_k")), F.ceil((i + 1) * F.col("_size") / F.col("_k"))
    return df.select(*[c for c in rows.columns if c != "_src"], "block", "slot", "phase", release.alias("release"), deadline.alias("deadline"), pos.cast("long").alias("pos"))


def whole_weights(weights: list) -> list[int]:
    """The same proportions as whole numbers, exactly."""
    exact = [Fraction(w) for w in weights]
    unit = lcm(*[x.denominator for x in exact])
    return [x.numerator * (unit // x.denominator) for x in exact]


def order(blocks: list[int], weights: list[int]) -> Iterator[tuple[int, int, int, int]]:
    """(source, block, release, deadline) of each slot from 0 on, for sources with so many blocks (1 or more) and such whole weights."""
    fine = 2 * max(weights, default=1).bit_length() + 1  # so many bits tell any two of the fractions below apart
    by_end = sorted(((n << fine) // w, n, w) for n, w in zip(blocks, weights))
    ends = [e for e, _, _ in by_end]
    ran = [0, *accumulate(n for _, n, _ in by_end)]
    rate = [sum(weights)]
    for _, _, w in by_end:
        rate.append(rate[-1] - w)

    def passed(s: int, i: int) -> tuple[int, int]:
        """R(i / w) rounded down and up."""
        w = weights[s]
        j = bisect_right(ends, (i << fine) // w)
        slots = ran[j] * w + i * rate[j]
        return slots // w, -(-slots // w)

    ready, later = [], []
    for s in range(len(blocks)):
        after, deadline = passed(s, 1)
        ready.append((deadline, s, 0, 0, after))
    heapq.heapify(ready)
    for t in range(ran[-1]):
        while later and later[0][0] <= t:
            heapq.heappush(ready, heapq.heappop(later)[1])
        deadline, s, i, release, after = heapq.heappop(ready)
        assert release <= t < deadline
        yield s, i, release, deadline
        if i + 1 < blocks[s]:
            release, (after, deadline) = after, passed(s, i + 2)
            heapq.heappush(later, (release, (deadline, s, i + 1, release, after)))


_TURN = {"_src": pa.string(), "block": pa.int64(), "slot": pa.int64(), "phase": pa.int64(), "release": pa.int64(), "deadline": pa.int64(), "_first": pa.int64()}


def turns_of(counts: DataFrame, weights: dict | None, block: int, temperature: float) -> DataFrame:
    """counts (_src, n) -> _src, block, slot, phase, release, deadline, _first (documents before the block): every block's turn."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        known = sorted(x for b in batches for x in zip(b.column(0).to_pylist(), b.column(1).to_pylist()))
        given = [float(n) ** temperature if weights is None else weights.get(None if s == "\x00" else s, 0) for s, n in known]
        slot = first = 0
        out: list[tuple] = []
        for phase in (0, 1):  # the sources with a weight, then those without
            part = [(s, n, w if phase == 0 else 1) for (s, n), w in zip(known, given) if (w > 0) == (phase == 0)]
            start = slot
            for s, i, release, deadline in order([-(-n // block) for _, n, _ in part], whole_weights([w for _, _, w in part])):
                out.append((part[s][0], i, slot, phase, start + release, start + deadline, first))
                slot, first = slot + 1, first + min(block, part[s][1] - i * block)
                if len(out) == 65_536:
                    yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*out), _TURN.values())], names=list(_TURN))
                    out = []
        if out:
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*out), _TURN.values())], names=list(_TURN))

    return counts.select("_src", "n").repartition(1).mapInArrow(run, "_src string, block long, slot long, phase long, release long, deadline long, _first long")


def placed(rows: DataFrame, weights: dict | None = None, block: int = 16, temperature: float = 0.5) -> DataFrame:
    """rows (written table: doc_id, source, extra columns) -> rows with block, slot, phase, release, deadline and pos, all long.

    weights: source -> target weight; None: each source's count to the power `temperature`.  block: documents in a block.
    release and deadline are slots of the whole schedule.  phase: 1 for sources without a weight, else 0.  pos is gapless
    from 0 over all rows in schedule order.  A source's documents come by a hash of their ids, so that any cell of the
    metadata has its part of every stretch of the schedule."""
    rows = rows.drop("block", "slot", "phase", "release", "deadline", "pos").withColumn("_src", F.coalesce(F.col("source"), F.lit("\x00")))
    rows = rows.withColumn("_h", F.xxhash64("doc_id", F.lit(8)))
    turns = written(turns_of(rows.groupBy("_src").agg(F.count(F.lit(1)).alias("n")), weights, block, temperature), "turns")
    df = ranked(rows, ["_src"], ["_h", "doc_id"], "_rank").withColumn("block", F.floor(F.col("_rank") / block)).join(turns, ["_src", "block"])
    pos = F.col("_first") + F.pmod(F.col("_rank"), F.lit(block))
    return df.select(*[c for c in rows.columns if c not in ("_src", "_h")], "block", "slot", "phase", "release", "deadline", pos.cast("long").alias("pos"))


def op8_pfair_mix(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every document's place in the mix of all sources; weights grow with the square root of a source's documents."""
    rows = written(table(spark, sf_dir, "documents").select("doc_id", "source"), "sources")
    return placed(rows).select("doc_id", "source", "block", "phase", "release", "deadline", "slot", "pos")


def mix_documents(docs: DataFrame) -> DataFrame:
    """docs in schedule order: the rows themselves, range-dealt and sorted by position."""
    places = placed(written(docs.select("doc_id", "source"), "sources")).select("doc_id", "pos")
    places = places.groupBy("doc_id").agg(F.min("pos").alias("_pos"))
    keyed = docs.join(places, docs["doc_id"].eqNullSafe(places["doc_id"])).drop(places["doc_id"])
    return keyed.orderBy("_pos").drop("_pos")
