"""Removal of word sequences that stand more than once, by a compacted de Bruijn graph of word k-mers.

The k-mers of every text are edges of a de Bruijn graph over the corpus.  Of these a window of `window` words keeps one,
its minimizer (the k-mer with the least hash, the leftmost of equals): it depends on the window's words alone, so equal
windows have equal minimizers.  Consecutive windows with the same minimizer occurrence are one edge of the sparse graph:
minimizer h, hash g of its words, hash before of the edge that stands before it in the text, source coordinates.  Then,
by Spark joins:

1. Edges whose h stands once are dropped: none of their windows can repeat.
2. Edges are counted by (h, g).  Edge y is linked to edge x if x stands before every y and both stand equally often: no
   text enters or leaves between them (an in- and out-degree join of the graph with itself).  Linked edges are
   compacted, text by text along the source coordinates, into nonbranching paths; a path repeats as a whole.
3. If the edges of an h differ, the graph branches there.  Of each (h, g) one edge is expanded into its windows from the
   words at its source coordinates.
4. Every occurrence of a path is verified by a digest of its very bytes at its source coordinates, each window of step 3
   by a hash of all its words; what stands twice is removed.

Joins on keys that a large share of all rows may have are salted (even_join); all else is aggregated before it is
shuffled.  Texts are shuffled once, those with repeats twice.

Edge cases: null and empty texts have 0 words, and the digest of the empty string; texts shorter than the window keep
all words; a repeated row repeats all its windows, if it has any; rows with a null or repeated doc_id are judged each by
its own text; an empty table gives an empty result; other columns are ignored.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from . import kernel as K
from .common import even_join, forget, release, table, written

WINDOW, KMER = 35, 8
_LOW = 28


def paths_of(w: K.Words, window: int, k: int) -> tuple[np.ndarray, ...]:
    """(h, g, before, row, start word in the row, windows) of every edge of the rows; before is 0 where a text begins."""
    reach = window - k + 1
    n = len(w.ids) - window + 1
    if n <= 0:
        return tuple(np.zeros(0, t) for t in (np.uint64, np.uint64, np.uint64, np.int64, np.int64, np.int64))
    kmer = K.grams(w.ids, k)
    least = (kmer >> np.uint64(_LOW) << np.uint64(_LOW)) | (np.arange(len(kmer), dtype=np.uint64) & np.uint64((1 << _LOW) - 1))
    span = 1
    while span * 2 <= reach:
        least = np.minimum(least[:-span], least[span:])
        span *= 2
    if span < reach:
        least = np.minimum(least[: span - reach], least[reach - span :])
    start = np.flatnonzero(w.row[:n] == w.row[window - 1 :])
    at = (least[start] & np.uint64((1 << _LOW) - 1)).astype(np.int64)
    new = np.flatnonzero(np.r_[True, at[1:] != at[:-1]]) if len(at) else np.zeros(0, np.int64)
    count = np.diff(np.r_[new, len(at)])
    s = start[new]
    g, row = K.spans(w.ids, s, s + count + window - 1), w.row[s]
    before = np.zeros(len(g), np.uint64)
    same = row[1:] == row[:-1]
    before[1:][same] = g[:-1][same]
    return kmer[at[new]], g, before, row, s - w.first[row], count


def paths(docs: DataFrame, window: int, k: int) -> DataFrame:
    """h, g, before, key, start, n (windows) of every edge of all texts."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for lo, hi, data, offsets in K.text_slices(b.column(1)):
                h, g, before, row, s, n = paths_of(K.words(data, offsets), window, k)
                yield pa.RecordBatch.from_arrays([pa.array(K.signed(h)), pa.array(K.signed(g)), pa.array(K.signed(before)), b.column(0).slice(lo, hi - lo).take(pa.array(row)), pa.array(s.astype(np.int32)), pa.array(n.astype(np.int32))], names=["h", "g", "before", "key", "start", "n"])
        K.give_back()

    return docs.select("key", "text").mapInArrow(run, "h long, g long, before long, key long, start int, n int")


def edges(again: DataFrame) -> DataFrame:
    """h, g, c (occurrences), first (tag of one of them), link (the edge continues the only edge before it) of repeated h."""
    own = written(again.groupBy("h", "g").agg(F.count(F.lit(1)).alias("c"), F.min("before").alias("b0"), F.max("before").alias("b1"), F.min("tag").alias("first")), "edges")
    more = own.where("c > 1")
    after = more.where("b0 = b1 and b0 <> 0").groupBy(F.col("b0").alias("g"), "c").agg(F.min("g").alias("y"), F.count(F.lit(1)).alias("ways")).where("ways = 1")
    linked = after.join(more.select("g", "c"), ["g", "c"]).select(F.col("y").alias("g"), F.lit(True).alias("link"))
    out = written(own.join(linked.distinct(), "g", "left").select("h", "g", "c", "first", F.coalesce("link", F.lit(False)).alias("link")), "graph")
    forget(own)
    return out


def compacted(marked: DataFrame) -> DataFrame:
    """key, spans (g, start, n of every nonbranching path of the text), open (h, start, n, whole of edges to expand)."""
    own = marked.repartition("key").dropDuplicates(["key", "start"])  # repeated rows share a key and all edges
    along = Window.partitionBy("key").orderBy("start")
    own = own.withColumn("path", F.sum((~F.col("link")).cast("int")).over(along))
    runs = own.groupBy("key", "path").agg(F.min_by("g", "start").alias("g"), F.min("start").alias("start"), F.sum("n").cast("int").alias("n"), F.bool_and("whole").alias("whole"), F.collect_list(F.when(F.col("expand"), F.struct("h", F.col("start"), F.col("n"), "whole"))).alias("open"))
    return runs.groupBy("key").agg(F.collect_list(F.when(F.col("whole"), F.struct("g", "start", "n"))).alias("spans"), F.flatten(F.collect_list("open")).alias("open"))


_PLAIN, _HELPER, _OPEN = 0, 1, 2
_SEEN = pa.list_(pa.struct([("h", pa.int64()), ("w", pa.int64()), ("at", pa.int32()), ("n", pa.int32()), ("kind", pa.int8())]))
_SEEN_SQL = "array<struct<h:long,w:long,at:int,n:int,kind:byte>>"


def _line(out: np.ndarray, at: np.ndarray, a: int, z: int, ranges: np.ndarray | None, digest: bool) -> tuple[int, int, str]:
    """(words, removed words, kept words joined by a space or their SHA-256) of words a to z, those of ranges (starts, ends) removed."""
    body, gone = out[at[a] : at[z]], 0
    if ranges is not None and ranges.size:
        depth = np.zeros(z - a + 1, np.int32)
        np.add.at(depth, ranges[0], 1)
        np.add.at(depth, ranges[1], -1)
        cut = np.cumsum(depth[:-1]) > 0
        gone = int(cut.sum())
        body = body[np.repeat(~cut, np.diff(at[a : z + 1]))]
    line = body[:-1].tobytes()
    return z - a, gone, hashlib.sha256(line).hexdigest() if digest else line.decode()


def _lists(column: pa.ListArray) -> tuple[np.ndarray, dict[str, np.ndarray]]:
    """(rows + 1 offsets, fields) of a column of lists of structs; a null is an empty list."""
    size = np.array(column.value_lengths().fill_null(0), np.int64)
    flat = column.flatten()
    return np.r_[0, np.cumsum(size)], {f.name: flat.field(i).to_numpy(zero_copy_only=False) for i, f in enumerate(flat.type)}


def strip_repeats(docs: DataFrame, window: int = WINDOW, k: int = KMER, digest: bool = False) -> DataFrame:
    """doc_id, n_words, n_removed, kept: each document without the words of repeated windows, in the order they had.

    digest: kept is the SHA-256 of the kept words, so no second copy of the texts is written."""
    # rows with one key have one text, so that ranges found in one fit all of them
    docs = docs.select("doc_id", F.xxhash64(F.coalesce("doc_id", F.lit(-(2**63))), F.xxhash64("text"), F.crc32(F.col("text").cast("binary"))).alias("key"), "text")
    found = written(paths(docs, window, k), "paths")
    many = written(found.groupBy("h").agg(F.count(F.lit(1)).alias("c"), F.min("g").alias("g0"), F.max("g").alias("g1")).where("c > 1").select("h", "c", (F.col("g0") == F.col("g1")).alias("same")), "many")
    again = written(even_join(found, many, ["h"]).drop("c").withColumn("tag", F.xxhash64("key", "start")), "again")
    forget(found, many)
    graph = edges(again)
    marked = even_join(again, graph, ["h", "g"]).select("key", "h", "g", "start", "n", (F.col("c") > 1).alias("whole"), (~F.col("same") & ((F.col("c") == 1) | (F.col("tag") == F.col("first")))).alias("expand"), "link")
    todo = compacted(marked)

    def visit(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for lo, hi, data, offsets in K.text_slices(b.column(2)):
                rows = hi - lo
                part = b.slice(lo, rows)
                (sa, span), (oa, open_) = _lists(part.column(3)), _lists(part.column(4))
                out, at, first = K.normal(data, offsets)
                hashes = K.words(data, offsets).ids if oa[-1] else None
                done, sizes, seen = [], [], [[], [], [], [], []]
                for r in range(rows):
                    a, z = int(first[r]), int(first[r + 1])
                    if sa[r] == sa[r + 1] and oa[r] == oa[r + 1]:
                        done.append(_line(out, at, a, z, None, digest))
                        sizes.append(None)
                        continue
                    done.append((None, None, None))
                    s, n = span["start"][sa[r] : sa[r + 1]].astype(np.int64), span["n"][sa[r] : sa[r + 1]].astype(np.int64)
                    bytes_ = [hashlib.blake2b(out[at[a + x] : at[a + x + y + window - 1]], digest_size=8).digest() for x, y in zip(s.tolist(), n.tolist())]
                    own = [(span["g"][sa[r] : sa[r + 1]], np.frombuffer(b"".join(bytes_), np.int64), s, n + window - 1, np.full(len(s), _PLAIN))]
                    ids = hashes[a:z] if oa[r] < oa[r + 1] else None
                    for j in range(oa[r], oa[r + 1]):
                        p = np.arange(open_["start"][j], open_["start"][j] + open_["n"][j])
                        own.append((np.full(len(p), open_["h"][j]), K.signed(K.spans(ids, p, p + window)), p, np.full(len(p), window), np.full(len(p), _HELPER if open_["whole"][j] else _OPEN)))
                    for x, y in zip(seen, zip(*own)):
                        x.extend(y)
                    sizes.append(sum(len(x[0]) for x in own))
                flat = [pa.array(np.concatenate(x) if x else np.zeros(0, np.int64)).cast(f.type) for x, f in zip(seen, _SEEN.value_type)]
                ends = np.cumsum([0] + [x or 0 for x in sizes])
                # an offset that is null makes the row null
                places = pa.array([None if x is None else int(e) for x, e in zip(sizes, ends)] + [int(ends[-1])], pa.int32())
                told = pa.ListArray.from_arrays(places, pa.StructArray.from_arrays(flat, fields=list(_SEEN.value_type)))
                text = part.column(2).take(pa.array([None if x is None else r for r, x in enumerate(sizes)], pa.int64()))  # only where it is needed again
                yield pa.RecordBatch.from_arrays([part.column(0), part.column(1), *[pa.array(c, t) for c, t in zip(zip(*done), (pa.int64(), pa.int64(), pa.string()))], text, told], names=["doc_id", "key", "n_words", "n_removed", "kept", "text", "seen"])
        K.give_back()

    joined = docs.join(todo.hint("shuffle_hash"), "key", "left").select("doc_id", "key", "text", "spans", "open")
    first = written(joined.mapInArrow(visit, f"doc_id long, key long, n_words long, n_removed long, kept string, text string, seen {_SEEN_SQL}"), "visited")
    forget(again, graph)
    seen = first.where("seen is not null").select("key", F.explode("seen").alias("x")).select("key", "x.*")
    twice = written(seen.groupBy("h", "w", "n").agg(F.count(F.lit(1)).alias("c")).where("c > 1"), "twice")
    more = even_join(seen.where(F.col("kind") != _HELPER), twice, ["h", "w", "n"]).groupBy("key").agg(F.collect_set(F.struct("at", "n")).alias("more"))

    def close(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for lo, hi, data, offsets in K.text_slices(b.column(1)):
                part = b.slice(lo, hi - lo)
                where, m = _lists(part.column(2))
                out, at, first = K.normal(data, offsets)
                done = []
                for r in range(hi - lo):
                    s = m["at"][where[r] : where[r + 1]].astype(np.int64)
                    done.append(_line(out, at, int(first[r]), int(first[r + 1]), np.stack([s, s + m["n"][where[r] : where[r + 1]]]), digest))
                yield pa.RecordBatch.from_arrays([part.column(0), *[pa.array(c, t) for c, t in zip(zip(*done), (pa.int64(), pa.int64(), pa.string()))]], names=["doc_id", "n_words", "n_removed", "kept"])
        K.give_back()

    rest = first.where("seen is not null").select("doc_id", "key", "text").join(more.hint("shuffle_hash"), "key", "left")
    closed = rest.select("doc_id", "text", "more").mapInArrow(close, "doc_id long, n_words long, n_removed long, kept string")
    release(docs.sparkSession)
    return first.where("seen is null").select("doc_id", "n_words", "n_removed", "kept").unionByName(closed)


def op3_debruijn_substrings(spark: SparkSession, sf_dir: str) -> DataFrame:
    return strip_repeats(table(spark, sf_dir, "documents"), digest=True).withColumnRenamed("kept", "kept_sha256")


#: The same rows by window sequences themselves: every window of 35 words is compared as a string.
SQL = r"""
WITH w AS (SELECT doc_id, regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+') AS ws FROM documents),
t AS (SELECT doc_id, unnest(ws) AS word, generate_subscripts(ws, 1) AS i FROM w),
g AS (SELECT doc_id, word, i, string_agg(word, ' ') OVER (PARTITION BY doc_id ORDER BY i ROWS BETWEEN CURRENT ROW AND 34 FOLLOWING) AS span, count(*) OVER (PARTITION BY doc_id ORDER BY i ROWS BETWEEN CURRENT ROW AND 34 FOLLOWING) AS k FROM t),
r AS (SELECT doc_id, word, i, k = 35 AND count(*) OVER (PARTITION BY span, k) > 1 AS again FROM g),
c AS (SELECT doc_id, word, i, coalesce(bool_or(again) OVER (PARTITION BY doc_id ORDER BY i ROWS BETWEEN 34 PRECEDING AND CURRENT ROW), false) AS gone FROM r),
d AS (SELECT doc_id, count(*) AS n_words, count(*) FILTER (gone) AS n_removed, coalesce(string_agg(word, ' ' ORDER BY i) FILTER (NOT gone), '') AS kept FROM c GROUP BY doc_id)
SELECT w.doc_id, coalesce(n_words, 0) AS n_words, coalesce(n_removed, 0) AS n_removed, sha256(coalesce(kept, '')) AS kept_sha256 FROM w LEFT JOIN d USING (doc_id)
"""
