"""Benchmark decontamination: SimHash of item-sized windows, multi-index Hamming look-up, exact verification.

Words are lower-cased (A-Z) without ASCII punctuation; shingles are five words, or the whole text of a shorter item.
A window is as many consecutive words of a document as the item has (the whole document, if that is shorter).  Windows
have a 256-bit SimHash, looked up in a multi-index of the items of that length: the bits are cut into 16 blocks, and by
the pigeonhole principle two fingerprints within the radius of 63 differ in some block by at most 3 bits, so the items
that are that near in a block are all that can be within the radius.  Each hit is then verified by weighted Jaccard
similarity of the two shingle multisets (weight: log(1 + items / items with the shingle)), 0.8 or more.

Shingles count in a fingerprint by the root of their weight: two sets of weighted similarity s then have a cosine of at
least 2 s / (1 + s), however uneven the weights, which is 0.889 at 0.8: about 39 of 256 bits differ, and 64 or more in
about one case of 100,000.

Only windows that can reach the similarity get a fingerprint: the rarest shingles of an item that together hold over a
fifth of its weight are its seeds; a window without any seed has a similarity under 0.8, so all windows that cover a seed
are looked at and no other.  Common shingles are no seeds, so a sentence that many items share finds nothing by itself.

Items are held in blocks of at most `block_words` words, one pass over the documents for each block.  Weights are those
of the whole benchmark in every block: Spark counts the items and the shingles' items once, and each block is handed the
shingles that stand in two items or more (one item weighs as much as none), 16 bytes each beside its own items.

Edge cases: null and empty texts hold nothing; items without words match nothing; items repeated in the benchmark are
each reported; an item may be the whole document; of equally similar windows the first is told; empty tables give an
empty result.
"""

from __future__ import annotations

from collections.abc import Iterator
from itertools import combinations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import kernel as K
from .common import table

SHINGLE, RADIUS, SIMILARITY = 5, 63, 0.8
LANES, BLOCKS = 4, 16  # 64-bit words of a fingerprint, blocks of the index
_SALT = K.mix(np.arange(1, LANES + 1, dtype=np.uint64))


def signs(h: np.ndarray) -> np.ndarray:
    """(n, 64 * LANES) of +1 and -1."""
    lanes = K.mix(h[:, None] ^ _SALT[None, :])
    return np.unpackbits(lanes.view(np.uint8).reshape(len(h), -1), axis=1).astype(np.int8) * 2 - 1


def scale(weight: np.ndarray) -> np.ndarray:
    """Roots of the weights as whole numbers, so that sums are exact in any order."""
    return np.rint(np.sqrt(weight) * 1024).astype(np.int64)


def simhash(h: np.ndarray, weight: np.ndarray) -> np.ndarray:
    """(LANES,) signs of the sums of the shingles' bits, each by the root of its weight."""
    return np.packbits((scale(weight) @ signs(h).astype(np.int64)) > 0).view(np.uint64)


def sliding_simhash(h: np.ndarray, weight: np.ndarray, starts: np.ndarray, k: int, run: int = 1024) -> np.ndarray:
    """(len(starts), LANES): simhash of the k shingles from each start on; starts ascend.  Neighbours share their sums."""
    out = np.zeros((len(starts), LANES), np.uint64)
    cut = np.flatnonzero(np.r_[True, np.diff(starts) > k])
    for a, z in zip(cut, [*cut[1:], len(starts)]):
        while a < z:
            e = min(z, a + int(np.searchsorted(starts[a:z], starts[a] + run)))
            lo, hi = int(starts[a]), int(starts[e - 1]) + k
            total = np.zeros((hi - lo + 1, 64 * LANES), np.int64)
            np.cumsum(signs(h[lo:hi]) * scale(weight[lo:hi])[:, None], axis=0, out=total[1:])
            at = starts[a:e] - lo
            out[a:e] = np.packbits(total[at + k] - total[at] > 0, axis=1).view(np.uint64)
            a = e
    return out


class MultiIndex:
    """Fingerprints (n, LANES) by blocks of bits; near(x) has every stored one within the radius of each of x."""

    def __init__(self, prints: np.ndarray, radius: int = RADIUS, blocks: int = BLOCKS) -> None:
        self.prints, self.radius, self.wide = prints.reshape(-1, LANES), radius, 64 * LANES // blocks
        self.reach, self.each = radius // blocks, 64 // self.wide
        self.flips = np.array([sum(1 << i for i in c) for r in range(self.reach + 1) for c in combinations(range(self.wide), r)], np.uint64)
        self.tables = []
        for part in self._blocks(self.prints):
            order = np.argsort(part, kind="stable")
            values, first = np.unique(part[order], return_index=True)
            self.tables.append((values, np.r_[first, len(part)], order))

    def _blocks(self, x: np.ndarray) -> Iterator[np.ndarray]:
        for lane in range(LANES):
            for at in range(self.each):
                yield (x[:, lane] >> np.uint64(at * self.wide)) & np.uint64((1 << self.wide) - 1)

    def near(self, x: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(row of x, stored one) of all pairs within the radius, each once, in order."""
        found = []
        for part, (values, first, order) in zip(self._blocks(x), self.tables):
            if len(values) <= len(self.flips):  # few values: compare with all of them
                row, at = np.nonzero(np.bitwise_count(part[:, None] ^ values[None, :]) <= self.reach)
            else:  # many: look up all that are near
                probe = part[:, None] ^ self.flips[None, :]
                at = np.minimum(np.searchsorted(values, probe), len(values) - 1)
                row, col = np.nonzero(values[at] == probe)
                at = at[row, col]
            n = first[at + 1] - first[at]
            place = np.repeat(first[at] - np.r_[0, np.cumsum(n)[:-1]], n) + np.arange(n.sum())
            found.append(np.repeat(row, n) * len(self.prints) + order[place])
        pairs = np.unique(np.concatenate(found)) if found and len(self.prints) else np.zeros(0, np.int64)
        row, at = pairs // max(len(self.prints), 1), pairs % max(len(self.prints), 1)
        ok = np.bitwise_count(x[row] ^ self.prints[at]).sum(1) <= self.radius
        return row[ok], at[ok]


def weighted_similarity(a: np.ndarray, b: np.ndarray, weight) -> float:  # noqa: ANN001
    """Sum of least over sum of greatest weighted counts of the shingles of both."""
    keys, at = np.unique(np.concatenate([a, b]), return_inverse=True)
    na, nb = np.bincount(at[: len(a)], minlength=len(keys)), np.bincount(at[len(a) :], minlength=len(keys))
    w = weight(keys)
    top = (w * np.maximum(na, nb)).sum()
    return float((w * np.minimum(na, nb)).sum() / top) if top > 0 else 0.0


class Items:
    """Searchable items: shingles, weights, seeds, and a multi-index for each length.  Built from (item_id, text) rows.

    n_items, seen (sorted shingles, items with each): of the whole benchmark; shingles in one item may be left out.  None: these rows are all."""

    def __init__(self, rows: list[tuple[int, str]], radius: int = RADIUS, n_items: int | None = None, seen: tuple[np.ndarray, np.ndarray] | None = None, least: float = SIMILARITY) -> None:
        self.ids, self.size, self.shingles = [], [], []
        for item, text in rows:
            for _, _, data, offsets in K.text_slices(pa.array([text], pa.string())):
                w = K.words(data, offsets, lower=True, punct=True)
                if not len(w.ids):
                    continue
                _, h = K.row_grams(w, SHINGLE)
                self.ids.append(item), self.size.append(len(w.ids)), self.shingles.append(h)
        self.n = n_items or max(len(self.ids), 1)
        distinct = [np.unique(s) for s in self.shingles]
        self.keys, count = seen if seen is not None else np.unique(np.concatenate(distinct), return_counts=True) if distinct else (np.zeros(0, np.uint64), np.zeros(0, np.int64))
        self.key_weight = np.log1p(self.n / np.maximum(count, 1))
        seeds = [(x, size) for h, size in zip(self.shingles, self.size) for x in self.seeds_of(h, least).tolist()]
        seeds = sorted(set(seeds))
        self.seed, self.seed_size = np.array([x for x, _ in seeds], np.uint64), np.array([x for _, x in seeds], np.int64)
        self.short = sorted({s for s in self.size if s < SHINGLE})
        self.of_size: dict[int, tuple[np.ndarray, MultiIndex]] = {}
        sizes = np.array(self.size, np.int64)
        for size in sorted(set(self.size)):
            own = np.flatnonzero(sizes == size)
            self.of_size[size] = own, MultiIndex(np.stack([simhash(self.shingles[i], self.weight(self.shingles[i])) for i in own]), radius)

    def weight(self, h: np.ndarray) -> np.ndarray:
        if not len(self.keys):
            return np.full(len(h), np.log1p(self.n))
        at = np.minimum(np.searchsorted(self.keys, h), len(self.keys) - 1)
        return np.where(self.keys[at] == h, self.key_weight[at], np.log1p(self.n))

    def seeds_of(self, h: np.ndarray, least: float) -> np.ndarray:
        """The heaviest shingles that together hold more than 1 - least of the item's weight."""
        keys, count = np.unique(h, return_counts=True)
        w = self.weight(keys)
        order = np.lexsort((keys, -w))
        mass = np.cumsum((w * count)[order])
        return keys[order[: int(np.searchsorted(mass, (1 - least) * mass[-1] + 1e-9, "right")) + 1]]

    def windows(self, ids: np.ndarray) -> Iterator[tuple[int, int, np.ndarray]]:
        """(item size, words, starts) of the windows of one document that cover a seed of an item of that size."""
        n = len(ids)
        hit: dict[int, list[np.ndarray]] = {}
        for k in [SHINGLE, *self.short]:
            h = K.grams(ids, SHINGLE) if k == SHINGLE else K.spans(ids, np.arange(max(n - k + 1, 0)), np.arange(max(n - k + 1, 0)) + k, salt=SHINGLE)
            lo, hi = np.searchsorted(self.seed, h, "left"), np.searchsorted(self.seed, h, "right")
            many = hi - lo
            if many.any():
                p = np.repeat(np.arange(len(h)), many)
                size = self.seed_size[np.repeat(lo - np.r_[0, np.cumsum(many)[:-1]], many) + np.arange(len(p))]
                for s in np.unique(size).tolist():
                    hit.setdefault(s, []).append(p[size == s])
        for s, parts in sorted(hit.items()):
            p, words = np.concatenate(parts), min(s, n)
            last = n - words
            change = np.zeros(last + 2, np.int64)
            np.add.at(change, np.clip(p + min(s, SHINGLE) - s, 0, last + 1), 1)
            np.add.at(change, np.minimum(p, last) + 1, -1)
            yield s, words, np.flatnonzero(np.cumsum(change[:-1]) > 0)

    def hits(self, ids: np.ndarray, least: float) -> dict[int, tuple[float, int, int]]:
        """item -> (similarity, start word, words) of its best window in one document."""
        best: dict[int, tuple[float, int, int]] = {}
        for size, words, starts in self.windows(ids):
            own, index = self.of_size[size]
            k = max(words - SHINGLE + 1, 1)
            h = K.grams(ids, SHINGLE) if words >= SHINGLE else K.spans(ids, np.arange(len(ids) - words + 1), np.arange(len(ids) - words + 1) + words, salt=SHINGLE)
            weight = self.weight(h)
            for lo in range(0, len(starts), 4096):
                part = starts[lo : lo + 4096]
                for w, i in zip(*(x.tolist() for x in index.near(sliding_simhash(h, weight, part, k)))):
                    start, item = int(part[w]), int(own[i])
                    s = weighted_similarity(h[start : start + k], self.shingles[item], self.weight)
                    if s >= least and s > best.get(item, (0.0,))[0]:
                        best[item] = (s, start, words)
        return best


def _marked(items: Items, w: K.Words) -> np.ndarray:
    """Rows with any word sequence that is a seed of an item."""
    own = items.seed
    if not len(own):
        return np.zeros(0, np.int64)
    row, h = K.row_grams(w, SHINGLE)
    at = np.minimum(np.searchsorted(own, h), len(own) - 1)
    rows = [np.unique(row[own[at] == h])]
    for k in items.short:
        n = max(len(w.ids) - k + 1, 0)
        p = np.arange(n)
        h = K.spans(w.ids, p, p + k, salt=SHINGLE)
        at = np.minimum(np.searchsorted(own, h), len(own) - 1)
        hit = (own[at] == h) & (p + k <= w.first[1:][w.row[:n]])
        rows.append(np.unique(w.row[:n][hit]))
    return np.unique(np.concatenate(rows))


def shingle_counts(rows: DataFrame) -> tuple[int, tuple[np.ndarray, np.ndarray]]:
    """(items with words, (shingles, items with each)) of all rows (text), the shingles in two items or more, sorted."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for lo, hi, data, offsets in K.text_slices(b.column(0)):
                w = K.words(data, offsets, lower=True, punct=True)
                _, h = K.distinct(*K.row_grams(w, SHINGLE))
                items = int((np.diff(w.first) > 0).sum())
                yield pa.RecordBatch.from_arrays([pa.array([*K.signed(h).tolist(), None], pa.int64()), pa.array([1] * len(h) + [items], pa.int64())], names=["h", "n"])

    counts = rows.select("text").mapInArrow(run, "h long, n long").groupBy("h").agg(F.sum("n").alias("n")).where("h is null or n > 1").toArrow()
    h, n = counts["h"].combine_chunks(), counts["n"].to_numpy().astype(np.int64)
    total = n[h.is_null().to_numpy(zero_copy_only=False)].sum()
    real = h.is_valid().to_numpy(zero_copy_only=False)
    keys, n = h.drop_null().to_numpy().astype(np.int64).view(np.uint64), n[real]
    by_key = np.argsort(keys)
    return int(total), (keys[by_key], n[by_key])


def item_blocks(benchmark: DataFrame, block_words: int = 2_000_000, least: float = SIMILARITY) -> Iterator[Items]:
    """Items in blocks of bounded size, each with weights from the whole benchmark."""
    rows = benchmark.where(F.col("text").isNotNull()).select("item_id", "text")
    size = rows.agg(F.sum(F.length("text"))).first()[0] or 0
    n = max(1, -(-size // (4 * block_words)))
    items, seen = shingle_counts(rows)
    for b in range(n):
        part = rows.where(F.pmod(F.xxhash64("item_id", "text"), F.lit(n)) == b).orderBy("item_id", "text").collect()
        yield Items([(r["item_id"], r["text"]) for r in part], n_items=items, seen=seen, least=least)


def contaminated(docs: DataFrame, benchmark: DataFrame, least: float = SIMILARITY, block_words: int = 2_000_000) -> DataFrame:
    """doc_id, item_id, similarity, start_word, n_words: each item that a document holds, at its best place."""
    at = docs.select("doc_id", "text")
    out = None
    for items in item_blocks(benchmark, block_words, least):

        def run(batches: Iterator[pa.RecordBatch], items: Items = items) -> Iterator[pa.RecordBatch]:
            for b in batches:
                found = []
                for lo, _, data, offsets in K.text_slices(b.column(1)):
                    w = K.words(data, offsets, lower=True, punct=True)
                    for r in _marked(items, w):
                        doc = b.column(0)[lo + int(r)].as_py()
                        found += [(doc, items.ids[i], s, start, n) for i, (s, start, n) in sorted(items.hits(w.ids[w.first[r] : w.first[r + 1]], least).items())]
                if found:
                    yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*found), (pa.int64(), pa.int64(), pa.float64(), pa.int32(), pa.int32()))], names=["doc_id", "item_id", "similarity", "start_word", "n_words"])

        part = at.mapInArrow(run, "doc_id long, item_id long, similarity double, start_word int, n_words int")
        out = part if out is None else out.unionByName(part)
    return out


def decontaminated(docs: DataFrame, benchmark: DataFrame, least: float = SIMILARITY, block_words: int = 2_000_000) -> DataFrame:
    """The rows of docs that hold no item, as they are; texts are not shuffled."""
    at = docs.columns.index("text")
    for items in item_blocks(benchmark, block_words, least):

        def run(batches: Iterator[pa.RecordBatch], items: Items = items) -> Iterator[pa.RecordBatch]:
            for b in batches:
                keep = np.ones(b.num_rows, bool)
                for lo, _, data, offsets in K.text_slices(b.column(at)):
                    w = K.words(data, offsets, lower=True, punct=True)
                    for r in _marked(items, w):
                        keep[lo + r] = not items.hits(w.ids[w.first[r] : w.first[r + 1]], least)
                yield b.filter(pa.array(keep))

        docs = docs.mapInArrow(run, docs.schema)
    return docs


def op5_simhash_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every (document, benchmark item) pair where the document holds the item."""
    return contaminated(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))
