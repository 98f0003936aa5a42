"""Quality classifier: histogram gradient-boosted trees over document statistics.

Statistics come from one vectorised pass over each batch of texts.  Trees are grown on the driver from the statistics
of a bounded sample of labelled rows (`limit`, chosen by hash, held-out rows left out), as complete binary trees in flat
arrays, and applied to batches by array look-ups.

Edge cases: null and empty texts have all-zero statistics and are scored like any other; repeated rows are scored alike;
without labels of both kinds every score is the (smoothed) share of good labels; an empty table gives an empty result.
"""

from __future__ import annotations

from collections.abc import Iterator
from typing import NamedTuple

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from . import kernel as K
from .common import held_out, labelled_sample, only_ids, table

LIMIT = 20_000
THRESHOLD = 0.3


def _set(chars: bytes) -> np.ndarray:
    out = np.zeros(256, bool)
    out[list(chars)] = True
    return out


_CLASSES = [
    np.array([65 <= b <= 90 for b in range(256)]),
    np.array([97 <= b <= 122 for b in range(256)]),
    _set(b"0123456789"),
    K.SPACE,
    _set(b"\n"),
    _set(b"*$%&#|@<>{}[]=+~^\\_/"),
    _set(b".,;:?"),
    _set(b"!"),
    np.arange(256) >= 128,
    _set(b"|"),
]
_NEWLINE = _set(b"\n\r")
STATISTICS = ["log_bytes", "upper", "lower", "digit", "space", "newline", "symbol", "stop", "shout", "high", "pipe", "log_words", "word_bytes", "long_words", "distinct_words", "log_lines", "line_words", "repeated_lines", "upper_share"]


def statistics(data: np.ndarray, offsets: np.ndarray) -> np.ndarray:
    """One row of STATISTICS for each text; lines count as words separated by line ends."""
    n = np.diff(offsets).astype(np.float64)
    per = np.maximum(n, 1)
    counts = []
    for c in _CLASSES:
        total = np.zeros(len(data) + 1, np.int64)
        np.cumsum(c[data], out=total[1:])
        counts.append((total[offsets[1:]] - total[offsets[:-1]]).astype(np.float64))
    w = K.words(data, offsets)
    rows = len(n)
    m = np.diff(w.first).astype(np.float64)
    size = (w.end - w.start).astype(np.float64)
    total_size = np.bincount(w.row, size, rows)
    long_ = np.bincount(w.row, size > 14, rows)
    row, _ = K.distinct(w.row, w.ids)
    lines = K.words(data, offsets, sep=_NEWLINE)
    k = np.diff(lines.first).astype(np.float64)
    lrow, _ = K.distinct(lines.row, lines.ids)
    letters = np.maximum(counts[0] + counts[1], 1)
    mw, kl = np.maximum(m, 1), np.maximum(k, 1)
    cols = [np.log1p(n), *[c / per for c in counts], np.log1p(m), total_size / mw, long_ / mw, np.bincount(row, minlength=rows) / mw, np.log1p(k), m / kl, 1 - np.bincount(lrow, minlength=rows) / kl, counts[0] / letters]
    out = np.stack(cols, 1)
    out[n == 0] = 0
    return out


class Trees(NamedTuple):
    """Complete binary trees in heap order: feature and cut of inner nodes, value of leaves."""

    base: float
    feature: np.ndarray  # (trees, 2**depth - 1)
    cut: np.ndarray
    leaf: np.ndarray  # (trees, 2**depth)

    def margin(self, x: np.ndarray) -> np.ndarray:
        t, inner = self.feature.shape
        out = np.full(len(x), self.base)
        for lo in range(0, len(x), 4096):
            part = x[lo : lo + 4096]
            node = np.zeros((len(part), t), np.int64)
            rows, trees = np.arange(len(part))[:, None], np.arange(t)[None, :]
            for _ in range((inner + 1).bit_length() - 1):
                node = 2 * node + 1 + (part[rows, self.feature[trees, node]] > self.cut[trees, node])
            out[lo : lo + 4096] += self.leaf[trees, node - inner].sum(1)
        return out

    def probability(self, x: np.ndarray) -> np.ndarray:
        return 1 / (1 + np.exp(-self.margin(x)))


def grow(x: np.ndarray, y: np.ndarray, trees: int = 60, depth: int = 3, rate: float = 0.15, bins: int = 64, l2: float = 5.0, least: float = 3.0) -> Trees:
    """Boosting on the logistic loss; splits are chosen from histograms of quantile bins."""
    n, f = x.shape if len(x) else (0, len(STATISTICS))
    p = (y.sum() + 1.0) / (n + 2.0)
    inner = 2**depth - 1
    base = float(np.log(p / (1 - p)))
    feature, cut, leaf = np.zeros((trees, inner), np.int64), np.full((trees, inner), np.inf), np.zeros((trees, inner + 1))
    if n == 0 or y.min() == y.max():
        return Trees(base, feature, cut, leaf)
    edges = [np.unique(np.quantile(x[:, j], np.linspace(0, 1, bins + 1)[1:-1])) for j in range(f)]
    code = np.stack([np.searchsorted(e, x[:, j], "left") for j, e in enumerate(edges)], 1)  # code > b iff x > edges[b]
    margin = np.full(n, base)
    for t in range(trees):
        q = 1 / (1 + np.exp(-margin))
        grad, hess = y - q, q * (1 - q)
        node = np.zeros(n, np.int64)
        for d in range(depth):
            first, width = 2**d - 1, 2**d
            at = node - first
            best = np.full(width, 1e-6)
            g_all, h_all = np.bincount(at, grad, width), np.bincount(at, hess, width)
            for j, e in enumerate(edges):
                if not len(e):
                    continue
                b = len(e) + 1
                g = np.bincount(at * b + code[:, j], grad, width * b).reshape(width, b).cumsum(1)[:, :-1]
                h = np.bincount(at * b + code[:, j], hess, width * b).reshape(width, b).cumsum(1)[:, :-1]
                gr, hr = g_all[:, None] - g, h_all[:, None] - h
                gain = np.where((h >= least) & (hr >= least), g**2 / (h + l2) + gr**2 / (hr + l2) - (g_all**2 / (h_all + l2))[:, None], -1)
                top = gain.argmax(1)
                win = gain[np.arange(width), top] > best
                best[win] = gain[np.arange(width), top][win]
                feature[t, first:][:width][win] = j
                cut[t, first:][:width][win] = e[top[win]]
            node = 2 * node + 1 + (x[np.arange(n), feature[t, node]] > cut[t, node])
        at = node - inner
        leaf[t] = rate * np.bincount(at, grad, inner + 1) / (np.bincount(at, hess, inner + 1) + l2)
        margin += leaf[t][at]
    return Trees(base, feature, cut, leaf)


def _stat_rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for b in batches:
        for lo, hi, data, offsets in K.text_slices(b.column(b.schema.get_field_index("text"))):
            x = statistics(data, offsets)
            yield pa.RecordBatch.from_arrays([b.column(b.schema.get_field_index("y")).slice(lo, hi - lo).cast(pa.int32()), pa.array(list(x), pa.list_(pa.float64()))], names=["y", "x"])


def fit(docs: DataFrame, labels: DataFrame, limit: int = LIMIT) -> Trees:
    """Trees from at most `limit` labelled rows; their statistics (limit * 19 numbers) are gathered on the driver."""
    rows = only_ids(docs, labelled_sample(labels, "quality", limit)).select("text", "y").mapInArrow(_stat_rows, "y int, x array<double>").toPandas()
    x = np.array(rows["x"].tolist(), float).reshape(len(rows), -1)
    order = np.lexsort([*x.T, rows["y"]]) if len(rows) else []
    return grow(x[order] if len(rows) else x, rows["y"].to_numpy(float)[order])


def score(docs: DataFrame, model: Trees) -> DataFrame:
    """All columns of docs and `score` double (which replaces a column of that name)."""
    docs = docs.drop("score")
    at = docs.columns.index("text")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for lo, hi, data, offsets in K.text_slices(b.column(at)):
                s = pa.array(model.probability(statistics(data, offsets)))
                yield pa.RecordBatch.from_arrays([*b.slice(lo, hi - lo).columns, s], names=[*b.schema.names, "score"])

    return docs.mapInArrow(run, T.StructType([*docs.schema.fields, T.StructField("score", T.DoubleType())]))


def keep_good(docs: DataFrame, labels: DataFrame, threshold: float = THRESHOLD) -> DataFrame:
    """The rows of docs that score at or over the threshold, as they are; texts are not shuffled."""
    at, model = docs.columns.index("text"), fit(docs, labels)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for lo, hi, data, offsets in K.text_slices(b.column(at)):
                yield b.slice(lo, hi - lo).filter(pa.array(model.probability(statistics(data, offsets)) >= threshold))

    return docs.mapInArrow(run, docs.schema)


def op4_quality_trees(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    model = fit(docs, table(spark, sf_dir, "labels"))
    at = score(docs, model)
    return at.select("doc_id", held_out(F.col("doc_id")).alias("held_out"), "score", (F.col("score") >= THRESHOLD).cast("int").alias("predicted"))
