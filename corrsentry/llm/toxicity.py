"""Toxic passages by maximum-scoring segments of token log-odds.

Tokens are lower-cased words without ASCII punctuation.  Each token's log-odds of toxic against clean text has a
Dirichlet prior: the share of its first six bytes in each class, times the token's share among the words with those
bytes in the whole corpus.  So an unseen token has the log-odds of its beginning.  A negative drift makes the expected
score of clean text negative; a linear-time scan then finds all maximal-scoring segments of a text.  For clean text
the largest segment score follows an extreme-value law with parameters lambda (from the token scores' distribution) and
K (from the clean labelled texts), which gives each segment an expected number of equal or better ones by chance.  The
text's score is a logistic function of its best segment's and all significant segments' evidence.

Learning uses at most `limit` labelled rows, chosen by hash, held-out rows left out; corpus shares use all texts.

Edge cases: null and empty texts have no segments and the score of a text without evidence; repeated rows are scored
alike; without toxic labels no token scores and every score is the (smoothed) share of toxic labels; an empty table
gives an empty result.
"""

from __future__ import annotations

from collections.abc import Iterator
from typing import NamedTuple

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import kernel as K
from .common import held_out, labelled_sample, only_ids, table, written

LIMIT = 20_000
HEAD = 6
EULER = 0.5772156649015329


def maximal_segments(score: np.ndarray) -> list[tuple[int, int, float]]:
    """All maximal-scoring segments (start, end, sum) of a score sequence, left to right: disjoint, each with a positive
    sum, no part of one scores more and none can be widened to score more.  Linear in the positive scores."""
    total = np.concatenate([[0.0], np.cumsum(score)])
    up = np.flatnonzero(np.asarray(score) > 0)
    return _segments(up, total)


def _segments(up: np.ndarray, total: np.ndarray) -> list[tuple[int, int, float]]:
    found: list[tuple[int, int, float, float, int]] = []  # start, end, total before, total after, nearest earlier one with a lower total before
    for i, before, after in zip(up.tolist(), total[up].tolist(), total[up + 1].tolist()):
        start, end = i, i + 1
        j = len(found) - 1
        while True:
            while j >= 0 and found[j][2] >= before:
                j = found[j][4]
            if j < 0 or found[j][3] >= after:
                found.append((start, end, before, after, j))
                break
            start, before, nxt = found[j][0], found[j][2], found[j][4]
            del found[j:]
            j = nxt
    return [(s, e, b - a) for s, e, a, b, _ in found]


class Model(NamedTuple):
    token: np.ndarray  # sorted ids
    token_score: np.ndarray
    head: np.ndarray
    head_score: np.ndarray
    unseen: float
    rate: float  # lambda
    log_k: float
    weight: np.ndarray  # of 1 and of evidence()


def look(ids: np.ndarray, keys: np.ndarray, values: np.ndarray, other: np.ndarray | float) -> np.ndarray:
    if not len(keys):
        return np.broadcast_to(other, ids.shape).astype(float)
    at = np.minimum(np.searchsorted(keys, ids), len(keys) - 1)
    return np.where(keys[at] == ids, values[at], other)


def token_scores(w: K.Words, m: Model) -> np.ndarray:
    return look(w.ids, m.token, m.token_score, look(w.head, m.head, m.head_score, m.unseen))


def row_segments(w: K.Words, score: np.ndarray) -> Iterator[list[tuple[int, int, float]]]:
    """Maximal segments of each row, in word positions of the row."""
    up = np.flatnonzero(score > 0)
    at = np.searchsorted(up, w.first)
    for r in range(len(w.first) - 1):
        lo, hi = w.first[r], w.first[r + 1]
        if at[r] == at[r + 1]:
            yield []
        else:
            yield _segments(up[at[r] : at[r + 1]] - lo, np.concatenate([[0.0], np.cumsum(score[lo:hi])]))


def significance(n: int, s: float, m: Model) -> float:
    """-log of the number of segments of at least this score to expect in n clean tokens."""
    return m.rate * s - np.log(max(n, 1)) - m.log_k


def evidence(n: int, segments: list[tuple[int, int, float]], m: Model) -> tuple[float, float, float]:
    """(of the best segment, of all significant ones together, their number), tamed."""
    if not segments:
        return 0.0, 0.0, 0.0
    at = np.array([significance(n, s, m) for _, _, s in segments])
    sure = at[at > 0]
    return float(np.clip(at.max() + 5, 0, 60)) / 10, float(np.log1p(sure.sum())), float(np.log1p(len(sure)))


def _words(data: np.ndarray, offsets: np.ndarray) -> K.Words:
    return K.words(data, offsets, lower=True, punct=True, prefix=HEAD)


def logistic(x: np.ndarray, y: np.ndarray, l2: float = 0.1, rounds: int = 30) -> np.ndarray:
    """Weights of x (first column 1) by Newton's method."""
    w = np.zeros(x.shape[1])
    penalty = np.full(x.shape[1], l2)
    penalty[0] = 1e-6
    for _ in range(rounds):
        p = 1 / (1 + np.exp(-np.clip(x @ w, -30, 30)))
        step = np.linalg.solve((x * (p * (1 - p) + 1e-9)[:, None]).T @ x + np.diag(penalty), x.T @ (y - p) - penalty * w)
        w += np.clip(step, -5, 5)
        if np.abs(step).max() < 1e-9:
            break
    return w


def _label_counts(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """(kind, id, y0, y1): texts of each class with the token (kind 0) or word beginning (kind 1); kind 2, id 0: all texts."""
    for b in batches:
        y = b.column(b.schema.get_field_index("y")).to_numpy(zero_copy_only=False)
        for lo, hi, data, offsets in K.text_slices(b.column(b.schema.get_field_index("text"))):
            w, own = _words(data, offsets), y[lo:hi]
            for kind, ids in ((0, w.ids), (1, w.head)):
                row, h = K.distinct(w.row, ids)
                keys, at = np.unique(h, return_inverse=True)
                ones = np.bincount(at, own[row], len(keys)).astype(np.int64)
                n = np.bincount(at, minlength=len(keys))
                yield _counts(kind, keys, n - ones, ones)
            yield _counts(2, np.zeros(1, np.uint64), np.array([(own == 0).sum()]), np.array([(own == 1).sum()]))


def _counts(kind: int, keys: np.ndarray, y0: np.ndarray, y1: np.ndarray) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array(np.full(len(keys), kind, np.int32)), pa.array(K.signed(keys)), pa.array(y0.astype(np.int64)), pa.array(y1.astype(np.int64))], names=["kind", "id", "y0", "y1"])


def corpus_counts(docs: DataFrame, tokens: np.ndarray, heads: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """How often each of the given tokens and beginnings stands in all texts; a task returns each with its own count."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = [np.zeros(len(tokens), np.int64), np.zeros(len(heads), np.int64)]
        for b in batches:
            for _, _, data, offsets in K.text_slices(b.column(0)):
                w = _words(data, offsets)
                for t, keys, ids in zip(total, (tokens, heads), (w.ids, w.head)):
                    if len(keys) and len(ids):
                        at = np.minimum(np.searchsorted(keys, ids), len(keys) - 1)
                        t += np.bincount(at[keys[at] == ids], minlength=len(keys))
        for kind, t in enumerate(total):
            full = np.flatnonzero(t)
            yield pa.RecordBatch.from_arrays([pa.array(np.full(len(full), kind, np.int32)), pa.array(full.astype(np.int32)), pa.array(t[full])], names=["kind", "at", "n"])

    out = [np.zeros(len(tokens)), np.zeros(len(heads))]
    summed = docs.select("text").mapInArrow(run, "kind int, at int, n long").groupBy("kind", "at").agg(F.sum("n").alias("n")).toPandas()
    for kind in (0, 1):
        part = summed[summed["kind"] == kind]
        out[kind][part["at"].to_numpy()] = part["n"].to_numpy()
    return out[0], out[1]


def fit(docs: DataFrame, labels: DataFrame, limit: int = LIMIT, kappa: float = 4.0, drift: float = 0.8, least: int = 3) -> Model:
    """Model from a bounded labelled sample and the counts of its tokens in the whole corpus.

    Only tokens in at least `least` sampled texts get scores of their own, so their number is bounded by the sample."""
    # read again and again below: a bounded table of its own, so that the corpus is read just for the counts
    sample = written(only_ids(docs, labelled_sample(labels, "toxic", limit)).select("text", "y"), "sample")
    counts = sample.mapInArrow(_label_counts, "kind int, id long, y0 long, y1 long").groupBy("kind", "id").agg(F.sum("y0").alias("y0"), F.sum("y1").alias("y1"))
    got = counts.where(F.col("y0") + F.col("y1") >= F.when(F.col("kind") == 2, 0).otherwise(least)).toPandas().sort_values(["kind", "id"])
    whole = got[got["kind"] == 2]
    n0, n1 = (float(whole[c].sum()) for c in ("y0", "y1"))
    none = np.zeros(0, np.uint64)
    prior = np.log((n1 + 1) / (n0 + 1))
    if not n1 or not n0:
        return Model(none, none.astype(float), none, none.astype(float), -drift, 1.0, 0.0, np.array([prior, 0.0, 0.0, 0.0]))

    def part(kind: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        p = got[got["kind"] == kind]
        ids = p["id"].to_numpy(np.int64).view(np.uint64)
        order = np.argsort(ids)
        return ids[order], p["y0"].to_numpy(float)[order], p["y1"].to_numpy(float)[order]

    (token, t0, t1), (head, h0, h1) = part(0), part(1)
    c_token, c_head = corpus_counts(docs, token, head)
    # shares of texts with the beginning, drawn to the share over both classes
    both = (h0 + h1 + 1) / (n0 + n1 + 2)
    p0, p1 = (h0 + kappa * both) / (n0 + kappa), (h1 + kappa * both) / (n1 + kappa)
    head_odds = np.log(p1 / (1 - p1 + 1e-9)) - np.log(p0 / (1 - p0 + 1e-9))
    return _calibrated(sample, token, t0, t1, head, p0, p1, head_odds, c_token, c_head, n0, n1, kappa, drift)


def _token_heads(sample: DataFrame, token: np.ndarray) -> np.ndarray:
    """Beginning of each token; a token has one."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for _, _, data, offsets in K.text_slices(b.column(0)):
                w = _words(data, offsets)
                keys, first = np.unique(w.ids, return_index=True)
                ok = np.isin(keys, token)
                yield pa.RecordBatch.from_arrays([pa.array(K.signed(keys[ok])), pa.array(K.signed(w.head[first[ok]]))], names=["id", "head"])

    got = sample.select("text").mapInArrow(run, "id long, head long").groupBy("id").agg(F.min("head").alias("head")).toPandas()
    ids = got["id"].to_numpy(np.int64).view(np.uint64)
    order = np.argsort(ids)
    return got["head"].to_numpy(np.int64).view(np.uint64)[order]


def _calibrated(sample: DataFrame, token, t0, t1, head, p0, p1, head_odds, c_token, c_head, n0, n1, kappa, drift) -> Model:  # noqa: ANN001
    owner = _token_heads(sample, token)
    share = np.clip(c_token / np.maximum(look(owner, head, c_head, 1.0), 1.0), 1e-6, 1.0)
    a0, a1 = kappa * share * look(owner, head, p0, 1e-4), kappa * share * look(owner, head, p1, 1e-4)
    q0, q1 = (t0 + a0 + 1e-3) / (n0 + kappa), (t1 + a1 + 1e-3 * n1 / n0) / (n1 + kappa)
    odds = np.log(q1) - np.log1p(-np.minimum(q1, 0.999)) - np.log(q0) + np.log1p(-np.minimum(q0, 0.999))
    clip = lambda x: np.clip(x, -2.0, 5.0) - drift
    draft = Model(token, clip(odds), head, clip(head_odds), -drift, 1.0, 0.0, np.zeros(4))
    rate = _rate(sample, draft)
    draft = draft._replace(rate=rate)
    best = _texts(sample, draft)
    clean = best[(best["y"] == 0) & (best["n"] > 0)]
    log_k = float((rate * clean["s"] - np.log(clean["n"])).mean() - EULER) if len(clean) else 0.0
    draft = draft._replace(log_k=log_k)
    rows = _texts(sample, draft).sort_values(["n", "y", "s", "e0", "e1", "e2"])
    x = np.column_stack([np.ones(len(rows)), rows[["e0", "e1", "e2"]].to_numpy()])
    return draft._replace(weight=logistic(x, rows["y"].to_numpy(float)))


def _rate(sample: DataFrame, m: Model) -> float:
    """The positive root of mean(exp(lambda * score)) = 1 over the tokens of clean texts, from a histogram of scores."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            y = b.column(b.schema.get_field_index("y")).to_numpy(zero_copy_only=False)
            for lo, hi, data, offsets in K.text_slices(b.column(b.schema.get_field_index("text"))):
                w = _words(data, offsets)
                s = token_scores(w, m)[y[lo:hi][w.row] == 0]
                v, n = np.unique(np.round(s, 2), return_counts=True)
                yield pa.RecordBatch.from_arrays([pa.array(np.rint(v * 100).astype(np.int32)), pa.array(n.astype(np.int64))], names=["v", "n"])

    got = sample.mapInArrow(run, "v int, n long").groupBy("v").agg(F.sum("n").alias("n")).toPandas()
    v, n = got["v"].to_numpy(float) / 100, got["n"].to_numpy(float)
    if not len(v) or v.max() <= 0 or (v * n).sum() >= 0:
        return 1.0
    lo, hi = 1e-3, 20.0
    for _ in range(60):
        mid = (lo + hi) / 2
        lo, hi = (mid, hi) if (n * np.exp(np.minimum(mid * v, 700))).sum() < n.sum() else (lo, mid)
    return (lo + hi) / 2


def _texts(sample: DataFrame, m: Model):  # noqa: ANN202
    """y, n, s (best segment) and evidence of each sampled text, on the driver."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            y = b.column(b.schema.get_field_index("y")).to_numpy(zero_copy_only=False)
            for lo, hi, data, offsets in K.text_slices(b.column(b.schema.get_field_index("text"))):
                w = _words(data, offsets)
                n = np.diff(w.first)
                segs = list(row_segments(w, token_scores(w, m)))
                e = np.array([evidence(k, s, m) for k, s in zip(n, segs)]).reshape(-1, 3)
                top = np.array([max((x[2] for x in s), default=0.0) for s in segs])
                yield pa.RecordBatch.from_arrays([pa.array(y[lo:hi].astype(np.int32)), pa.array(n.astype(np.int64)), *[pa.array(np.ascontiguousarray(c, dtype=float)) for c in (top, *e.T)]], names=["y", "n", "s", "e0", "e1", "e2"])

    return sample.mapInArrow(run, "y int, n long, s double, e0 double, e1 double, e2 double").toPandas()


def toxic_passages(docs: DataFrame, m: Model, level: float = 0.05) -> DataFrame:
    """All columns of docs but text, `score` double and `passages` array of (start word, end word, evidence, text): every
    segment of which fewer than `level` are to be expected by chance."""
    at = docs.columns.index("text")
    rest = [c for c in docs.columns if c not in ("text", "score", "passages")]
    kind = pa.list_(pa.struct([("start", pa.int32()), ("end", pa.int32()), ("evidence", pa.float64()), ("text", pa.string())]))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for lo, hi, data, offsets in K.text_slices(b.column(at)):
                w = _words(data, offsets)
                n = np.diff(w.first)
                score, found = np.zeros(hi - lo), []
                for r, segs in enumerate(row_segments(w, token_scores(w, m))):
                    score[r] = np.array([1.0, *evidence(n[r], segs, m)]) @ m.weight
                    own = []
                    for s, e, v in segs:
                        if (sure := significance(n[r], v, m)) >= -np.log(level):
                            a, z = w.start[w.first[r] + s], w.end[w.first[r] + e - 1]
                            own.append({"start": s, "end": e, "evidence": float(sure), "text": data[a:z].tobytes().decode("utf-8", "replace")})
                    found.append(own)
                part = b.slice(lo, hi - lo)
                yield pa.RecordBatch.from_arrays([*[part.column(part.schema.get_field_index(c)) for c in rest], pa.array(1 / (1 + np.exp(-np.clip(score, -30, 30)))), pa.array(found, kind)], names=[*rest, "score", "passages"])

    schema = docs.select(*rest).schema.add("score", "double")
    fields = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in schema)
    return docs.mapInArrow(run, f"{fields}, passages array<struct<start:int,end:int,evidence:double,text:string>>")


def op2_toxic_segments(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    found = toxic_passages(docs, fit(docs, table(spark, sf_dir, "labels")))
    return found.select("doc_id", held_out(F.col("doc_id")).alias("held_out"), "score", (F.col("score") >= 0.5).cast("int").alias("predicted"), F.size("passages").alias("n_passages"))
