import random

import numpy as np
from conftest import prose
from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F

from corrsentry.llm import common, quality, toxicity

BAD = ["vile", "rotten", "wretched"]


def labelled(spark, n=900):
    rng = random.Random(2)
    data, labels = [], []
    for i in range(n):
        text, toxic, good = prose(rng, rng.randrange(20, 120)), i % 4 == 0, i % 3 != 0
        w = text.split()
        if toxic:
            for _ in range(rng.randrange(2, 5)):
                w.insert(rng.randrange(len(w)), rng.choice(BAD))
        text = " ".join(w) if good else " ".join(x.upper() + "!!" for x in w)
        data.append((i, text)), labels.append((i, int(good), int(toxic)))
    data += [(n, ""), (n + 1, None), (n + 2, prose(rng, 30_000)), (0, data[0][1])]
    labels += [(1, None, None), (None, 1, 1), (10**9, 1, 1)]
    return spark.createDataFrame(data, "doc_id long, text string").repartition(4), spark.createDataFrame(labels, "doc_id long, quality int, toxic int")


def held_out_accuracy(found, labels, column):
    x = found.join(labels, "doc_id").where(f"held_out and {column} is not null").select("predicted", column).toPandas()
    return (x["predicted"] == x[column]).mean(), len(x)


def test_quality_on_held_out_rows_and_odd_texts(spark, none):
    docs, labels = labelled(spark)
    model = quality.fit(docs, labels)
    found = quality.score(docs.withColumn("score", common.held_out(F.col("doc_id"))), model)
    found = found.selectExpr("doc_id", "score", "cast(score >= 0.3 as int) predicted").withColumn("held_out", common.held_out(F.col("doc_id")))
    accuracy, n = held_out_accuracy(found, labels, "quality")
    assert n > 100 and accuracy > 0.97
    scores = [r.score for r in found.collect()]
    assert len(scores) == docs.count() and all(0 <= s <= 1 for s in scores)
    kept = quality.keep_good(docs, labels)
    assert kept.columns == docs.columns and sorted(map(str, kept.collect())) == sorted(str(r) for r in docs.join(found.where("predicted = 1").select("doc_id").distinct(), "doc_id").collect())
    assert quality.score(none, model).count() == 0
    flat = quality.fit(docs, labels.where("quality = 1"))
    assert len({round(r.score, 9) for r in quality.score(docs, flat).collect()}) == 1


def test_trees_in_flat_arrays_agree_with_a_walk_node_by_node():
    rng = np.random.default_rng(0)
    x = rng.normal(size=(400, len(quality.STATISTICS)))
    y = ((x[:, 0] > 0.3) ^ (x[:, 3] < 0)).astype(float)
    t = quality.grow(x, y)

    def walk(v):
        total = t.base
        for f, c, leaf in zip(t.feature, t.cut, t.leaf):
            k = 0
            while k < len(f):
                k = 2 * k + 1 + int(v[f[k]] > c[k])
            total += leaf[k - len(f)]
        return total

    assert np.allclose(t.margin(x), [walk(v) for v in x])
    assert ((t.probability(x) > 0.5) == y).mean() > 0.9


def brute_segments(score):
    """By definition: take the best segment (shortest, leftmost of equals), then the same on both sides."""
    best = (0.0, 0, 0)
    for i in range(len(score)):
        for j in range(i + 1, len(score) + 1):
            s = sum(score[i:j])
            if s > best[0] or (s == best[0] and s > 0 and j - i < best[2] - best[1]):
                best = (s, i, j)
    s, i, j = best
    if s <= 0:
        return []
    return [*brute_segments(score[:i]), (i, j, s), *[(a + j, b + j, v) for a, b, v in brute_segments(score[j:])]]


@settings(max_examples=200, deadline=None)
@given(st.lists(st.integers(-5, 5).map(float), max_size=24))
def test_segments_are_the_maximal_ones(score):
    got, want = toxicity.maximal_segments(np.array(score)), brute_segments(score)
    assert sorted(s for _, _, s in got) == sorted(s for _, _, s in want)


def test_toxicity_on_held_out_rows_passages_and_odd_texts(spark, none):
    docs, labels = labelled(spark)
    model = toxicity.fit(docs, labels)
    found = toxicity.toxic_passages(docs, model)
    judged = found.selectExpr("doc_id", "score", "passages", "cast(score >= 0.5 as int) predicted").withColumn("held_out", common.held_out(F.col("doc_id")))
    accuracy, n = held_out_accuracy(judged, labels, "toxic")
    assert n > 100 and accuracy > 0.97
    spans = [p.text for r in judged.where("passages is not null and size(passages) > 0").collect() for p in r.passages]
    assert spans and sum(any(b in s.lower() for b in BAD) for s in spans) > 0.9 * len(spans)
    empty = {r.doc_id: r.score for r in judged.where("doc_id in (900, 901)").collect()}
    assert set(empty) == {900, 901} and max(empty.values()) < 0.5
    assert toxicity.toxic_passages(none, model).count() == 0
    mute = toxicity.fit(docs, labels.where("toxic = 0"))
    assert len({round(r.score, 9) for r in toxicity.toxic_passages(docs, mute).collect()}) == 1


def test_no_held_out_label_is_learned_from(spark):
    _, labels = labelled(spark)
    import zlib

    ids = common.labelled_sample(labels, "toxic", 10**6)
    assert ids and all(zlib.crc32(str(i).encode()) % 5 for i in ids)
    assert len(common.labelled_sample(labels, "toxic", 50)) == 50
