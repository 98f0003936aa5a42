import random
import zlib
from collections import Counter

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from corrsentry.llm import common, mixing, shards


def test_shards_hold_all_rows_near_equal_and_groups_together(spark, docs):
    plain = docs.where("doc_id < 120")  # without the two long texts, each over a shard
    rows = common.written(shards.sized(plain), "t")
    out = shards.kd_shards(rows.withColumnRenamed("lang", "slot").withColumn("lang", rows["source"]), ["chars", "lang", "source", "doc_id"], n_shards=4).toPandas()
    data = plain.collect()
    assert sorted(out["doc_id"]) == sorted(r.doc_id for r in data)
    size = {r.doc_id: len((r.text or "").encode()) + 16 for r in data}
    crc = {r.doc_id: zlib.crc32((r.text or "").encode()) for r in data}
    assert all(size[d] == s and crc[d] == c for d, s, c in zip(out["doc_id"], out["size"], out["text_crc32"]))
    for _, part in out.groupby("shard"):
        assert sorted(part["slot"]) == list(range(len(part)))
    full = out.groupby("shard")["size"].sum()
    assert len(full) == 4 and full.max() - full.min() < 0.1 * full.mean()
    assert (out.groupby("gkey")["shard"].nunique() == 1).all()


def test_a_group_over_a_shard_is_cut_and_others_stay_whole(spark):
    text = "x" * 100
    df = spark.createDataFrame([(i, text if i < 300 else f"{i}" * 20, None, None, 1) for i in range(900)], "doc_id long, text string, lang string, source string, n_chars long")
    out = shards.kd_shards(common.written(shards.sized(df), "t"), ["chars", "lang", "source", "doc_id"], n_shards=8).toPandas()
    full = out.groupby("shard")["size"].sum()
    assert len(full) == 8 and full.max() < 1.05 * full.mean() and len(out) == 900


def test_target_bytes_and_no_rows(spark, docs, none):
    rows = common.written(shards.sized(docs.where("doc_id < 120")), "t")
    total = sum(r["size"] for r in rows.collect())
    n = shards.kd_shards(rows, ["chars", "doc_id"], target_bytes=total // 5 + 1).select("shard").distinct().count()
    assert n == 5
    assert shards.kd_shards(common.written(shards.sized(none), "t"), ["chars", "lang"], n_shards=3).count() == 0


def test_tree_splits_the_widest_dimension_at_the_weighted_median(spark):
    rng = random.Random(0)
    rows = [(i, rng.random(), rng.random() * 0.2, rng.randrange(1, 50)) for i in range(4000)]
    pts = spark.createDataFrame(rows, "gkey long, c0 double, c1 double, bytes long")
    splits, leaves = shards.tree(pts, 2, [0.25] * 4)
    assert [splits[k][0] for k in (0, 1, 2)] == [0, 0, 0]
    x, w = np.array([r[1:3] for r in rows]), np.array([r[3] for r in rows])
    order = np.argsort(x[:, 0])
    median = x[order[np.searchsorted(np.cumsum(w[order]), w.sum() / 2)], 0]
    assert abs(splits[0][1] - median) < 1e-3
    part = np.bincount([leaves[k] for k in shards.locate(x, splits)], w)
    assert part.max() - part.min() < 0.01 * w.sum()


@settings(max_examples=60, deadline=None)
@given(st.dictionaries(st.sampled_from("abcdefg"), st.floats(0.01, 10), min_size=1), st.integers(10, 80))
def test_every_source_lags_by_less_than_a_block(weights, q):
    k = mixing.quanta(weights, q)
    order = mixing.edf(k)
    size = sum(k.values())
    assert len(order) == size and Counter(order) == k
    done = Counter()
    for t, s in enumerate(order):
        done[s] += 1
        assert all(abs(done[x] - k[x] * (t + 1) / size) < 1 for x in k)


def test_schedule_runs_each_block_once_and_ends_sources_in_turn():
    blocks = {"a": 50, "b": 7, "c": 1, "d": 0}
    phases, turns = mixing.schedule(blocks, {"a": 1, "b": 1, "c": 5, "d": 1}, 40)
    at = {(p, s, j): t for p, s, j, t in turns}
    slots = [slot0 + (i - a) // k * size + at[p, s, (i - a) % k] for p, s, a, b, slot0, k, size in phases for i in range(a, b)]
    assert sorted(slots) == list(range(58))
    assert {s: max(b for _, x, _, b, *_ in phases if x == s) for s in "abc"} == {"a": 50, "b": 7, "c": 1}


def test_mix_against_a_slot_by_slot_simulation(spark, docs, none):
    rows = common.written(docs.select("doc_id", "source", "text").withColumnRenamed("text", "slot"), "t")
    out = mixing.mixed(rows, block=4, q=50).toPandas()
    n = Counter(r.source for r in rows.collect())
    assert sorted(out["pos"]) == list(range(sum(n.values())))
    assert (out["slot"] // 1 >= 0).all() and "slot" in out
    left = {s if s is not None else "\x00": -(-c // 4) for s, c in n.items()}
    weights = {s if s is not None else "\x00": c**0.5 for s, c in n.items()}
    want, line = [], []
    while left:  # one phase after another, slot by slot
        k = mixing.quanta({s: weights[s] for s in left}, 50)
        line = mixing.edf(k)
        t = 0
        while all(left.values()):
            want.append(line[t % len(line)])
            left[want[-1]] -= 1
            t += 1
        left = {s: c for s, c in left.items() if c}
    got = [s or "\x00" for s in out.assign(source=out["source"].fillna("")).sort_values("pos").drop_duplicates("slot")["source"]]
    assert got == want
    inside = out["slot"] - out.groupby("phase")["slot"].transform("min")
    assert (inside >= out["release"]).all() and (inside < out["deadline"]).all()
    assert mixing.mixed(common.written(none.select("doc_id", "source"), "t")).count() == 0
    mixed = mixing.mix_documents(docs.dropDuplicates(["doc_id"]))
    assert mixed.columns == docs.columns and mixed.count() == docs.select("doc_id").distinct().count()


def test_given_weights_and_too_many_sources(spark, monkeypatch):
    rows = common.written(spark.createDataFrame([(i, "ab"[i % 2]) for i in range(400)], "doc_id long, source string"), "t")
    head = mixing.mixed(rows, {"a": 3.0, "b": 1.0, "zz": 1.0}, block=1, q=100).where("pos < 100").groupBy("source").count().collect()
    assert {r["source"]: r["count"] for r in head} == {"a": 75, "b": 25}
    monkeypatch.setattr(mixing, "MAX_SOURCES", 1)
    with pytest.raises(ValueError):
        mixing.mixed(rows)


def test_ranks_are_gapless_over_many_buckets(spark):
    df = common.written(spark.createDataFrame([(i, None if i % 3 else "k") for i in range(500)], "doc_id long, k string"), "t")
    out = common.ranked(df, ["k"], ["doc_id"], "r", per_task=20).toPandas()
    for _, part in out.groupby(out["k"].fillna("")):
        assert sorted(part["r"]) == list(range(len(part)))
