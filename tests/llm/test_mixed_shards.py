import random

from conftest import DOC, prose

import corpus_pipeline as P
from corrsentry.llm import common, mixing, shards


def corpus(spark):
    rng = random.Random(11)
    return spark.createDataFrame([(i, prose(rng, 12), "en", "aaaaaabbc"[i % 9], 0) for i in range(2400)], DOC).repartition(4).cache()


def test_slots_of_every_shard_follow_the_mix(spark):
    docs = corpus(spark)
    rows = common.written(shards.sized(docs), "t")
    pos = {r.doc_id: r.pos for r in mixing.placed(rows).collect()}
    out = P.in_shards(spark, docs, "").toPandas()
    out["pos"] = out["doc_id"].map(pos)
    assert len(out) == 2400 and out["shard"].nunique() == P.N_SHARDS
    for _, part in out.groupby("shard"):
        part = part.sort_values("slot")
        assert part["slot"].tolist() == list(range(len(part))) and part["pos"].is_monotonic_increasing
    root = {s: (out["source"] == s).sum() ** 0.5 for s in "abc"}  # what the shards hold of the mix's first slots has its weights
    head = out[out["pos"] < 640]["source"].value_counts()
    assert all(abs(head[s] - 640 * root[s] / sum(root.values())) < 16 for s in "abc")


def test_slots_keep_shares_in_each_shard_and_change_with_the_mix(spark):
    rows = common.written(shards.sized(corpus(spark)), "t")
    found = []
    for weights in ({"a": 4, "b": 1, "c": 1}, {"a": 1, "b": 2, "c": 1}):
        placed = common.written(mixing.placed(rows, weights, block=1).drop("slot"), "t")
        out = shards.kd_shards(placed, ["chars", "doc_id"], n_shards=4, by="pos").toPandas()
        for _, part in out.groupby("shard"):
            head = part.sort_values("slot").head(200)["source"].value_counts()
            inside = {s: w * (part["source"] == s).mean() / (out["source"] == s).mean() for s, w in weights.items()}  # weight times the shard's part of the source
            assert all(abs(head.get(s, 0) / 200 - w / sum(inside.values())) < 0.12 for s, w in inside.items())
        found.append(out.set_index("doc_id")[["shard", "slot"]].sort_index())
    assert (found[0]["shard"] == found[1]["shard"]).all() and (found[0]["slot"] != found[1]["slot"]).mean() > 0.5


def test_ranks_by_place_are_in_order_over_many_buckets(spark):
    df = common.written(spark.createDataFrame([(i * 7 % 500, f"k{i % 3}") for i in range(500)], "p long, k string"), "t")
    for k, part in common.ranked(df, ["k"], ["p"], "r", per_task=20, place=df["p"]).toPandas().groupby("k"):
        assert part.sort_values("p")["r"].tolist() == list(range(len(part)))
