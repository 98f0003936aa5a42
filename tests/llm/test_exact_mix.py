from collections import Counter
from fractions import Fraction

import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from corrsentry.llm import common, mixing


def ideal(blocks, weights, t):
    """Blocks of each source when the mix by exact weights has served t: sources that run out leave their part to the others."""
    served, left = [Fraction(0)] * len(blocks), Fraction(t)
    while left > 0:
        on = [s for s, n in enumerate(blocks) if served[s] < n]
        w = sum(weights[s] for s in on)
        step = min([left / w, *[(blocks[s] - served[s]) / weights[s] for s in on]])
        for s in on:
            served[s] += step * weights[s]
        left -= step * w
    return served


@settings(max_examples=80, deadline=None)
@given(st.lists(st.tuples(st.integers(1, 12), st.one_of(st.integers(1, 9), st.floats(1e-4, 10))), min_size=1, max_size=7))
def test_every_source_is_less_than_a_block_from_its_given_weight(sources):
    blocks, weights = [n for n, _ in sources], [w for _, w in sources]
    exact = [Fraction(w) for w in weights]
    done = [0] * len(blocks)
    for t, (s, i, release, deadline) in enumerate(mixing.order(blocks, mixing.whole_weights(weights))):
        assert i == done[s] and release <= t < deadline
        done[s] += 1
        assert all(abs(d - x) < 1 for d, x in zip(done, ideal(blocks, exact, t + 1)))
    assert done == blocks


def test_no_drift_from_the_given_weights_over_a_million_slots():
    weights = [0.61803, 0.2718281, 0.1096, 0.00041, 0.0001319]
    whole = mixing.whole_weights(weights)
    total, slots = sum(whole), 10**6
    blocks = [2 * slots * w // total + 2 for w in whole]
    done = [0] * len(whole)
    for t, (s, *_) in zip(range(1, slots + 1), mixing.order(blocks, whole)):
        done[s] += 1
        if t % 997 == 0 or t > slots - 2000:
            assert all(abs(d * total - w * t) < total for d, w in zip(done, whole))
    k = mixing.quanta(dict(enumerate(weights)))  # the rounded form is off by many blocks
    assert max(abs(k[s] / sum(k.values()) - w / total) * slots for s, w in enumerate(whole)) > 100


def test_rows_are_placed_as_the_order_says(spark, docs, none):
    rows = common.written(docs.select("doc_id", "source", "text").withColumnRenamed("text", "slot"), "t")
    out = mixing.placed(rows, block=4).toPandas()
    n = Counter(r.source if r.source is not None else "\x00" for r in rows.collect())
    names = sorted(n)
    want = [names[s] for s, *_ in mixing.order([-(-n[s] // 4) for s in names], mixing.whole_weights([float(n[s]) ** 0.5 for s in names]))]
    assert sorted(out["pos"]) == list(range(sum(n.values())))
    got = out.assign(source=out["source"].fillna("")).sort_values("pos")
    assert got["slot"].is_monotonic_increasing and [s or "\x00" for s in got.drop_duplicates("slot")["source"]] == want
    assert (out["slot"] >= out["release"]).all() and (out["slot"] < out["deadline"]).all()
    assert mixing.placed(common.written(none.select("doc_id", "source"), "t")).count() == 0


def test_sources_without_a_weight_come_last(spark):
    rows = common.written(spark.createDataFrame([(i, "abcd"[i % 4]) for i in range(400)], "doc_id long, source string"), "t")
    out = mixing.placed(rows, {"a": 3.0, "b": 1.0, "c": 0.0, "zz": 1.0}, block=1).toPandas()
    assert out[out["pos"] < 100]["source"].value_counts().to_dict() == {"a": 75, "b": 25}
    assert set(out[out["pos"] >= 200]["source"]) == {"c", "d"} and (out["phase"] == (out["pos"] >= 200)).all()


@pytest.mark.parametrize("each", [1, 3])
def test_any_number_of_sources_is_mixed(spark, each):
    n = 4 * mixing.MAX_SOURCES
    rows = common.written(spark.range(n * each).selectExpr("id doc_id", f"concat('host', id % {n}) source"), "t")
    out = mixing.placed(rows, block=1).toPandas()
    assert sorted(out["pos"]) == list(range(n * each))
    assert (out["slot"] >= out["release"]).all() and (out["slot"] < out["deadline"]).all()
    for part in range(each):  # equal weights: each host once before any host again
        assert out[(out["pos"] >= part * n) & (out["pos"] < (part + 1) * n)]["source"].nunique() == n
