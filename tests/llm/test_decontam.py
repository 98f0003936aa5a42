import random

import numpy as np
from conftest import prose

from corrsentry.llm import decontam
from corrsentry.llm import kernel as K


def brute(docs, items):
    """Best aligned window of every item in every document by exact similarity, trying all windows."""
    import pyarrow as pa

    index = decontam.Items(items)
    out = {}
    for d, t in docs:
        for _, _, data, offsets in K.text_slices(pa.array([t], pa.string())):
            ids = K.words(data, offsets, lower=True, punct=True).ids
            for i, size in enumerate(index.size):
                for start in range(max(len(ids) - size, 0) + 1):
                    own = ids[start : start + size]
                    if not len(own):
                        continue
                    h = K.grams(own, 5) if len(own) >= 5 else K.spans(own, np.zeros(1, int), np.array([len(own)]), salt=5)
                    s = decontam.weighted_similarity(h, index.shingles[i], index.weight)
                    if s >= 0.8:
                        out[d, index.ids[i]] = max(s, out.get((d, index.ids[i]), 0))
    return out


def test_planted_items_are_found_and_nothing_else(spark, none):
    rng = random.Random(4)
    items = [(i, prose(rng, rng.randrange(20, 60))) for i in range(12)] + [(12, "only four words here"), (13, ""), (14, None)]
    docs = []
    for i in range(60):
        w = prose(rng, rng.choice([5, 80, 300])).split()
        if i % 3 == 0:
            item = items[i // 3 % 13][1]
            own = item.upper().replace(" ", ", ").split() if i % 2 else item.split()
            if i % 5 == 0 and len(own) > 30:
                own[len(own) // 2] = "changed"
            at = rng.randrange(len(w))
            w[at:at] = own
        docs.append((i, " ".join(w)))
    docs += [(60, None), (61, ""), (62, items[0][1]), (0, docs[0][1])]
    df = spark.createDataFrame([(*d, 1.0) for d in docs], "doc_id long, text string, similarity double").repartition(3)
    bench = spark.createDataFrame(items, "item_id long, text string")
    got = {(r.doc_id, r.item_id): r.similarity for r in decontam.contaminated(df, bench).collect()}
    want = brute(docs, [x for x in items if x[1] is not None])
    assert set(got) == set(want) and all(abs(got[k] - want[k]) < 1e-9 for k in got)
    assert len(got) > 15
    clean = decontam.decontaminated(df, bench)
    assert clean.columns == df.columns and {r.doc_id for r in clean.collect()} == {d for d, _ in docs} - {d for d, _ in want}
    assert decontam.contaminated(none, bench).count() == 0
    assert decontam.contaminated(df, bench.limit(0)).count() == 0 and decontam.decontaminated(df, bench.limit(0)).count() == len(docs)


def test_items_in_several_blocks_give_the_same_pairs(spark):
    rng = random.Random(6)
    items = [(i, prose(rng, 30)) for i in range(10)]
    df = spark.createDataFrame([(i, prose(rng, 20) + " " + items[i][1]) for i in range(10)], "doc_id long, text string")
    bench = spark.createDataFrame(items, "item_id long, text string")
    blocks = list(decontam.item_blocks(bench, block_words=100))
    assert len(blocks) > 1 and sum(len(b.ids) for b in blocks) == 10
    assert decontam.contaminated(df, bench).count() == 10


def test_multi_index_finds_all_within_the_radius():
    rng = np.random.default_rng(3)
    base = rng.integers(0, 2**63, (300, decontam.LANES), dtype=np.uint64)
    other = base.copy()
    for row in other:
        for b in rng.choice(256, rng.integers(0, 80), replace=False):
            row[b // 64] ^= np.uint64(1 << int(b % 64))
    prints = np.concatenate([base, other])
    want = [(x, i) for x in range(100) for i in np.flatnonzero(np.bitwise_count(prints ^ base[x]).sum(1) <= decontam.RADIUS).tolist()]
    for few in (False, True):  # by comparing values, and by looking up all that are near
        index = decontam.MultiIndex(prints)
        if few:
            index.flips, index.tables = index.flips, [(np.r_[v, np.full(900, v[-1], np.uint64)], np.r_[f, np.full(900, f[-1])], o) for v, f, o in index.tables]
        assert [tuple(map(int, x)) for x in zip(*index.near(base[:100]))] == want
    assert decontam.MultiIndex(prints[:0]).near(base)[0].size == 0


def test_sliding_fingerprints_are_those_of_the_windows():
    rng = np.random.default_rng(4)
    h, w = rng.integers(0, 2**63, 5000, dtype=np.uint64), rng.random(5000) * 3
    starts = np.unique(np.r_[rng.integers(0, 4900, 300), np.arange(1000, 2600)])
    got = decontam.sliding_simhash(h, w, starts, 60)
    assert all((got[i] == decontam.simhash(h[s : s + 60], w[s : s + 60])).all() for i, s in enumerate(starts.tolist()))


def test_fingerprints_of_similar_sets_are_near_however_uneven_the_weights():
    """A template of low weight and some rare shingles: of sets with weighted similarity 0.8, 999 in 1000 are within the radius."""
    rng = np.random.default_rng(5)
    lost = n = 0
    for _ in range(1500):
        low, high = int(rng.integers(20, 120)), int(rng.integers(6, 30))
        h = rng.integers(0, 2**63, low + high + 40, dtype=np.uint64)
        weight = dict(zip(h.tolist(), [0.7] * low + [float(rng.uniform(3, 8))] * high + [8.0] * 40))
        of = lambda x: np.array([weight[i] for i in x.tolist()])
        a, b = h[: low + high], h.copy()
        for cut in range(1, 40):  # rare shingles of a are changed until the similarity would fall below 0.8
            c = np.concatenate([h[: low + high - cut], h[low + high : low + high + cut]])
            if cut >= high or decontam.weighted_similarity(a, c, of) < 0.8:
                break
            b = c
        if len(b) == len(a):
            n += 1
            lost += int(np.bitwise_count(decontam.simhash(a, of(a)) ^ decontam.simhash(b, of(b))).sum()) > decontam.RADIUS
    assert n > 500 and lost <= n / 1000


def test_copies_with_words_put_in_taken_out_and_changed(spark):
    """The same pairs and similarities as all windows of all items, and the first of the best windows."""
    rng = random.Random(9)
    template = prose(rng, 30)
    items = [(i, f"{template} {prose(rng, 15)}" if i % 3 == 0 else prose(rng, rng.randrange(50, 110))) for i in range(15)]
    docs = []
    for i in range(120):
        w = items[i % 15][1].split()
        for _ in range(rng.randrange(4)):
            at = rng.randrange(len(w))
            kind = rng.randrange(3)
            w[at : at + (kind != 0)] = [f"x{rng.randrange(10**6)}"] if kind != 1 else []
        docs.append((i, f"{prose(rng, rng.choice([0, 12]))} {' '.join(w)} {template if i % 4 == 0 else prose(rng, rng.choice([0, 9]))}"))
    df = spark.createDataFrame(docs, "doc_id long, text string").repartition(2)
    bench = spark.createDataFrame(items, "item_id long, text string")
    got = {(r.doc_id, r.item_id): round(r.similarity, 9) for r in decontam.contaminated(df, bench).collect()}
    assert got == {k: round(s, 9) for k, s in brute(docs, items).items()}
    assert len(got) > 40 and sum(s < 0.95 for s in got.values()) > 10
