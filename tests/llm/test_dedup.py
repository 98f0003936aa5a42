import hashlib
import random
import re
from collections import Counter

import numpy as np
from conftest import DOC, prose, rows

from corrsentry.llm import neardup, substring


def words(t):
    return re.findall(r"[^\x20\x09-\x0D]+", t or "")


def brute_strip(texts, window):
    count = Counter(tuple(w[i : i + window]) for w in map(words, texts) for i in range(len(w) - window + 1))
    out = []
    for w in map(words, texts):
        gone = [False] * len(w)
        for i in range(len(w) - window + 1):
            if count[tuple(w[i : i + window])] > 1:
                gone[i : i + window] = [True] * window
        out.append((len(w), sum(gone), " ".join(x for x, g in zip(w, gone) if not g)))
    return out


def test_substrings_against_brute_force(spark, docs):
    got = sorted((r.doc_id, r.n_words, r.n_removed, r.kept) for r in substring.strip_repeats(docs).collect())
    data = [(r.doc_id, r.text) for r in docs.collect()]
    assert got == sorted((d, *x) for (d, _), x in zip(data, brute_strip([t for _, t in data], 35)))
    digest = {r.doc_id: r.kept for r in substring.strip_repeats(docs, digest=True).collect()}
    assert all(hashlib.sha256(k.encode()).hexdigest() == digest[d] for d, _, _, k in got)


def test_substrings_of_periodic_texts_and_other_windows(spark):
    rng = random.Random(5)
    texts = ["a b " * 40, "b a " * 40 + "c", "a " * 36, "a " * 35, "x y z " * 9] + [" ".join(rng.choice("abc") for _ in range(70)) for _ in range(30)]
    df = spark.createDataFrame([(i, t) for i, t in enumerate(texts)], "doc_id long, text string")
    for window, k in ((35, 8), (5, 3), (6, 6)):
        got = sorted((r.doc_id, r.n_words, r.n_removed, r.kept) for r in substring.strip_repeats(df, window, k).collect())
        assert got == [(i, *x) for i, x in enumerate(brute_strip(texts, window))]


def test_substrings_of_nothing(none, spark):
    assert substring.strip_repeats(none).count() == 0
    one = spark.createDataFrame([(None, "a b", 1, "k", "t")], "doc_id long, text string, key int, kept string, todo string")
    assert [tuple(r) for r in substring.strip_repeats(one).collect()] == [(None, 2, 0, "a b")]


def brute_components(data, size):
    sets = []
    for _, t in data:
        w = words(re.sub("[A-Z]", lambda m: m[0].lower(), t or ""))
        sets.append({tuple(w[i : i + size]) for i in range(len(w) - size + 1)} if len(w) >= size else {tuple(w)} if w else set())
    parent = list(range(len(data)))

    def find(a):
        while parent[a] != a:
            a = parent[a]
        return a

    for i in range(len(data)):
        for j in range(i):
            both = len(sets[i] & sets[j])
            if sets[i] and sets[j] and 100 * both >= 80 * (len(sets[i]) + len(sets[j]) - both):
                parent[find(i)] = find(j)
    least = {}
    for i, (d, _) in enumerate(data):
        least[find(i)] = min(least.get(find(i), d), d)
    return sorted((d, len(sets[i]), least[find(i)], least[find(i)] == d) for i, (d, _) in enumerate(data))


def test_components_against_brute_force(spark, docs):
    data = [(r.doc_id, r.text) for r in docs.collect()]
    for size in (2, 5):
        got = sorted(tuple(r) for r in neardup.near_duplicates(docs, size).collect())
        assert got == brute_components(data, size)


def test_a_chain_of_near_copies_is_one_component(spark):
    """Each text differs a little from the one before; the ends have nothing in common.  Plus a large group of near copies."""
    rng = random.Random(8)
    w, chain = prose(rng, 150).split(), []
    for i in range(40):
        w[i * 3 : i * 3 + 3] = [f"n{i}a", f"n{i}b", f"n{i}c"]
        chain.append(" ".join(w))
    base, group = prose(rng, 120).split(), []
    for i in range(150):
        v = list(base)
        for _ in range(rng.randrange(6)):
            v[rng.randrange(len(v))] = f"e{rng.randrange(10**6)}"
        group.append(" ".join(v))
    data = [(i, t) for i, t in enumerate(chain + group)]
    got = sorted(tuple(r) for r in neardup.near_duplicates(spark.createDataFrame(data, "doc_id long, text string"), 2).collect())
    assert got == brute_components(data, 2)


def test_tensored_keys_collide_as_planned():
    """Measured share of pairs of similarity 0.8 with a common key, and the number of minhashes behind the keys."""
    rng = np.random.default_rng(1)
    hit = 0
    for _ in range(200):
        x = rng.integers(0, 2**63, 180, dtype=np.uint64)
        a, b = x[:162], x[18:]  # 144 common of 180
        m = [neardup.minhashes(np.zeros(len(s), int), s, 1, 2 * neardup.Q * neardup.T) for s in (a, b)]
        ka, kb = (neardup.tensor_keys(v)[0] for v in m)
        assert len(ka) == neardup.T**2 and m[0].shape[1] == 2 * neardup.Q * neardup.T
        hit += bool((ka == kb).any())
    assert hit >= 196


def test_dropping_keeps_the_smallest_of_each_group(spark, docs, none):
    kept = neardup.drop_near_duplicates(docs)
    assert kept.columns == docs.columns
    want = sorted({c for _, _, c, _ in brute_components([(r.doc_id, r.text) for r in docs.collect()], 5)})
    assert sorted(r.doc_id for r in kept.select("doc_id").collect()) == want
    assert neardup.near_duplicates(none).count() == 0 and neardup.drop_near_duplicates(none).count() == 0


def test_repeated_and_missing_ids(spark):
    """Rows are judged by their own text: ids may be null, or repeated with other texts."""
    rng = random.Random(3)
    a, b, c = prose(rng, 80), prose(rng, 80), prose(rng, 80)
    near = lambda t: t.rsplit(" ", 1)[0] + " changed"
    data = [(7, a), (7, b), (3, near(b)), (None, near(a)), (None, c), (None, c), (None, None), (4, "")]
    df = spark.createDataFrame(data, "doc_id long, text string").repartition(3)
    got = {(r.doc_id, r.component_id, r.kept) for r in neardup.near_duplicates(df, 2).collect()}
    assert got == {(7, 7, True), (7, 3, False), (3, 3, True), (None, 7, False), (None, None, True), (4, 4, True)}
    kept = sorted(((r.doc_id, r.text) for r in neardup.drop_near_duplicates(df).collect()), key=str)
    assert kept == sorted([(7, a), (3, near(b)), (None, c), (None, None), (4, "")], key=str)


def test_fixture_has_the_hard_cases():
    data = rows()
    assert any(r[1] is None for r in data) and any(r[1] == "" for r in data) and DOC.count(",") == 4
