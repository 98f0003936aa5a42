import random

import pyarrow as pa
from conftest import prose
from test_dedup import brute_strip

from corrsentry.llm import common, kernel, substring


def test_rows_of_null_and_repeated_ids_are_judged_by_their_own_text(spark):
    rng = random.Random(8)
    passage, other = prose(rng, 60), prose(rng, 45)
    data = []
    for d in (None, 7, None, 7, 8):
        data += [(d, f"{prose(rng, 90)} {passage} {prose(rng, 30)}"), (d, prose(rng, 300)), (d, prose(rng, 4)), (d, None)]
        data += [(d, f"{prose(rng, 120)} {passage} {other}"), (d, f"{other} {prose(rng, 20)}"), (d, f"{prose(rng, 50)} {' '.join(passage.split()[:48])} {prose(rng, 9)}")]
    data += data[:2]
    df = spark.createDataFrame(data, "doc_id long, text string").repartition(3)
    got = sorted((str(r.doc_id), r.n_words, r.n_removed, r.kept) for r in substring.strip_repeats(df).collect())
    assert got == sorted((str(d), *x) for (d, _), x in zip(data, brute_strip([t for _, t in data], 35)))


def test_edges_are_linked_where_no_text_enters_or_leaves(spark):
    """Texts 1 and 2 go a-b-c, text 3 enters at b, text 4 leaves after c for d alone: a, b are apart, b and c are one path."""
    texts = {1: "abc", 2: "abc", 3: "xbc", 4: "xbcd", 5: "d"}
    data = [(ord(g), ord(g), ord(t[i - 1]) if i else 0, key, 10 * i, 10, key * 100 + i) for key, t in texts.items() for i, g in enumerate(t)]
    again = spark.createDataFrame(data, "h long, g long, before long, key long, start int, n int, tag long")
    got = {chr(r.g): (r.c, r.link) for r in substring.edges(again).collect()}
    assert got == {"a": (2, False), "x": (2, False), "b": (4, False), "c": (4, True), "d": (2, False)}
    marked = again.join(substring.edges(again), ["h", "g"]).selectExpr("key", "h", "g", "start", "n", "c > 1 whole", "g = 100 expand", "link")
    rows = {r.key: (sorted((chr(s.g), s.start, s.n) for s in r.spans), [(chr(o.h), o.start, o.n, o.whole) for o in r.open]) for r in substring.compacted(marked.unionByName(marked)).collect()}
    assert rows[2] == ([("a", 0, 10), ("b", 10, 20)], [])
    assert rows[4] == ([("b", 10, 20), ("d", 30, 10), ("x", 0, 10)], [("d", 30, 10, True)])


def test_joins_of_hot_keys_keep_all_rows(spark):
    rows = spark.range(30_000).selectExpr("CASE WHEN id < 20000 THEN -1 ELSE id END k", "id v")
    few = rows.groupBy("k").count().withColumnRenamed("count", "c")
    assert common.even_join(rows, few, ["k"]).selectExpr("count(*)", "count(DISTINCT v)", "sum(c)").first() == (30_000, 30_000, 20_000 * 20_000 + 10_000)


def test_normal_bytes_are_the_words_with_a_space_after_each(spark):
    texts = ["  a\tbc\x0b", "", "x", "é   z\n\n", " ", "end"]
    for _, _, data, offsets in kernel.text_slices(pa.array(texts)):
        out, at, first = kernel.normal(data, offsets)
        own = [out[at[a] : at[z]].tobytes() for a, z in zip(first, first[1:])]
        assert own == [b"".join(w + b" " for w in t.encode().split()) for t in texts]
        assert len(at) - 1 == len(kernel.words(data, offsets).ids)
