import random

from conftest import prose

from corrsentry.llm import decontam


def edited(rng, text, changes):
    w = text.split()
    for at in rng.sample(range(len(w)), changes):
        w[at] = f"x{rng.randrange(10**6)}"
    return " ".join(w)


def test_edited_copies_have_the_same_similarities_in_one_block_and_in_many(spark):
    rng = random.Random(5)
    template = prose(rng, 40)
    items = [(i, f"{template} {prose(rng, 25)}" if i % 2 else prose(rng, 60)) for i in range(24)] + [(24, ""), (25, None), (26, "four words of template"), (27, items_text := prose(rng, 50)), (28, items_text)]
    docs = [(i, f"{prose(rng, 15)} {edited(rng, items[i % 24][1], i % 3)} {prose(rng, 10)}") for i in range(96)] + [(96, items_text), (97, items[26][1])]
    df = spark.createDataFrame(docs, "doc_id long, text string").repartition(3)
    bench = spark.createDataFrame(items, "item_id long, text string").repartition(2)
    assert len(list(decontam.item_blocks(bench, block_words=150))) > 5
    one, many = ({(r.doc_id, r.item_id): round(r.similarity, 12) for r in decontam.contaminated(df, bench, block_words=n).collect()} for n in (2_000_000, 150))
    assert one == many and len(one) > 40 and sum(s < 0.9 for s in one.values()) > 5
    whole = decontam.Items([x for x in items if x[1] is not None])
    n, (keys, counts) = decontam.shingle_counts(bench)
    assert n == whole.n and len(keys) and dict(zip(keys.tolist(), counts.tolist())).items() <= {int(k): round(whole.n / (2.718281828459045**w - 1)) for k, w in zip(whole.keys, whole.key_weight)}.items()
    assert {r.doc_id for r in decontam.decontaminated(df, bench, block_words=150).collect()} == {d for d, _ in docs} - {d for d, _ in one}
