import random

import pytest

DOC = "doc_id long, text string, lang string, source string, n_chars long"


def prose(rng: random.Random, n: int, start: int = 0) -> str:
    words = [f"w{rng.randrange(400)}" + rng.choice(["", "", ".", ","]) for _ in range(n)]
    return " ".join(words)


def rows(seed: int = 1, n: int = 120) -> list[tuple]:
    """Documents with copies, near copies, shared passages, nulls, empty, one-word and long texts, and repeated rows."""
    rng = random.Random(seed)
    shared = [prose(rng, k) for k in (34, 35, 36, 60, 90)]
    out = []
    for i in range(n):
        kind = i % 10
        text = prose(rng, rng.choice([3, 20, 60, 200]))
        if kind in (1, 2):
            cut = rng.randrange(len(text.split()))
            w = text.split()
            text = " ".join([*w[:cut], rng.choice(shared), *w[cut:]])
        elif kind == 3 and i > 10:
            text = out[i - 7][1]
        elif kind in (4, 5) and i > 20 and (out[i - 11][1] or "").strip():
            w = out[i - 11][1].split()
            for _ in range(max(1, len(w) // 30)):
                w[rng.randrange(len(w))] = "edited"
            text = " ".join(w)
        elif kind == 6:
            text = ["", None, " \n\t ", "one", "a a a a " * 30, "Ünïcode   wörter"][i // 10 % 6]
        out.append((i, text, ["en", "de", None][i % 3], None if i % 17 == 0 else "src0" if i % 3 == 0 else f"src{i % 7}", len(text or "")))
    out.append((n, prose(rng, 40_000), "en", "src1", 0))
    out.append((n + 1, out[n][1][:150_000], "en", "src1", 0))
    out += out[5:8]  # repeated rows
    return out


@pytest.fixture(scope="session")
def docs(spark):
    return spark.createDataFrame(rows(), DOC).repartition(5).cache()


@pytest.fixture(scope="session")
def none(spark):
    return spark.createDataFrame([], DOC)
