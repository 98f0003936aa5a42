import random
import re

import numpy as np
import pyarrow as pa

from corrsentry.llm import kernel as K


def split(texts, limit=64, **kind):
    out = []
    for lo, hi, data, offsets in K.text_slices(pa.array(texts, pa.string()), limit):
        w = K.words(data, offsets, **kind)
        for r in range(hi - lo):
            at = slice(w.first[r], w.first[r + 1])
            out.append(([bytes(data[a:b]).decode() for a, b in zip(w.start[at], w.end[at])], w.ids[at].tolist()))
    return out


def test_words_are_those_of_the_pattern_and_ids_follow_content():
    rng = random.Random(3)
    texts = ["".join(rng.choice("abÉ \t\n\x0b\x0c\r x") for _ in range(rng.randrange(60))) for _ in range(200)] + [None, "", " "]
    known = {}
    for text, (found, ids) in zip(texts, split(texts)):
        assert found == re.findall(r"[^\x20\x09-\x0D]+", text or "")
        for x, i in zip(found, ids):
            assert known.setdefault(x, i) == i
    assert len(set(known.values())) == len(known)


def test_lower_and_punctuation():
    (a, ia), (b, ib) = split(["Ab,cD", "ab CD"], lower=True, punct=True)
    assert a == ["Ab", "cD"] and ia == ib


def test_pieces_of_a_long_text_agree_with_the_whole(monkeypatch):
    text = " ".join(f"w{i % 97}" for i in range(5000))
    whole = split([text], limit=1 << 20)
    monkeypatch.setattr(K, "SLICE_BYTES", 512)
    assert split([text], limit=1 << 20) == whole


def test_grams_spans_and_distinct_depend_on_content_only():
    ids = K.mix(np.array([1, 2, 3, 1, 2, 3, 9], np.uint64))
    g = K.grams(ids, 3)
    assert g[0] == g[3] and len(set(g.tolist())) == 4
    s = K.spans(ids, np.array([0, 3, 1]), np.array([3, 6, 4]))
    assert s[0] == s[1] != s[2]
    row, h = K.distinct(np.array([1, 0, 1]), np.array([5, 5, 5], np.uint64))
    assert row.tolist() == [0, 1] and h.tolist() == [5, 5]
