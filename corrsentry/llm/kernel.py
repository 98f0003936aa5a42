"""Vectorised text kernels shared by the operators: one numpy pass over the bytes of an Arrow string column.

A *word* is a maximal run of bytes that are no separator.  Its id is a 64-bit hash of its bytes alone, so equal
words have equal ids in every batch, task and run.  All arithmetic on ids wraps modulo 2**64.
"""

from __future__ import annotations

import ctypes
from collections.abc import Iterator
from typing import NamedTuple

import numpy as np
import pyarrow as pa

U = np.uint64
#: An odd multiplier and its inverse modulo 2**64, used for all polynomial hashes.
BASE = 0x9E3779B97F4A7C15
INVERSE = pow(BASE, -1, 1 << 64)
#: Bytes of text handled at once; a longer document is cut at separators.
SLICE_BYTES = 1 << 20


def mix(x: np.ndarray) -> np.ndarray:
    """A bijective scrambling of 64-bit values (xor-shift-multiply finaliser)."""
    x = x.astype(U, copy=True)
    x ^= x >> U(30)
    x *= U(0xBF58476D1CE4E5B9)
    x ^= x >> U(27)
    x *= U(0x94D049BB133111EB)
    x ^= x >> U(31)
    return x


def powers(base: int, n: int) -> np.ndarray:
    """base**0 .. base**(n-1) modulo 2**64."""
    out = np.full(max(n, 1), base, U)
    out[0] = 1
    return np.multiply.accumulate(out)[:n]


_BYTE = mix(np.arange(1, 257, dtype=U) * U(BASE))
_LOWER = _BYTE[np.array([b + 32 if 65 <= b <= 90 else b for b in range(256)])]
_POW, _INV = powers(BASE, 2 * SLICE_BYTES), powers(INVERSE, 2 * SLICE_BYTES)
SPACE = np.zeros(256, bool)
SPACE[[0x20, *range(0x09, 0x0E)]] = True
#: Separators besides white space where punctuation does not belong to words: all ASCII that is no letter or digit.
PUNCT = np.array([b < 128 and not chr(b).isalnum() for b in range(256)])


class Words(NamedTuple):
    ids: np.ndarray  # uint64 hash of each word
    row: np.ndarray  # row that each word belongs to
    first: np.ndarray  # rows + 1 offsets into the words
    start: np.ndarray  # byte where each word starts
    end: np.ndarray  # byte after each word
    head: np.ndarray | None = None  # uint64 hash of each word's first bytes, if asked for


def text_slices(column: pa.Array, limit: int = SLICE_BYTES) -> Iterator[tuple[int, int, np.ndarray, np.ndarray]]:
    """(lo, hi, bytes, offsets) of consecutive rows with about `limit` bytes; a null counts as an empty text."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    column = column.cast(pa.large_string()).fill_null("")
    n = len(column)
    offsets = np.frombuffer(column.buffers()[1], np.int64)[column.offset : column.offset + n + 1] if n else np.zeros(1, np.int64)
    raw = column.buffers()[2]
    data = np.frombuffer(raw, np.uint8) if raw is not None and raw.size else np.zeros(0, np.uint8)
    lo = 0
    while lo < n:
        hi = max(lo + 1, int(np.searchsorted(offsets, offsets[lo] + limit, "right")) - 1)
        hi = min(hi, n)
        yield lo, hi, data[offsets[lo] : offsets[hi]], offsets[lo : hi + 1] - offsets[lo]
        lo = hi


def _piece(data: np.ndarray, breaks: np.ndarray, table: np.ndarray, sep: np.ndarray, prefix: int) -> tuple:
    n = len(data)
    gap = sep[data]
    before, after = np.empty(n, bool), np.empty(n, bool)
    before[0], before[1:] = True, gap[:-1]
    after[-1], after[:-1] = True, gap[1:]
    inner = breaks[(breaks > 0) & (breaks < n)]
    before[inner], after[inner - 1] = True, True
    word = ~gap
    start, end = np.flatnonzero(word & before), np.flatnonzero(word & after) + 1
    if n <= len(_POW):
        pow_, inv = _POW, _INV
    else:
        pow_, inv = powers(BASE, n), powers(INVERSE, n)
    total = np.zeros(n + 1, U)
    np.cumsum(table[data] * inv[:n], out=total[1:])
    ids = mix((total[end] - total[start]) * pow_[start])
    head = mix((total[np.minimum(end, start + prefix)] - total[start]) * pow_[start] + U(1)) if prefix else None
    return ids, start, end, head


def words(data: np.ndarray, offsets: np.ndarray, lower: bool = False, punct: bool = False, sep: np.ndarray | None = None, prefix: int = 0) -> Words:
    """Words of all rows.  lower: A-Z count as a-z.  punct: ASCII punctuation separates words, too.  sep: other separators
    (256 booleans).  prefix: also the hash of each word's first bytes, so many at most."""
    table = _LOWER if lower else _BYTE
    sep = (SPACE | PUNCT if punct else SPACE) if sep is None else sep
    ids, start, end, heads, at, n = [], [], [], [], 0, len(data)
    while at < n:
        to = min(n, at + SLICE_BYTES)
        while to < n:  # cut between words only
            ahead = sep[data[to : to + 4096]]
            if ahead.any():
                to += int(ahead.argmax())
                break
            to = min(n, to + 4096)
        i, s, e, h = _piece(data[at:to], offsets - at, table, sep, prefix)
        ids.append(i), start.append(s + at), end.append(e + at), heads.append(h)
        at = to
    if not ids:
        none = np.zeros(0, np.int64)
        return Words(np.zeros(0, U), none, np.zeros(len(offsets), np.int64), none, none, np.zeros(0, U) if prefix else None)
    i, s, e = np.concatenate(ids), np.concatenate(start), np.concatenate(end)
    first = np.searchsorted(s, offsets)
    return Words(i, np.repeat(np.arange(len(offsets) - 1), np.diff(first)), first, s, e, np.concatenate(heads) if prefix else None)


def normal(data: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(bytes of all words with a space after each, where each word begins there and the end, first: rows + 1 offsets
    into the words).  The words are those of words() with its defaults."""
    n = len(data)
    if not n:
        return np.zeros(0, np.uint8), np.zeros(1, np.int64), np.zeros(len(offsets), np.int64)
    word = ~SPACE[data]
    edge = np.ones(n + 1, bool)
    edge[1:n] = ~word[:-1]
    edge[offsets] = True
    start = np.flatnonzero(word & edge[:-1])
    edge[:n] = ~word
    edge[offsets] = True
    size = np.flatnonzero(word & edge[1:]) + 2 - start
    at = np.concatenate([np.zeros(1, np.int64), np.cumsum(size)])
    own = np.ones(at[-1], bool)
    own[at[1:] - 1] = False
    out = np.full(at[-1], 0x20, np.uint8)
    out[own] = data[word]
    return out, at, np.searchsorted(start, offsets)


def give_back() -> None:
    """Return freed memory to the system: Python workers stay alive between stages, beside the next stage's needs."""
    pa.default_memory_pool().release_unused()
    trim = getattr(ctypes.CDLL(None), "malloc_trim", None)
    if trim:
        trim(0)


def grams(ids: np.ndarray, k: int) -> np.ndarray:
    """Hash of the k ids from each position on (positions to len(ids) - k)."""
    n = len(ids) - k + 1
    if n <= 0:
        return np.zeros(0, U)
    out = ids[:n].copy()
    for j in range(1, k):
        out *= U(BASE)
        out += ids[j : j + n]
    return mix(out)


def spans(ids: np.ndarray, start: np.ndarray, end: np.ndarray, salt: int = 0) -> np.ndarray:
    """Hash of ids[start:end] for each pair of bounds; equal sequences have equal hashes wherever they stand."""
    total = np.zeros(len(ids) + 1, U)
    np.cumsum(mix(ids ^ U(salt)) * powers(INVERSE, len(ids)), out=total[1:])
    return mix((total[end] - total[start]) * powers(BASE, len(ids) + 1)[start] + (end - start).astype(U) * U(BASE))


def row_grams(w: Words, k: int) -> tuple[np.ndarray, np.ndarray]:
    """(row, hash) of every k-word shingle; a row with 1 to k-1 words has its whole sequence as the only one."""
    n = np.diff(w.first)
    g = grams(w.ids, k)
    at = np.arange(len(g))
    inside = at + k <= w.first[1:][w.row[: len(g)]]
    row, h = w.row[: len(g)][inside], g[inside]
    short = np.flatnonzero((n > 0) & (n < k))
    if len(short):
        own = spans(w.ids, w.first[short], w.first[short + 1], salt=k)
        row, h = np.concatenate([row, short]), np.concatenate([h, own])
        order = np.argsort(row, kind="stable")
        row, h = row[order], h[order]
    return row, h


def distinct(row: np.ndarray, h: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(row, hash) without repeats, sorted by both."""
    order = np.lexsort((h, row))
    row, h = row[order], h[order]
    new = np.ones(len(h), bool)
    new[1:] = (row[1:] != row[:-1]) | (h[1:] != h[:-1])
    return row[new], h[new]


def by_row(row: np.ndarray, n: int) -> np.ndarray:
    """n + 1 offsets of the rows in a sorted row column."""
    return np.searchsorted(row, np.arange(n + 1))


def signed(x: np.ndarray) -> np.ndarray:
    return np.ascontiguousarray(x).view(np.int64)
