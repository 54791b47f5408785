"""Words and word shingles of a text as hashes, a whole text at a time in numpy.

A word is a run of bytes other than white space (20, 09 to 0D); such bytes are no part of any
other character in UTF-8. The hash of a word is a polynomial over a table of random 64-bit values of
its bytes, taken from prefix sums, so no word becomes a Python object. Equal words have equal
hashes; different ones differ but for a chance of about 2**-60.
"""

from __future__ import annotations

import numpy as np

U = np.uint64
_TABLE = np.random.default_rng(20_240_601).integers(1, 1 << 63, 256, dtype=np.uint64) * U(2) + U(1)
_BASE = 0x9E3779B97F4A7C15
_INVERSE = pow(_BASE, -1, 1 << 64)
_SPACE = np.zeros(256, bool)
_SPACE[[0x20, 9, 10, 11, 12, 13]] = True
_POWERS = [np.ones(1, np.uint64), np.ones(1, np.uint64)]


def _powers(n: int) -> tuple[np.ndarray, np.ndarray]:
    if len(_POWERS[0]) < n:
        size = 1 << (n - 1).bit_length()
        with np.errstate(over="ignore"):
            for i, base in enumerate((_BASE, _INVERSE)):
                p = np.full(size, U(base), np.uint64)
                p[0] = 1
                _POWERS[i] = np.multiply.accumulate(p)
    return _POWERS[0], _POWERS[1]


def mix(x: np.ndarray, seed: int = 0) -> np.ndarray:
    """A bijection of 64-bit values (a finaliser of shifts and products)."""
    with np.errstate(over="ignore"):
        x = x + U((seed * 0x9E3779B97F4A7C15 + 0x632BE59BD9B4E019) & 0xFFFFFFFFFFFFFFFF)
        x = (x ^ (x >> U(30))) * U(0xBF58476D1CE4E5B9)
        x = (x ^ (x >> U(27))) * U(0x94D049BB133111EB)
        return x ^ (x >> U(31))


def words(data: bytes) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Hash, first byte and end byte of each word."""
    raw = np.frombuffer(data, np.uint8)
    if not len(raw):
        return np.zeros(0, np.uint64), np.zeros(0, np.int64), np.zeros(0, np.int64)
    inside = np.concatenate([[False], ~_SPACE[raw], [False]])
    edge = np.flatnonzero(inside[1:] != inside[:-1])
    start, end = edge[::2], edge[1::2]
    power, inverse = _powers(len(raw) + 1)
    with np.errstate(over="ignore"):
        total = np.concatenate([np.zeros(1, np.uint64), np.cumsum(_TABLE[raw] * power[: len(raw)], dtype=np.uint64)])
        return mix((total[end] - total[start]) * inverse[start]), start, end


def shingles(word: np.ndarray, size: int = 5, whole: bool = False) -> np.ndarray:
    """Hash of each run of ``size`` words. whole: a text of 1 to size - 1 words is one shingle."""
    n = len(word)
    if n < size:
        if not (whole and n):
            return np.zeros(0, np.uint64)
        size = n
    with np.errstate(over="ignore"):
        out = word[: n - size + 1].copy()
        for k in range(1, size):
            out = mix(out, size) + word[k : n - size + 1 + k]
        return mix(out)


def column_words(column) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of the words of an Arrow column of texts, one text after the other, and how many each text has. Words are
    those of words(), taken from the column's own bytes."""
    import pyarrow as pa

    _, at, data = column.buffers()
    wide = np.int64 if pa.types.is_large_string(column.type) else np.int32
    offset = np.frombuffer(at, wide)[column.offset : column.offset + len(column) + 1].astype(np.int64)
    raw = np.frombuffer(data, np.uint8)[offset[0] : offset[-1]] if data is not None else np.zeros(0, np.uint8)
    offset -= offset[0]
    if not len(raw):
        return np.zeros(0, np.uint64), np.zeros(len(column), np.int64)
    inside = ~_SPACE[raw]
    first, last = inside.copy(), inside.copy()
    first[1:] &= ~inside[:-1]
    last[:-1] &= ~inside[1:]
    some = offset[1:] > offset[:-1]  # a word ends with its text
    first[offset[:-1][some]] = inside[offset[:-1][some]]
    last[offset[1:][some] - 1] = inside[offset[1:][some] - 1]
    start, end = np.flatnonzero(first), np.flatnonzero(last)
    power, inverse = _powers(len(raw) + 1)
    with np.errstate(over="ignore"):
        value = _TABLE[raw]
        value *= power[: len(raw)]
        lead = value[start]
        total = np.cumsum(value, dtype=np.uint64, out=value)
        return mix((total[end] - total[start] + lead) * inverse[start]), np.diff(np.searchsorted(start, offset))


def column_shingles(column, size: int = 5) -> tuple[np.ndarray, np.ndarray]:
    """shingles() of each text of an Arrow column, one text after the other, and how many each text has."""
    word, many = column_words(column)
    every = shingles(word, size)
    room = np.cumsum(many)[np.repeat(np.arange(len(many)), many)][: len(every)] - np.arange(len(every))  # words to the text's end
    return every[room >= size], np.maximum(0, many - size + 1)


def shingle_set(text: str | None, size: int = 5) -> np.ndarray:
    """The distinct shingles of a text, ascending."""
    return np.unique(shingles(words((text or "").encode("utf-8", "surrogatepass"))[0], size, whole=True))


def jaccard(a: np.ndarray, b: np.ndarray) -> float:
    """Of two ascending sets; 0 where both are empty."""
    both = len(np.intersect1d(a, b, assume_unique=True))
    all_ = len(a) + len(b) - both
    return both / all_ if all_ else 0.0
