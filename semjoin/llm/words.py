"""Words, word hashes and rolling n-gram hashes of whole texts, columnar in numpy.

A word is a run of bytes other than space and 0x09-0x0D.  All functions take a
slice of an Arrow string column and work on its byte buffer; memory is a small
multiple of the slice, which ``slices`` bounds by bytes (one longer text makes a
slice of its own).
"""

from __future__ import annotations

import ctypes
from collections.abc import Iterator
from dataclasses import dataclass
from functools import lru_cache

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

SLICE_BYTES = 3 << 20
HASH_BYTES = 1 << 19  # bytes whose powers are held at once
_U = np.uint64
BASE = _U(0x9E3779B97F4A7C15 | 1)
WORD_BASE = _U(0xD1342543DE82EF95)
SPACE = np.zeros(256, bool)
SPACE[[0x20, *range(0x09, 0x0E)]] = True
LOWER = np.arange(256, dtype=np.uint8)
LOWER[65:91] += 32


def strings(col: pa.Array | pa.ChunkedArray) -> pa.Array:
    """One array of strings with 64-bit offsets; null counts as empty."""
    if isinstance(col, pa.ChunkedArray):
        col = col.combine_chunks() if col.num_chunks != 1 else col.chunk(0)
    col = col.cast(pa.large_string())
    return pc.fill_null(col, "") if col.null_count else col


@lru_cache(1)
def _libc() -> ctypes.CDLL | None:
    """The C library, told to keep two arenas; None where it isn't glibc."""
    try:
        libc = ctypes.CDLL("libc.so.6")
        libc.mallopt(-8, 2)  # arenas at most
        libc.malloc_trim(0)
    except (OSError, AttributeError):
        return None
    return libc


def tidy() -> None:
    """Gives memory that is free in this worker back to the system; executors share theirs with it."""
    pa.default_memory_pool().release_unused()
    if (libc := _libc()) is not None:
        libc.malloc_trim(0)


def slices(batch: pa.RecordBatch, text: str = "text", limit: int = SLICE_BYTES) -> Iterator[tuple[pa.RecordBatch, pa.Array]]:
    """Row ranges of a batch whose texts take about ``limit`` bytes, with the text column."""
    if not batch.num_rows:
        return
    col = strings(batch.column(batch.schema.get_field_index(text)))
    at = np.frombuffer(col.buffers()[1], np.int64)[col.offset : col.offset + len(col) + 1]
    lo = 0
    while lo < len(col):
        hi = max(lo + 1, int(np.searchsorted(at, at[lo] + limit, "right")) - 1)
        yield batch.slice(lo, hi - lo), col.slice(lo, hi - lo)
        lo = hi
    tidy()


def buffer(col: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """Bytes of a large_string array and the offsets of its values in them."""
    at = np.frombuffer(col.buffers()[1], np.int64)[col.offset : col.offset + len(col) + 1]
    raw = col.buffers()[2]
    data = np.frombuffer(raw, np.uint8)[at[0] : at[-1]] if raw is not None else np.zeros(0, np.uint8)
    return data, at - at[0]


@dataclass
class Words:
    data: np.ndarray  # bytes of all words, without what separates them
    at: np.ndarray  # offsets of words in data, one more than words
    docs: np.ndarray  # index of each document's first word, one more than documents

    @property
    def n(self) -> int:
        return len(self.at) - 1

    def array(self) -> pa.Array:
        return pa.Array.from_buffers(pa.large_string(), self.n, [None, pa.py_buffer(np.ascontiguousarray(self.at)), pa.py_buffer(np.ascontiguousarray(self.data))])


def split(col: pa.Array, lower: bool = False) -> Words:
    data, at = buffer(col)
    non = ~SPACE[data]
    start = non.copy()
    start[1:] &= ~non[:-1]
    first = at[:-1][at[:-1] < at[1:]]
    start[first] = non[first]
    begin = np.flatnonzero(start)
    packed = data[non]
    word_at = np.empty(len(begin) + 1, np.int64)
    np.subtract(np.cumsum(non)[begin], 1, out=word_at[:-1])
    word_at[-1] = len(packed)
    return Words(LOWER[packed] if lower else packed, word_at, np.searchsorted(begin, at))


def mix(x: np.ndarray) -> np.ndarray:
    """A bijection of 64-bit integers that spreads every bit."""
    x = x ^ (x >> _U(30))
    x = x * _U(0xBF58476D1CE4E5B9)
    x ^= x >> _U(27)
    x *= _U(0x94D049BB133111EB)
    return x ^ (x >> _U(31))


_powers: dict[int, np.ndarray] = {}


def powers(base: np.uint64, n: int) -> np.ndarray:
    got = _powers.get(int(base))
    if got is None or len(got) < n:
        size = max(1024, 1 << int(n).bit_length())
        made = np.full(size, base, _U)
        made[0] = 1
        made = np.multiply.accumulate(made)
        if size > 1 << 20:  # an odd long text; not kept
            return made
        _powers[int(base)] = got = made
    return got


def word_hashes(w: Words, base: np.uint64 = WORD_BASE) -> np.ndarray:
    out = np.empty(w.n, _U)
    lo = 0
    while lo < w.n:
        hi = max(lo + 1, int(np.searchsorted(w.at, w.at[lo] + HASH_BYTES, "right")) - 1)
        at = w.at[lo : hi + 1] - w.at[lo]
        size = np.diff(at)
        place = np.arange(at[-1]) - np.repeat(at[:-1], size)
        v = w.data[w.at[lo] : w.at[hi]].astype(_U)
        v += _U(1)
        v *= powers(base, int(size.max()))[place]
        out[lo:hi] = mix(np.add.reduceat(v, at[:-1]) ^ (size.astype(_U) << _U(48)))
        lo = hi
    return out


def _inverse(odd: np.uint64) -> np.uint64:
    return _U(pow(int(odd), -1, 1 << 64))


def gram_hashes(h: np.ndarray, k: int, base: np.uint64 = BASE) -> np.ndarray:
    """Hash of h[i:i+k] at each i; the caller drops those that cross documents."""
    n = len(h) - k + 1
    if n <= 0:
        return np.zeros(0, _U)
    if k <= 8:
        out = np.zeros(n, _U)
        for j in range(k):
            out *= base
            out += h[j : j + n]
        return mix(out)
    s = np.zeros(len(h) + 1, _U)
    np.cumsum(h * powers(base, len(h))[: len(h)], out=s[1:])
    return mix((s[k:] - s[:n]) * powers(_inverse(base), n)[:n])


def sequence_hashes(h: np.ndarray, docs: np.ndarray) -> np.ndarray:
    """One hash for the whole word sequence of each document."""
    size = np.diff(docs)
    out = np.zeros(len(size), _U)
    if len(h):
        place = np.arange(len(h)) - np.repeat(docs[:-1], size)
        v = h * powers(BASE, int(size.max()))[place]
        full = np.flatnonzero(size)
        out[full] = np.add.reduceat(v, docs[:-1][full])
    return mix(out ^ (size.astype(_U) << _U(40)))


def ranges(start: np.ndarray, size: np.ndarray) -> np.ndarray:
    """Concatenation of start[i] .. start[i]+size[i]-1."""
    if not len(size):
        return np.zeros(0, np.int64)
    ends = np.cumsum(size)
    return np.arange(ends[-1]) + np.repeat(start - (ends - size), size)


def shingle_sets(col: pa.Array, k: int = 5) -> list[np.ndarray]:
    """Sorted distinct hashes of each document's k-word shingles (lower-cased A-Z).

    With fewer words than k, the whole sequence is the one shingle; without words
    the set is empty.
    """
    w = split(col, lower=True)
    h = word_hashes(w)
    g = gram_hashes(h, k)
    whole = sequence_hashes(h, w.docs)
    out = []
    for i, (lo, hi) in enumerate(zip(w.docs[:-1].tolist(), w.docs[1:].tolist())):
        if hi - lo >= k:
            s = g[lo : hi - k + 1].copy()
            s.sort()
            if len(s) > 1:
                keep = np.empty(len(s), bool)
                keep[0] = True
                np.not_equal(s[1:], s[:-1], out=keep[1:])
                s = s[keep]
            out.append(s)
        else:
            out.append(whole[i : i + 1] if hi > lo else g[:0])
    return out
