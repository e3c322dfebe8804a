"""Vectorised text kernels that the operators share.

Everything here works on Arrow string buffers with numpy, one batch at a time, and keeps per-byte
scratch arrays to chunks of ``CHUNK`` bytes, so that memory follows the batch and not the text.
"""

from __future__ import annotations

import ctypes

import numpy as np
import pyarrow as pa

CHUNK = 1 << 18

#: Bytes of words: digits, a-z (A-Z are lower-cased first) and every byte of a non-ASCII character.
_LOWER = np.arange(256, dtype=np.uint8)
_LOWER[65:91] += 32
_WORD = np.zeros(256, dtype=bool)
_WORD[48:58] = _WORD[97:123] = _WORD[65:91] = _WORD[128:] = True

_MIX1, _MIX2, _STEP = np.uint64(0xBF58476D1CE4E5B9), np.uint64(0x94D049BB133111EB), np.uint64(0x9E3779B97F4A7C15)
_BASE = 0x5851F42D4C957F2D | 1
_S30, _S27, _S31 = np.uint64(30), np.uint64(27), np.uint64(31)


def give_back() -> None:
    """Memory that is free but still held by this process goes back to the machine: a worker lives on for tasks of other kinds."""
    pa.default_memory_pool().release_unused()
    if _TRIM is not None:
        _TRIM(0)


try:
    _TRIM = ctypes.CDLL(None).malloc_trim
except (AttributeError, OSError):  # another C library
    _TRIM = None


def _powers(base: int, n: int) -> np.ndarray:
    out, x = [], 1
    for _ in range(n):
        out.append(x)
        x = x * base & 0xFFFFFFFFFFFFFFFF
    return np.array(out, dtype=np.uint64)


_POW = _powers(_BASE, 4096)


def mix64(x: np.ndarray) -> np.ndarray:
    """A bijective scrambling of unsigned 64-bit integers."""
    x = x + _STEP
    x = (x ^ (x >> _S30)) * _MIX1
    x = (x ^ (x >> _S27)) * _MIX2
    return x ^ (x >> _S31)


def string_buffer(col: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """UTF-8 bytes and ``len(col) + 1`` offsets of a string column; nulls are empty."""
    if isinstance(col, pa.ChunkedArray):
        col = col.combine_chunks()
    if not pa.types.is_large_string(col.type):
        col = col.cast(pa.large_string())
    if col.null_count:
        col = col.fill_null("")
    _, off, data = col.buffers()
    offsets = np.frombuffer(off, dtype=np.int64)[col.offset : col.offset + len(col) + 1] if len(col) else np.zeros(1, np.int64)
    return (np.frombuffer(data, dtype=np.uint8) if data is not None else np.zeros(0, np.uint8)), offsets


def tokenize(data: np.ndarray, cuts: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Words between the byte positions ``cuts`` (ascending; no word spans one).

    Returns their 64-bit hashes and their first and one-past-last byte positions.
    """
    at, end = int(cuts[0]), int(cuts[-1])
    hashes, firsts, lasts = [], [], []
    while at < end:
        stop = min(at + CHUNK, end)
        while stop < end and _WORD[data[stop - 1]] and _WORD[data[stop]]:
            ahead = np.flatnonzero(~_WORD[data[stop : min(stop + CHUNK, end)]])
            stop = stop + int(ahead[0]) if len(ahead) else min(stop + CHUNK, end)
        raw = data[at:stop]
        word = _WORD[raw]
        begins = word.copy()
        begins[1:] &= ~word[:-1]
        inner = cuts[np.searchsorted(cuts, at) : np.searchsorted(cuts, stop)] - at
        begins[inner[word[inner]]] = True
        first = np.flatnonzero(begins)
        if len(first):
            place = np.flatnonzero(word)
            head = np.searchsorted(place, first)
            size = np.diff(np.append(head, len(place)))
            pos = np.arange(len(place)) - np.repeat(head, size)
            if pos.max(initial=0) >= len(_POW):
                power = _powers(_BASE, int(pos.max()) + 1)[pos]
            else:
                power = _POW[pos]
            value = (_LOWER[raw[place]].astype(np.uint64) + np.uint64(1)) * power
            hashes.append(mix64(np.add.reduceat(value, head) + size.astype(np.uint64)))
            firsts.append(first + at)
            lasts.append(first + at + size)
        at = stop
    if not hashes:
        return np.zeros(0, np.uint64), np.zeros(0, np.int64), np.zeros(0, np.int64)
    return np.concatenate(hashes), np.concatenate(firsts), np.concatenate(lasts)


def words_of(col: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """Word hashes of all texts of a column, and ``len(col) + 1`` pointers to each text's first word."""
    data, offsets = string_buffer(col)
    hashes, first, _ = tokenize(data, offsets)
    return hashes, np.searchsorted(first, offsets)


def grams(hashes: np.ndarray, k: int) -> np.ndarray:
    """Hash of the ``k`` words from each word on; the last ``k - 1`` have none."""
    n = len(hashes) - k + 1
    if n <= 0:
        return np.zeros(0, np.uint64)
    out = np.zeros(n, np.uint64)
    for j, p in enumerate(_powers(0xD6E8FEB86659FD93, k)):
        out += hashes[j : j + n] * p
    return mix64(out)


def inside(ptr: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray]:
    """Starts of the ``k``-grams that lie inside one text, and the number of them in each text."""
    count = np.maximum(np.diff(ptr) - k + 1, 0)
    starts = np.repeat(ptr[:-1], count) + ranges(count)
    return starts, count


def ranges(count: np.ndarray) -> np.ndarray:
    """0 .. c-1 for each c of ``count``, one after the other."""
    total = int(count.sum())
    return np.arange(total) - np.repeat(np.cumsum(count) - count, count)


def shingles(col: pa.Array, k: int = 5) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of the ``k``-word shingles of each text, and pointers; a text of fewer words has one shingle of them all."""
    hashes, ptr = words_of(col)
    starts, count = inside(ptr, k)
    gram = grams(hashes, k)
    size = np.diff(ptr)
    short = np.flatnonzero((size > 0) & (size < k))
    value = gram[starts] if len(starts) else np.zeros(0, np.uint64)
    if len(short):
        own = np.array([grams(hashes[ptr[i] : ptr[i + 1]], int(size[i]))[0] for i in short], dtype=np.uint64)
        at = np.cumsum(count)[short] - count[short]
        value = np.insert(value, at, own)
        count = count.copy()
        count[short] = 1
    return value, np.concatenate([[0], np.cumsum(count)])


#: Bits of a shingle that are kept.
HASH_BITS = 44


def weighted_sets(value: np.ndarray, ptr: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Distinct values of each text, cut to 44 bits, with their counts: text index, value, count, in order of both."""
    doc = np.repeat(np.arange(len(ptr) - 1), np.diff(ptr))
    value = value >> np.uint64(64 - HASH_BITS)
    if len(ptr) <= 1 << 20:  # both fit one integer, which sorts much faster
        both = np.sort((doc.astype(np.uint64) << np.uint64(HASH_BITS)) | value)
        new = np.ones(len(both), bool)
        new[1:] = both[1:] != both[:-1]
        at = np.flatnonzero(new)
        kept = both[at]
        return (kept >> np.uint64(HASH_BITS)).view(np.int64), kept & np.uint64((1 << HASH_BITS) - 1), np.diff(np.append(at, len(both)))
    order = np.lexsort((value, doc))
    v, d = value[order], doc[order]
    new = np.ones(len(v), bool)
    new[1:] = (v[1:] != v[:-1]) | (d[1:] != d[:-1])
    at = np.flatnonzero(new)
    return d[at], v[at], np.diff(np.append(at, len(v)))


def signed(x: np.ndarray) -> np.ndarray:
    return x.view(np.int64) if x.dtype == np.uint64 else x


def list_array(flat: pa.Array, count: np.ndarray) -> pa.Array:
    return pa.ListArray.from_arrays(pa.array(np.concatenate([[0], np.cumsum(count)]).astype(np.int32)), flat)
