"""Stretches of a text: a fixed number of words from each of its cuts on, with digests.

A cut is a word whose rank is the least of some ``window`` words in a row (of equal ranks the last), and a
word's rank is the first eight bytes of its MD5. Whether a word is a cut depends on the words near it alone, so a passage
has the same cuts wherever it stands and wherever in a line it begins.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa

from .kernels import list_array, mix64, ranges, signed, string_buffer, tokenize
from .lines import slices

SCHEMA = "doc_id long, t long, at array<int>, h1 array<long>, h2 array<long>"
#: Words whose rank a task remembers.
MOST_KNOWN = 1 << 20


class Ranks:
    """Ranks of words by their hashes; remembers those of up to ``MOST_KNOWN`` distinct words."""

    def __init__(self) -> None:
        self.hashes, self.ranks = np.zeros(0, np.uint64), np.zeros(0, np.uint64)

    def __call__(self, data: np.ndarray, hashes: np.ndarray, begin: np.ndarray, end: np.ndarray) -> np.ndarray:
        out, known = self._find(hashes)
        if not known.all():
            if len(self.hashes) > MOST_KNOWN:
                self.hashes, self.ranks = np.zeros(0, np.uint64), np.zeros(0, np.uint64)
                known[:] = False
            rest = np.flatnonzero(~known)
            new, first = np.unique(hashes[rest], return_index=True)
            spans = zip(begin[rest[first]].tolist(), end[rest[first]].tolist(), strict=True)
            ranks = np.array([int.from_bytes(hashlib.md5(data[a:z].tobytes().lower()).digest()[:8], "big") for a, z in spans], np.uint64)
            order = np.argsort(every := np.concatenate([self.hashes, new]))
            self.hashes, self.ranks = every[order], np.concatenate([self.ranks, ranks])[order]
            out, _ = self._find(hashes)
        return out

    def _find(self, hashes: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        if not len(self.hashes):
            return np.zeros(len(hashes), np.uint64), np.zeros(len(hashes), bool)
        at = np.minimum(np.searchsorted(self.hashes, hashes), len(self.hashes) - 1)
        return self.ranks[at], self.hashes[at] == hashes


def cuts(rank: np.ndarray, ptr: np.ndarray, window: int) -> np.ndarray:
    """Words that are the last least one of ``window`` words in a row of one text."""
    best, at, have = rank, np.arange(len(rank)), 1
    while have < window:
        step = min(have, window - have)
        right = best[step:] <= best[:-step]
        best, at = np.where(right, best[step:], best[:-step]), np.where(right, at[step:], at[:-step])
        have += step
        if not len(best):
            return np.zeros(0, np.int64)
    count = np.maximum(np.diff(ptr) - window + 1, 0)
    is_cut = np.zeros(len(rank), bool)
    is_cut[at[np.repeat(ptr[:-1], count) + ranges(count)]] = True
    return np.flatnonzero(is_cut)


def _powers(base: int, n: int) -> np.ndarray:
    out = np.full(n, base, np.uint64)
    out[:1] = 1
    return np.multiply.accumulate(out)


def digests(hashes: np.ndarray, starts: np.ndarray, size: int, base: int) -> np.ndarray:
    """64-bit digest of the ``size`` words from each of ``starts`` on."""
    sums = np.append(np.uint64(0), np.add.accumulate(hashes * _powers(base, len(hashes)))) if len(hashes) else np.zeros(1, np.uint64)
    back = _powers(pow(base, -1, 1 << 64), len(hashes))
    return mix64((sums[starts + size] - sums[starts]) * back[starts])


def stretch_rows(batches: Iterator[pa.RecordBatch], window: int, size: int) -> Iterator[pa.RecordBatch]:
    """One row per text of ``size`` words or more: doc_id, digest of the text, and the first word and digests of each stretch.

    Stretches begin at cuts and at the first word, and the last one ends with the last word.
    """
    ranks = Ranks()
    for whole in batches:
        for batch in slices(whole):
            data, offsets = string_buffer(batch.column(1))
            hashes, begin, end = tokenize(data, offsets)
            ptr = np.searchsorted(begin, offsets)
            n = np.diff(ptr)
            big = np.flatnonzero(n >= size)
            at = cuts(ranks(data, hashes, begin, end), ptr, window)
            at = at[at + size <= ptr[np.searchsorted(ptr, at, "right")]] if len(at) else at
            at = np.unique(np.concatenate([at, ptr[big], ptr[big + 1] - size]))
            text = np.searchsorted(ptr, at, "right") - 1
            count = np.bincount(text, minlength=batch.num_rows)[big]
            yield pa.RecordBatch.from_arrays(
                [batch.column(0).take(pa.array(big)), batch.column(2).take(pa.array(big)), list_array(pa.array((at - ptr[text]).astype(np.int32)), count)]
                + [list_array(pa.array(signed(digests(hashes, at, size, base))), count) for base in (0x9FB21C651E98DF25, 0xC2B2AE3D27D4EB4F)],
                names=["doc_id", "t", "at", "h1", "h2"],
            )
