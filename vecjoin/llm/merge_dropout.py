"""SentencePiece merge-type encoding with seeded dropout, and lossless decoding.

A text gets the dummy space in front, spaces become the space mark, and the merges run inside each chunk of
leading spaces and other characters (no piece reaches beyond one). Merges go best score first, leftmost on a
tie. A candidate merge of characters [start, middle) and [middle, end) of a chunk is skipped if its keyed
hash - of seed, text, the chunk's number in the text and these three places - is below the dropout rate. The
decision doesn't depend on when the candidate comes up, so it is the same on any machine and after any retry.
Every occurrence of a chunk draws anew, in one text as well as in different ones; occurrences of a batch whose
draws come out alike share the work.

Characters that no piece has, line ends and the space mark itself are spelt in byte pieces, so decoding gives
every text back, white space included.

Rows: null text has no pieces and decodes to null; empty text has none and decodes to empty; equal texts have equal pieces;
other columns are ignored, whatever their names; a long run without spaces takes n log n steps.
"""

from __future__ import annotations

import heapq
import re
from collections import defaultdict
from collections.abc import Iterator
from functools import cached_property, lru_cache
from hashlib import blake2b
from itertools import count as counter

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .kernels import list_array, mix64, ranges
from .lines import slices

MODEL = "/opt/tokenizers/piece_bpe_32k.model"
DROPOUT, SEED = 0.1, 7
#: Chunks of more characters go through an agenda, one by one; shorter ones as rows of arrays.
LONG = 256
_MARK = "▁"
_CHUNK = re.compile(r"\n| *[^ \n]+| +")
_FULL = np.iinfo(np.int32).max


class Pieces:
    """A merge-type vocabulary with byte pieces, read from a model file."""

    def __init__(self, model: str):
        import sentencepiece

        sp = sentencepiece.SentencePieceProcessor(model_file=model)
        n = sp.get_piece_size()
        self.byte = {sp.id_to_piece(i): i for i in range(n) if sp.is_byte(i)}
        self.byte_id = np.array([self.byte[f"<0x{b:02X}>"] for b in range(256)])
        names = {sp.id_to_piece(i): i for i in range(n) if not (sp.is_byte(i) or sp.is_control(i) or sp.is_unknown(i) or sp.is_unused(i))}
        self.char = {p: i for p, i in names.items() if len(p) == 1}
        # letters that only occur inside pieces get numbers past the vocabulary
        for c in sorted({c for p in names for c in p} - self.char.keys()):
            self.char[c] = n + len(self.char)
        symbol = {**self.char, **names}
        self.base = max(symbol.values()) + 2
        pairs = {}
        for p, i in names.items():
            for cut in range(1, len(p)):
                a, b = symbol.get(p[:cut]), symbol.get(p[cut:])
                if a is not None and b is not None:
                    pairs[a * self.base + b] = i
        self.key = np.array(sorted(pairs), dtype=np.int64)
        self.merged = np.array([pairs[k] for k in self.key.tolist()], dtype=np.int32)
        order = sorted(names.values(), key=lambda i: (-sp.get_score(i), i))
        rank = np.full(n + 1, _FULL, np.int32)
        rank[order] = np.arange(len(order))
        self.rank = rank[self.merged]
        surface = [b""] * n
        for p, i in names.items():
            surface[i] = p.replace(_MARK, " ").encode()
        for b in range(256):
            surface[self.byte_id[b]] = bytes([b])
        self.size = np.array([len(s) for s in surface])
        self.begin = np.cumsum(self.size) - self.size
        self.flat = np.frombuffer(b"".join(surface), np.uint8)
        self.spelt = {c: names.get(c, -1) for c in self.char}

    def look(self, left: np.ndarray, right: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Rank (or _FULL) and result of merging neighbours."""
        key = left.astype(np.int64) * self.base + right
        at = np.minimum(np.searchsorted(self.key, key), len(self.key) - 1)
        hit = (self.key[at] == key) & (left >= 0) & (right >= 0)
        return np.where(hit, self.rank[at], np.int32(_FULL)), np.where(hit, self.merged[at], np.int32(-1))


    @cached_property
    def pairs(self) -> dict[int, tuple[int, int]]:
        """Rank and result of each pair of neighbours that merges, as a dictionary."""
        return dict(zip(self.key.tolist(), zip(self.rank.tolist(), self.merged.tolist(), strict=True), strict=True))


@lru_cache(maxsize=2)
def pieces(model: str) -> Pieces:
    return Pieces(model)


def _text_key(text: str, seed: int) -> int:
    """A keyed hash of a text."""
    return int.from_bytes(blake2b(text.encode("utf-8", "surrogatepass"), digest_size=8, key=str(seed).encode()).digest(), "little")


def _skipped(key: np.ndarray, start: np.ndarray, middle: np.ndarray, end: np.ndarray, dropout: float) -> np.ndarray:
    if dropout <= 0:
        return np.zeros(len(key), bool)
    h = mix64(key ^ ((start.astype(np.uint64) << np.uint64(42)) | (middle.astype(np.uint64) << np.uint64(21)) | end.astype(np.uint64)))
    return (h >> np.uint64(11)) * (1.0 / (1 << 53)) < dropout


def merge_chunks(chunks: list[str], chunk: np.ndarray, key: np.ndarray, vocabulary: Pieces, dropout: float) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Pieces of occurrences of distinct ``chunks``: ids of all outcomes, and where each occurrence's begin and how many they are.

    ``chunk`` and ``key`` have the chunk and the own key of each occurrence.
    """
    size = np.array([len(c) for c in chunks], dtype=np.int64)
    begin, count = np.zeros(len(chunk), np.int64), np.zeros(len(chunk), np.int64)
    parts: list[np.ndarray] = []
    used = 0
    order = np.argsort(size, kind="stable")
    # occurrences in order of their chunks: both in one integer, which sorts much faster
    by_chunk = np.sort((chunk.astype(np.int64) << 32) | np.arange(len(chunk))) & 0xFFFFFFFF
    last = np.cumsum(np.bincount(chunk, minlength=len(chunks)))
    a = 0
    short = int(np.searchsorted(size[order], LONG, "right"))
    for i in order[short:].tolist():
        for o in by_chunk[(last[i - 1] if i else 0) : last[i]].tolist():
            flat = _merge_long(chunks[i], int(key[o]), vocabulary, dropout)
            begin[o], count[o] = used, len(flat)
            parts.append(flat)
            used += len(flat)
    order = order[:short]
    while a < len(order):
        width = int(size[order[a]])
        z = int(np.searchsorted(size[order], width + (0 if width <= 4 else 3), "right"))
        z = min(z, a + max(1, (1 << 19) // max(1, width)))
        rows = order[a:z]
        a = z
        width = int(size[rows[-1]])
        points = np.zeros((len(rows), width), np.int64)
        own = np.frombuffer("".join(chunks[i] for i in rows.tolist()).encode("utf-32-le", "surrogatepass"), np.uint32)
        points[np.repeat(np.arange(len(rows)), size[rows]), ranges(size[rows])] = own
        first = np.append(0, last)[rows]
        each = last[rows] - first
        occurrence = by_chunk[np.repeat(first, each) + ranges(each)]
        flat, at, n = _merge_block(points, size[rows], np.repeat(np.arange(len(rows)), each), key[occurrence], vocabulary, dropout, [chunks[i] for i in rows.tolist()])
        begin[occurrence], count[occurrence] = at + used, n
        parts.append(flat)
        used += len(flat)
    return np.concatenate([np.zeros(0, np.int32), *parts]), begin, count


def _merge_long(text: str, key: int, v: Pieces, dropout: float) -> np.ndarray:
    """Ids of one occurrence of a long chunk, by an agenda: candidates wait in a heap, and symbols are a linked list.

    The outcome is that of ``_merge_block``, in n log n steps instead of n for each merge.
    """
    symbol = [-1 if c in (_MARK, "\n") else v.char.get(_MARK if c == " " else c, -1) for c in text]
    n = len(symbol)
    end, before, after = list(range(1, n + 1)), list(range(-1, n - 1)), [*range(1, n), -1]
    agenda: list[tuple[int, ...]] = []  # rank, place of the left symbol, both symbols, the result, place of the right symbol and its end

    def ask(i: int) -> None:
        j = after[i]
        if j >= 0 and symbol[i] >= 0 and symbol[j] >= 0:
            hit = v.pairs.get(symbol[i] * v.base + symbol[j])
            if hit is not None and hit[0] < _FULL:
                heapq.heappush(agenda, (hit[0], i, symbol[i], symbol[j], hit[1], j, end[j]))

    for i in range(n):
        ask(i)
    while agenda:
        _, i, x, y, result, j, stop = heapq.heappop(agenda)
        if symbol[i] != x or after[i] != j or symbol[j] != y or end[j] != stop:
            continue
        if dropout > 0 and _draw(key, i, j, stop) < dropout:
            continue  # skipped for good: only a pair of other symbols comes up again
        symbol[i], end[i], after[i] = result, stop, after[j]
        symbol[j] = -3
        if after[i] >= 0:
            before[after[i]] = i
        if before[i] >= 0:
            ask(before[i])
        ask(i)
    ids, i = [], 0
    while i >= 0 and n:
        ids.extend([symbol[i]] if 0 <= symbol[i] < len(v.size) else v.byte_id[list(text[i].encode("utf-8", "surrogatepass"))].tolist())
        i = after[i]
    return np.array(ids, np.int32)


def _draw(key: int, start: int, middle: int, end: int) -> float:
    """The draw of ``_skipped`` for one candidate."""
    full = 0xFFFFFFFFFFFFFFFF
    x = ((key ^ ((start << 42 | middle << 21 | end) & full)) + 0x9E3779B97F4A7C15) & full
    x = ((x ^ x >> 30) * 0xBF58476D1CE4E5B9) & full
    x = ((x ^ x >> 27) * 0x94D049BB133111EB) & full
    return ((x ^ x >> 31) >> 11) * (1.0 / (1 << 53))


def _merge_block(points, size, row, key, v: Pieces, dropout, chunks) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Ids of the outcomes of some chunks, and for each occurrence (``row``: its chunk) where its outcome begins and how many ids it has.

    Occurrences whose draws have been alike so far stand in one state; each step takes the best candidate of every
    state, and its occurrences part by their own draws into those that merge it and those that skip it for good.
    """
    n, width = points.shape
    kinds, back = np.unique(points, return_inverse=True)
    # the space mark as typed is spelt in bytes; a space becomes the mark
    table = np.array([v.char.get(_MARK, -1) if k == 32 else -1 if chr(k) in (_MARK, "\n") else v.char.get(chr(k), -1) for k in kinds.tolist()], dtype=np.int32)
    symbol = table[back.reshape(points.shape)]
    symbol[np.arange(width)[None, :] >= size[:, None]] = -2
    edge = np.broadcast_to(np.arange(width + 1, dtype=np.int32), (n, width + 1)).copy()  # first character of each symbol, and the end
    rank = np.full((n, max(width - 1, 1)), _FULL, np.int32)
    result = np.full(rank.shape, -1, np.int32)
    if width > 1:
        r, m = v.look(symbol[:, :-1].ravel(), symbol[:, 1:].ravel())
        rank, result = r.reshape(n, -1), m.reshape(n, -1)
    origin = np.arange(n)
    who, state = np.arange(len(row)), row  # occurrences still going, and their states
    begin, count = np.zeros(len(row), np.int64), np.zeros(len(row), np.int64)
    parts: list[np.ndarray] = []
    used = 0
    while len(symbol):
        best = np.argmin(rank, axis=1)
        going = rank[np.arange(len(best)), best] < _FULL
        if not going.all():
            flat, each = _spelt(symbol[~going], edge[~going], origin[~going], v, chunks)
            at = np.zeros(len(going), np.int64)
            amount = np.zeros(len(going), np.int64)
            amount[~going] = each
            at[~going] = np.cumsum(each) - each + used
            ended = ~going[state]
            begin[who[ended]], count[who[ended]] = at[state[ended]], amount[state[ended]]
            parts.append(flat)
            used += len(flat)
            number = np.cumsum(going) - 1
            who, state = who[~ended], number[state[~ended]]
            symbol, edge, rank, result, origin, best = symbol[going], edge[going], rank[going], result[going], origin[going], best[going]
            if not len(symbol):
                break
        at = np.arange(len(symbol))
        places = edge[at, best], edge[at, best + 1], edge[at, best + 2]
        skip = _skipped(key[who], *(p[state] for p in places), dropout)
        some = np.zeros(2 * len(symbol), bool)
        some[state + len(symbol) * skip] = True
        number = np.cumsum(some) - 1
        state = number[state + len(symbol) * skip]
        on, off = np.flatnonzero(some[: len(symbol)]), np.flatnonzero(some[len(symbol) :])
        held = rank[off]
        held[np.arange(len(off)), best[off]] = _FULL
        merged = _merged(symbol[on], edge[on], rank[on], result[on], best[on], v)
        symbol, edge, rank, result = (np.concatenate(x) for x in zip(merged, (symbol[off], edge[off], held, result[off]), strict=True))
        origin = np.concatenate([origin[on], origin[off]])
        w = symbol.shape[1]
        if w > 2 and (symbol[:, -1] == -2).all():
            symbol, edge, rank, result = symbol[:, :-1], edge[:, :-1], rank[:, :-1], result[:, :-1]
    return np.concatenate([np.zeros(0, np.int32), *parts]), begin, count


def _merged(symbol, edge, rank, result, best, v: Pieces) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """States after the merge at ``best``, as wide as before."""
    at, w = np.arange(len(symbol)), symbol.shape[1]
    symbol = symbol.copy()
    symbol[at, best] = result[at, best]
    fill = lambda x, value: np.concatenate([x, np.full((len(x), 1), value, x.dtype)], axis=1)
    symbol = fill(_dropped(symbol, best + 1), -2)
    edge = _dropped(edge, best + 1)
    edge = np.concatenate([edge, edge[:, -1:]], axis=1)
    rank, result = fill(_dropped(rank, best), _FULL), fill(_dropped(result, best), -1)
    for side in (best - 1, best):
        ok = (side >= 0) & (side < w - 1)
        row, col = at[ok], side[ok]
        rank[row, col], result[row, col] = v.look(symbol[row, col], symbol[row, col + 1])
    return symbol, edge, rank, result


def _dropped(x: np.ndarray, column: np.ndarray) -> np.ndarray:
    """Rows of ``x`` without one ``column`` each."""
    keep = np.ones(x.shape, bool)
    keep[np.arange(len(x)), column] = False
    return x[keep].reshape(len(x), x.shape[1] - 1)


def _spelt(symbol, edge, origin, v: Pieces, chunks) -> tuple[np.ndarray, np.ndarray]:
    """Ids of finished states one after the other, and how many each has; symbols outside the vocabulary are spelt in bytes."""
    held = symbol != -2
    each = held.sum(axis=1)
    plain = np.flatnonzero((held & ((symbol == -1) | (symbol >= len(v.size)))).any(axis=1))
    if not len(plain):
        return symbol[held].astype(np.int32), each
    own = np.split(symbol[held], np.cumsum(each)[:-1])
    for i in plain.tolist():
        text, ids = chunks[origin[i]], []
        for j, s in enumerate(own[i].tolist()):
            ids.extend([s] if 0 <= s < len(v.size) else v.byte_id[list(text[edge[i, j]].encode("utf-8", "surrogatepass"))].tolist())
        own[i] = np.array(ids)
    return np.concatenate(own).astype(np.int32), np.array([len(x) for x in own])


def encode(texts: list[str | None], vocabulary: Pieces, dropout: float = DROPOUT, seed: int = SEED) -> tuple[np.ndarray, np.ndarray]:
    """Piece ids of all texts, one after the other, and how many each has."""
    number: dict[str, int] = defaultdict(counter().__next__)  # a chunk gets the next number when it is first met
    index: list[int] = []
    per_text, own = np.zeros(len(texts), np.int64), np.zeros(len(texts), np.uint64)
    for i, t in enumerate(texts):
        if not t:
            continue
        before = len(index)
        index.extend(map(number.__getitem__, _CHUNK.findall(" " + t)))
        per_text[i], own[i] = len(index) - before, _text_key(t, seed)
    if not index:
        return np.zeros(0, np.int32), per_text
    key = mix64(np.repeat(own, per_text) ^ mix64(ranges(per_text).astype(np.uint64)))
    flat, begin, each = merge_chunks(list(number), np.array(index), key, vocabulary, dropout)
    ids = flat[np.repeat(begin, each) + ranges(each)]
    total = np.bincount(np.repeat(np.arange(len(texts)), per_text), weights=each, minlength=len(texts)).astype(np.int64)
    return ids, total


def decode(ids: np.ndarray, count: np.ndarray, vocabulary: Pieces) -> list[str]:
    """Texts of runs of piece ids, some hundred thousand pieces at a time."""
    ends = np.cumsum(count)
    out: list[str] = []
    a = 0
    while a < len(count):
        base = int(ends[a - 1]) if a else 0
        z = max(a + 1, int(np.searchsorted(ends, base + 300_000, "right")))
        own = ids[base : int(ends[z - 1])]
        each = vocabulary.size[own]
        data = vocabulary.flat[np.repeat(vocabulary.begin[own], each) + ranges(each)].tobytes()
        at = np.append(0, np.cumsum(each))[np.append(base, ends[a:z]) - base].tolist()
        out += [data[p:q].decode("utf-8", "surrogatepass")[1:] for p, q in zip(at, at[1:], strict=False)]
        a = z
    return out


def encode_docs(docs: DataFrame, dropout: float = DROPOUT, seed: int = SEED, model: str = MODEL, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """doc_id, ids (array; null where the text is), n_pieces, lossless (the pieces decode to the very text)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        vocabulary = pieces(model)
        for whole in batches:
            for batch in slices(whole, 1, 3 << 20):
                texts = batch.column(1).to_pylist()
                ids, count = encode(texts, vocabulary, dropout, seed)
                back = decode(ids, count, vocabulary)
                same = [(t or "") == b for t, b in zip(texts, back, strict=True)]
                lists = list_array(pa.array(ids.astype(np.int32)), count)
                nothing = pa.array([t is None for t in texts])
                import pyarrow.compute as pc

                yield pa.RecordBatch.from_arrays([batch.column(0), pc.if_else(nothing, None, lists) if pc.any(nothing).as_py() else lists, pa.array(count), pa.array(same)], names=["doc_id", "ids", "n_pieces", "lossless"])

    return docs.select(F.col(doc_id).cast("long").alias("doc_id"), F.col(text).cast("string").alias("text")).mapInArrow(run, "doc_id long, ids array<int>, n_pieces long, lossless boolean")


def decode_docs(encoded: DataFrame, model: str = MODEL) -> DataFrame:
    """doc_id and text of rows (doc_id, ids)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        vocabulary = pieces(model)
        for batch in batches:
            lists = [x or [] for x in batch.column(1).to_pylist()]
            ids = np.array([i for x in lists for i in x], dtype=np.int64)
            texts = decode(ids, np.array([len(x) for x in lists], dtype=np.int64), vocabulary)
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array([t if v else None for t, v in zip(texts, batch.column(1).is_valid().to_pylist(), strict=True)], pa.string())], names=["doc_id", "text"])

    return encoded.select("doc_id", "ids").mapInArrow(run, "doc_id long, text string")
