"""Benchmark decontamination by winnowing.

Words are hashed, every ``k`` consecutive words give one gram hash, and in each stretch of ``w``
consecutive grams the smallest hash is kept as a fingerprint. A stretch holds ``w + k - 1`` words, so any
span of that many words that a document shares with an item shares a fingerprint too. Fingerprints of
documents are looked up among those of the items, and each hit is extended word by word in both directions.

Rows: null or word-less text has no words and no hits; repeated rows and repeated item ids are judged
row by row (an item id counts once); an item with a null id counts in the hits but has no id to name; an empty benchmark contaminates nothing; other columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .kernels import grams, inside, list_array, words_of
from .lines import slices

WINDOW_WORDS, GRAM_WORDS = 10, 5
#: Bytes of benchmark text that travel to every task at once; a larger benchmark goes in several blocks.
BLOCK_BYTES = 32 << 20

HITS = "doc_id long, n_words long, spans array<struct<first:int,last:int>>, items array<string>"


def winnow(gram: np.ndarray, starts: np.ndarray, count: np.ndarray, w: int) -> np.ndarray:
    """Of the grams at ``starts`` (``count`` of them in each text), the places of those that are smallest in some stretch of ``w``; a text of fewer keeps its smallest."""
    g = gram[starts]
    if not len(g):
        return starts[:0]
    text = np.repeat(np.arange(len(count)), count)
    keep = np.zeros(len(g), bool)
    size = count[text]
    base = np.cumsum(count) - count
    best = np.arange(len(g))
    for j in range(1, w):
        other = np.minimum(np.arange(len(g)) + j, len(g) - 1)
        ok = (text[other] == text) & (np.arange(len(g)) + j == other)
        better = ok & (g[other] <= g[best])
        best = np.where(better, other, best)
    whole = (np.arange(len(g)) - base[text]) + w <= size
    keep[best[whole | ((size < w) & (np.arange(len(g)) == base[text]))]] = True
    return starts[keep]


class _Items:
    """Fingerprints and words of a block of items."""

    def __init__(self, ids: list[str | None], texts: list[str], window: int, k: int):
        self.ids, self.window, self.k = ids, window, k
        self.words, self.ptr = words_of(pa.array(texts, pa.large_string()))
        size = np.diff(self.ptr)
        owner = np.repeat(np.arange(len(ids)), size)
        self.kinds = []  # (gram length, stretch, sorted hashes, their word places)
        for n in [0, *sorted({int(s) for s in size if 0 < s < window})]:
            chosen = size >= window if n == 0 else size == n
            length, w = (k, window - k + 1) if n == 0 else (n, 1)
            gram = grams(self.words, length)
            starts, count = inside(self.ptr, length)
            at = winnow(gram, starts, count, w)
            at = at[chosen[owner[at]]] if len(at) else at
            if len(at):
                order = np.argsort(gram[at], kind="stable")
                self.kinds.append((length, w, gram[at][order], at[order]))
        self.owner = owner

    def hits(self, words: np.ndarray, ptr: np.ndarray) -> dict[int, tuple[list[tuple[int, int]], set[str]]]:
        """By text: the word spans hit, and the items."""
        out: dict[int, tuple[list[tuple[int, int]], set[str]]] = {}
        for length, w, known, places in self.kinds:
            gram = grams(words, length)
            if not len(gram):
                continue
            starts, count = inside(ptr, length)
            at = winnow(gram, starts, count, w)
            lo = np.searchsorted(known, gram[at], "left")
            hi = np.searchsorted(known, gram[at], "right")
            done: dict[tuple[int, int], int] = {}
            for i in np.flatnonzero(hi > lo):
                p = int(at[i])
                doc = int(np.searchsorted(ptr, p, "right")) - 1
                for q in places[lo[i] : hi[i]].tolist():
                    item = int(self.owner[q])
                    if done.get((item, p - q), -1) > p:
                        continue
                    first, last = self._extend(words, p, int(ptr[doc]), int(ptr[doc + 1]), q, int(self.ptr[item]), int(self.ptr[item + 1]), length)
                    done[item, p - q] = last
                    if last - first >= min(self.window, int(self.ptr[item + 1] - self.ptr[item])):
                        spans, items = out.setdefault(doc, ([], set()))
                        spans.append((first - int(ptr[doc]), last - int(ptr[doc])))
                        if self.ids[item] is not None:
                            items.add(self.ids[item])
        return out

    def _extend(self, words, p, p0, p1, q, q0, q1, length) -> tuple[int, int]:
        """The widest equal run around words p and q, inside both texts."""
        if not np.array_equal(words[p : p + length], self.words[q : q + length]):
            return p, p
        back = min(p - p0, q - q0)
        differ = np.flatnonzero(words[p - back : p] != self.words[q - back : q])
        first = p - back + (int(differ[-1]) + 1 if len(differ) else 0)
        ahead = min(p1 - p, q1 - q)
        differ = np.flatnonzero(words[p : p + ahead] != self.words[q : q + ahead])
        return first, p + (int(differ[0]) if len(differ) else ahead)


def _blocks(benchmark: DataFrame, block_bytes: int) -> Iterator[tuple[list[str | None], list[str]]]:
    """Ids and texts of the items, about ``block_bytes`` at a time."""
    items = benchmark.select(F.col("item_id").cast("string").alias("item"), F.coalesce(F.col("text").cast("string"), F.lit("")).alias("text"))
    total = items.agg(F.coalesce(F.sum(F.octet_length("text")), F.lit(0)).cast("long")).first()[0]
    blocks = max(1, -(-int(total) // block_bytes))
    for b in range(blocks):
        rows = (items.where(F.pmod(F.xxhash64("item", "text"), F.lit(blocks)) == b) if blocks > 1 else items).collect()
        yield [r[0] for r in rows], [r[1] for r in rows]


def clean_rows(batches: Iterator[pa.RecordBatch], known: _Items, at: int) -> Iterator[pa.RecordBatch]:
    """The rows whose text (column ``at``) holds no window of ``known``, by slices of bounded size."""
    for whole in batches:
        for batch in slices(whole, at):
            hits = known.hits(*words_of(batch.column(at)))
            yield batch.filter(pa.array([i not in hits for i in range(batch.num_rows)], pa.bool_()))


def drop_contaminated(docs: DataFrame, benchmark: DataFrame, window: int = WINDOW_WORDS, k: int = GRAM_WORDS, block_bytes: int = BLOCK_BYTES, text: str = "text") -> DataFrame:
    """``docs`` without the rows that share a window with an item; one pass over the rows for each block of items."""
    at = docs.columns.index(text)
    for ids, texts in _blocks(benchmark, block_bytes):

        def scan(batches: Iterator[pa.RecordBatch], ids=ids, texts=texts) -> Iterator[pa.RecordBatch]:
            yield from clean_rows(batches, _Items(ids, texts, window, k), at)

        docs = docs.mapInArrow(scan, docs.schema)
    return docs


def find_hits(docs: DataFrame, benchmark: DataFrame, window: int = WINDOW_WORDS, k: int = GRAM_WORDS, block_bytes: int = BLOCK_BYTES, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """One row per document: ``doc_id, n_words, spans`` (word spans hit, may overlap) ``, items``.

    The benchmark is cut into blocks of ``block_bytes``; each is sent to the tasks and read against all
    documents, so its size never bounds what can be checked.
    """
    if not 1 <= k <= window:
        raise ValueError("k lies between 1 and the window")
    source = docs.select(F.col(doc_id).cast("long").alias("doc_id"), F.col(text).cast("string").alias("text"))
    blocks = list(_blocks(benchmark, block_bytes))
    out = source
    for turn, (ids, texts) in enumerate(blocks):
        # the text goes along with its row, and what earlier blocks hit, until the last block
        names = [*(["text"] if turn < len(blocks) - 1 else []), "doc_id", "n_words", "spans", "items"]

        def scan(batches: Iterator[pa.RecordBatch], ids=ids, texts=texts, turn=turn, names=names) -> Iterator[pa.RecordBatch]:
            known = _Items(ids, texts, window, k)
            for batch in (part for whole in batches for part in slices(whole, whole.schema.get_field_index("text"))):
                words, ptr = words_of(batch.column("text"))
                hits = known.hits(words, ptr)
                spans = [hits[i][0] if i in hits else [] for i in range(batch.num_rows)]
                found = [hits[i][1] if i in hits else set() for i in range(batch.num_rows)]
                if turn:
                    spans = [[(s["first"], s["last"]) for s in x] + y for x, y in zip(batch.column("spans").to_pylist(), spans, strict=True)]
                    found = [y.union(x) for x, y in zip(batch.column("items").to_pylist(), found, strict=True)]
                flat = [s for x in spans for s in x]
                struct = pa.StructArray.from_arrays([pa.array([s[0] for s in flat], pa.int32()), pa.array([s[1] for s in flat], pa.int32())], names=["first", "last"])
                lists = list_array(struct, np.array([len(x) for x in spans], dtype=np.int64))
                made = {"text": batch.column("text"), "doc_id": batch.column("doc_id"), "n_words": pa.array(np.diff(ptr), pa.int64()), "spans": lists, "items": pa.array([sorted(x) for x in found], pa.list_(pa.string()))}
                yield pa.RecordBatch.from_arrays([made[n] for n in names], names=names)

        out = out.mapInArrow(scan, ("text string, " if "text" in names else "") + HITS)
    return out


def decontaminate(docs: DataFrame, benchmark: DataFrame, **options) -> DataFrame:
    """Per document: doc_id, n_words, n_hit, n_items, items, items_sha256, contaminated, spans (merged)."""
    hits = find_hits(docs, benchmark, **options)
    ordered = F.array_sort("spans")
    merged = F.aggregate(
        ordered,
        F.expr("cast(array() as array<struct<first:int,last:int>>)"),
        lambda acc, s: F.when((F.size(acc) > 0) & (F.element_at(acc, -1)["last"] >= s["first"]), F.concat(F.slice(acc, 1, F.size(acc) - 1), F.array(F.struct(F.element_at(acc, -1)["first"].alias("first"), F.greatest(F.element_at(acc, -1)["last"], s["last"]).alias("last"))))).otherwise(F.concat(acc, F.array(s))),
    )
    spans = F.when(F.size("spans") > 0, merged).otherwise(F.col("spans"))
    items = F.array_sort("items")
    out = hits.select("doc_id", "n_words", spans.alias("spans"), items.alias("items"))
    n_hit = F.aggregate("spans", F.lit(0).cast("long"), lambda acc, s: acc + (s["last"] - s["first"]).cast("long"))
    return out.select("doc_id", "n_words", n_hit.alias("n_hit"), F.size("items").cast("long").alias("n_items"), F.sha2(F.concat_ws(",", "items"), 256).alias("items_sha256"), (n_hit > 0).alias("contaminated"), "items", "spans")

