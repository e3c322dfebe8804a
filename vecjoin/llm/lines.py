"""Lines and paragraphs of documents as rows: where they are, and digests of their words.

The normal form of a unit is its sequence of words (A-Z lower-cased, everything else but digits, a-z and
non-ASCII characters parted off), so spacing, case and punctuation make no difference.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .kernels import give_back, grams, list_array, mix64, ranges, signed, string_buffer, tokenize

SCHEMA = "doc_id long, t long, unit_no int, h1 long, h2 long, simhash long, n_words int, first int, last int"
SLICE_BYTES = 2 << 20
BANDS = 5
_TURN = mix64(np.arange(1, BANDS + 1, dtype=np.uint64))
_ODD = mix64(_TURN) | np.uint64(1)


def slices(batch: pa.RecordBatch, column: int = 1, most: int = SLICE_BYTES) -> Iterator[pa.RecordBatch]:
    """Runs of rows of about ``most`` bytes of text each, so scratch memory doesn't follow the batch; what it took goes back after the last one."""
    size = np.diff(string_buffer(batch.column(column))[1])
    group = (np.cumsum(size) - 1).clip(0) // most
    at = np.flatnonzero(np.diff(group)) + 1
    for a, b in zip([0, *at.tolist()], [*at.tolist(), batch.num_rows], strict=True):
        if b > a:
            yield batch.slice(a, b - a)
    give_back()


def simhashes(hashes: np.ndarray, unit: np.ndarray, n: int) -> np.ndarray:
    """64-bit SimHash of the distinct words of each of ``n`` units; bit j is set where more words have it than have not."""
    out = np.zeros(n, np.uint64)
    if not len(hashes):
        return out
    _, h, head = _distinct(hashes, unit, n)
    # eight lanes of eight one-byte counters for each word; a byte holds the votes of up to 255 words
    lanes = _LANES[mix64(h).view(np.uint8).reshape(-1, 8)]
    size = np.diff(np.append(head, len(h)))
    parts = -(-size // 255)
    cut = np.repeat(head, parts) + 255 * ranges(parts)
    sums = np.add.reduceat(lanes, cut, axis=0).view(np.uint8).reshape(-1, 64).astype(np.int32)
    votes = np.add.reduceat(sums, np.cumsum(parts) - parts, axis=0)
    packed = np.packbits(2 * votes > size[:, None], axis=1, bitorder="little")
    out[unit_of(hashes, unit)] = packed.view(np.uint64).reshape(-1)
    return out


def band_keys(hashes: np.ndarray, width: np.ndarray, unit: np.ndarray, n: int) -> np.ndarray:
    """``BANDS`` 32-bit keys for each of ``n`` units, each of the word triple that comes first in a random order.

    The ends of a unit count as words, so w words have w triples. A triple weighs its bytes, as short ones are the
    common ones; two units agree in a key with about the share of the weight that they have in common.
    """
    out = np.zeros((n, BANDS), np.int32)
    if not len(hashes):
        return out
    head = np.flatnonzero(np.append(True, unit[1:] != unit[:-1]))
    size = np.diff(np.append(head, len(hashes)))
    # each unit between two ends
    place = np.arange(len(hashes)) + 2 * np.repeat(np.arange(len(head)), size) + 1
    word, weight = np.zeros(len(hashes) + 2 * len(head), np.uint64), np.ones(len(hashes) + 2 * len(head))
    word[place], weight[place] = hashes, width
    triple = grams(word, 3)[place - 1]
    weight = 1 / (weight[:-2] + weight[1:-1] + weight[2:])[place - 1]
    chosen = unit[head]
    for band in range(BANDS):
        least = np.minimum.reduceat(mix64((triple ^ _TURN[band]) * _ODD[band]) * weight, head)
        out[chosen, band] = (mix64(least.view(np.uint64)) >> np.uint64(32)).astype(np.uint32).view(np.int32)
    return out


def unit_of(hashes: np.ndarray, unit: np.ndarray) -> np.ndarray:
    """The units that have a word, in order."""
    return unit[np.append(True, unit[1:] != unit[:-1])] if len(unit) else unit


def _distinct(hashes: np.ndarray, unit: np.ndarray, n: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Distinct words (42 bits of their hashes) of each unit in order, and where each unit begins."""
    own = np.cumsum(np.append(False, unit[1:] != unit[:-1])).astype(np.uint64)
    if n < 1 << 22:
        both = np.sort((own << np.uint64(42)) | (hashes >> np.uint64(22)))
        both = both[np.append(True, both[1:] != both[:-1])]
        u, h = both >> np.uint64(42), both & np.uint64((1 << 42) - 1)
    else:
        order = np.lexsort((hashes, own))
        u, h = own[order], hashes[order] >> np.uint64(22)
        keep = np.append(True, (u[1:] != u[:-1]) | (h[1:] != h[:-1]))
        u, h = u[keep], h[keep]
    return u, h, np.flatnonzero(np.append(True, u[1:] != u[:-1]))


#: For each byte, a one-byte counter for each of its bits.
_LANES = np.unpackbits(np.arange(256, dtype=np.uint8)[:, None], axis=1, bitorder="little").copy().view(np.uint64).reshape(-1)


def _cuts(data: np.ndarray, offsets: np.ndarray, paragraphs: bool) -> tuple[np.ndarray, np.ndarray]:
    """First and one-past-last byte of each unit, with the separator left out; units of each text by ``searchsorted``."""
    a, z = int(offsets[0]), int(offsets[-1])
    newline = np.flatnonzero(data[a:z] == 10) + a
    if paragraphs:
        follows = np.zeros(len(newline), bool)
        follows[:-1] = np.diff(newline) == 1
        starts = newline[follows]  # "\n\n" parts; a run of more leaves empty units
        keep = np.ones(len(starts), bool)
        for i in range(1, len(starts)):
            keep[i] = not (keep[i - 1] and starts[i] == starts[i - 1] + 1)
        text = np.searchsorted(offsets, starts, "right")
        newline = starts[keep & (starts + 1 < offsets[np.minimum(text, len(offsets) - 1)])]
    width = 2 if paragraphs else 1
    first = np.sort(np.concatenate([offsets[:-1], newline + width]), kind="stable")
    last = np.sort(np.concatenate([offsets[1:], newline]), kind="stable")
    return first, last


def unit_rows(batches: Iterator[pa.RecordBatch], with_simhash: bool, paragraphs: bool, min_words: int, with_bands: bool = False) -> Iterator[pa.RecordBatch]:
    for whole in batches:
        for batch in slices(whole):
            data, offsets = string_buffer(batch.column(1))
            first, last = _cuts(data, offsets, paragraphs)
            text = _owners(first, last, offsets)
            per_text = np.bincount(text, minlength=batch.num_rows)
            number = ranges(per_text)
            cuts = np.unique(np.concatenate([first, last, offsets]))
            hashes, begin, end = tokenize(data, cuts)
            unit = np.searchsorted(last, begin, "right")
            n = len(first)
            words = np.bincount(unit, minlength=n)
            big = words >= min_words
            h1, h2 = _sequence(hashes, unit, words, 0x9FB21C651E98DF25), _sequence(hashes, unit, words, 0xC2B2AE3D27D4EB4F)
            if with_simhash:
                chosen = big[unit]
                sim = simhashes(hashes[chosen], unit[chosen], n)
            else:
                sim = np.zeros(n, np.uint64)
            follow = np.flatnonzero((data[int(offsets[0]) : int(offsets[-1])] & 0xC0) == 0x80) + int(offsets[0])
            base = offsets[:-1][text]
            skip = np.searchsorted(follow, base)
            start = first - base - (np.searchsorted(follow, first) - skip)
            stop = last - base - (np.searchsorted(follow, last) - skip)
            at = np.flatnonzero(big)
            names = ["doc_id", "t", "unit_no", "h1", "h2", "simhash", "n_words", "first", "last"]
            bands = []
            if with_bands:
                chosen = big[unit]
                keys = band_keys(hashes[chosen], (end - begin)[chosen], unit[chosen], n)[at]
                # code points of the normal form: those of the words and one space between each two
                size = np.bincount(unit, weights=end - begin, minlength=n).astype(np.int64) - (np.searchsorted(follow, last) - np.searchsorted(follow, first)) + words - 1
                bands = [list_array(pa.array(keys.reshape(-1)), np.full(len(at), BANDS)), pa.array(size[at].astype(np.int32))]
                names = [*names, "bands", "size"]
            yield pa.RecordBatch.from_arrays(
                [batch.column(0).take(pa.array(text[at])), batch.column(2).take(pa.array(text[at])), pa.array(number[at].astype(np.int32)), pa.array(signed(h1[at])), pa.array(signed(h2[at])), pa.array(signed(sim[at])), pa.array(words[at].astype(np.int32)), pa.array(start[at].astype(np.int32)), pa.array(stop[at].astype(np.int32)), *bands],
                names=names,
            )


def _owners(first: np.ndarray, last: np.ndarray, offsets: np.ndarray) -> np.ndarray:
    """Text of each unit: unit i lies in the text whose end is the first at or after its own, counting ends already used up."""
    ends = np.sort(offsets[1:], kind="stable")
    # the i-th text end closes exactly one unit, in order; find which entries of last are text ends
    before = np.searchsorted(last, ends, "left")
    rank = ranges(np.bincount(np.searchsorted(np.unique(ends), ends))) if len(ends) else ends
    closing = before + rank
    # separators at the same byte as a later text's end can't occur: a separator is a byte inside its text
    mark = np.zeros(len(last), np.int64)
    mark[closing] = 1
    return np.cumsum(mark) - mark


def _sequence(hashes: np.ndarray, unit: np.ndarray, words: np.ndarray, base: int) -> np.ndarray:
    """Order-sensitive 64-bit digest of each unit's words."""
    if not len(hashes):
        return np.zeros(len(words), np.uint64)
    most = int(words.max())
    power = np.ones(most, np.uint64)
    power[1:] = np.uint64(base)
    power = np.multiply.accumulate(power)
    head = np.flatnonzero(words)
    at = (np.cumsum(words) - words)[head]
    out = np.zeros(len(words), np.uint64)
    out[head] = mix64(np.add.reduceat((hashes ^ np.uint64(base)) * power[ranges(words[head])], at) + words[head].astype(np.uint64))
    return out


def units(docs: DataFrame, min_words: int, with_simhash: bool = False, paragraphs: bool = False, doc_id: str = "doc_id", text: str = "text", with_bands: bool = False) -> DataFrame:
    """One row per line (or blank-line separated paragraph) of at least ``min_words`` words; offsets are in code points."""
    source = docs.select(F.col(doc_id).cast("long").alias("doc_id"), F.col(text).cast("string").alias("text"), text_digest(text).alias("t"))
    return source.mapInArrow(lambda batches: unit_rows(batches, with_simhash, paragraphs, min_words, with_bands), SCHEMA + (", bands array<int>, size int" if with_bands else ""))


def separator(paragraphs: bool) -> str:
    return "\n\n" if paragraphs else "\n"


def normal(unit: Column) -> Column:
    """The words of a unit joined by one space, as SQL."""
    upper = "ABCDEFGHIJKLMNOPQRSTUVWXYZ"
    return F.trim(F.regexp_replace(F.translate(unit, upper, upper.lower()), "[\\x00-\\x2F\\x3A-\\x60\\x7B-\\x7F]+", " "))


def text_digest(text: str) -> Column:
    """By which rows that share a doc_id are told apart."""
    return F.xxhash64(F.col(text).cast("string"))


def removed_at(docs: DataFrame, gone: DataFrame, rest: Callable[..., Column], doc_id: str, text: str) -> DataFrame:
    """``docs`` with what ``rest`` leaves of each text that has a row in ``gone`` (doc_id, t, gone: what ``rest`` takes).

    Adds n_removed and removed (first and last code point of each span as they were); text is null only where it was.
    """
    gone = gone.select(F.col("doc_id").alias("__gone_doc"), F.col("t").alias("__gone_t"), F.col("gone").alias("__gone"))
    out = docs.join(gone, docs[doc_id].cast("long").eqNullSafe(gone["__gone_doc"]) & (text_digest(text) == gone["__gone_t"]), "left")
    # only the texts that lose something go through Python
    out = out.withColumn("__rest", rest(F.when(F.col("__gone").isNotNull(), F.col(text).cast("string")), F.col("__gone")))
    spans = F.transform(F.sequence(F.lit(0), F.size("__rest.spans") - 2, F.lit(2)), lambda i: F.struct(F.get("__rest.spans", i).alias("first"), F.get("__rest.spans", i + 1).alias("last")))
    none = F.expr("cast(array() as array<struct<first:int,last:int>>)")
    touched = F.coalesce(F.size("__rest.spans") > 0, F.lit(False))
    out = out.withColumns({text: F.when(touched, F.col("__rest.text")).otherwise(F.col(text)), "removed": F.when(touched, spans).otherwise(none)})
    return out.withColumn("n_removed", F.size("removed").cast("long")).drop("__gone_doc", "__gone_t", "__gone", "__rest")


def without(docs: DataFrame, removed: DataFrame, paragraphs: bool = False, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """``docs`` with their ``removed`` units (doc_id, t, unit_no, first, last) gone; see ``removed_at``."""
    sep = separator(paragraphs)

    @F.pandas_udf("struct<text:string,spans:array<int>>")
    def rest(texts: pd.Series, units: pd.Series) -> pd.DataFrame:
        done = []
        for t, u in zip(texts, units, strict=True):
            if u is None:
                done.append((t, []))
                continue
            flat = sorted({(x["unit_no"], x["first"], x["last"]) for x in u})
            numbers = {x[0] for x in flat}
            done.append((sep.join(p for i, p in enumerate(t.split(sep)) if i not in numbers), [x for _, a, z in flat for x in (a, z)]))
        return pd.DataFrame(done, columns=["text", "spans"])

    gone = removed.groupBy("doc_id", "t").agg(F.collect_list(F.struct("unit_no", "first", "last")).alias("gone"))
    return removed_at(docs, gone, rest, doc_id, text)
