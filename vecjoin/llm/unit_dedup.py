"""Substring dedup by hashing units: lines, paragraphs, or stretches of words.

Lines and paragraphs (``dedup_units``): every unit of at least ``min_words`` words gets a 128-bit digest of its
normal form; the occurrence that comes first by (doc_id, text, unit number) stays and all others go.

Stretches (``dedup_passages``): a passage that begins or ends inside a line shares no whole line with its copy, and
short stock lines repeat in texts that share nothing else. So the units are runs of ``span - window + 1`` words that begin at
cuts (see ``stretches``) or at the first word, or end at the last. Any ``span`` words that two texts share hold a cut
in their first ``window`` words and therefore a whole stretch: each such passage is found. What is found is a repeat of at least
``span - window + 1`` words; up to ``window - 1`` words at either end of a passage may stay. An occurrence is a repeat
if the same words stand earlier, by (doc_id, text, word), without overlapping it. A removed span runs from its first
word to the next word that stays, or to the end.

Offsets of what went are code points of the original text.

Rows: null text has no units and stays null; shorter units and texts always stay; rows of equal doc_id and equal text
hold one occurrence together, so exact repeats of a row are treated alike, and rows of one doc_id with different texts are
told apart by the texts' digests, by which they also rank; a null doc_id ranks first; texts of any length go in
slices of whole texts; other columns pass through.
"""

from __future__ import annotations

import re

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .lines import removed_at, text_digest, units, without
from .stretches import SCHEMA, stretch_rows
from .tables import cut

MIN_WORDS = 5
SPAN, WINDOW = 50, 12
#: A word and what parts it from the next one.
_WORD = re.compile(r"[^\x00-\x2F\x3A-\x40\x5B-\x60\x7B-\x7F]+[\x00-\x2F\x3A-\x40\x5B-\x60\x7B-\x7F]*")


def first_of(rows: DataFrame, *order: str) -> DataFrame:
    """Digests that ``rows`` (h1, h2 and the ``order``) hold more than once, with their first place ``kept``; written, so that a join with it can split a frequent digest."""
    found = rows.groupBy("h1", "h2").agg(F.min(F.struct(*order)).alias("kept"), F.count(F.lit(1)).alias("n"))
    return cut(found.where("n > 1").select("h1", "h2", "kept"))


def repeated_units(docs: DataFrame, min_words: int = MIN_WORDS, paragraphs: bool = False, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """Occurrences to remove: doc_id, t (digest of the text), unit_no, first, last, and the occurrence that stays (kept_doc, kept_unit)."""
    every = units(docs, min_words, paragraphs=paragraphs, doc_id=doc_id, text=text)
    found = every.join(first_of(every, "doc_id", "t", "unit_no"), ["h1", "h2"])
    stays = F.col("kept.doc_id").eqNullSafe(F.col("doc_id")) & (F.col("kept.t") == F.col("t")) & (F.col("kept.unit_no") == F.col("unit_no"))
    return found.where(~stays).select("doc_id", "t", "unit_no", "first", "last", F.col("kept.doc_id").alias("kept_doc"), F.col("kept.unit_no").alias("kept_unit"))


def dedup_units(docs: DataFrame, min_words: int = MIN_WORDS, paragraphs: bool = False, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """``docs`` without repeated units; adds n_removed and removed spans."""
    gone = repeated_units(docs, min_words, paragraphs, doc_id, text)
    return without(docs, gone, paragraphs, doc_id, text)


def repeated_stretches(docs: DataFrame, span: int = SPAN, window: int = WINDOW, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """Stretches that repeat earlier words: doc_id, t (digest of the text), at (number of the first word)."""
    if not 0 < window <= span:
        raise ValueError("window must be from 1 to span")
    size = span - window + 1
    source = docs.select(F.col(doc_id).cast("long").alias("doc_id"), F.col(text).cast("string").alias("text"), text_digest(text).alias("t"))
    rows = source.mapInArrow(lambda batches: stretch_rows(batches, window, size), SCHEMA)
    # most digests occur once: counting their first halves leaves few rows for what follows
    twice = cut(rows.select(F.explode("h1").alias("h1")).groupBy("h1").agg(F.count(F.lit(1)).alias("n")).where("n > 1").select("h1"))
    each = rows.select("doc_id", "t", F.explode(F.arrays_zip("at", "h1", "h2")).alias("s")).select("doc_id", "t", "s.at", "s.h1", "s.h2")
    several = cut(each.join(twice, "h1").select("doc_id", "t", "at", "h1", "h2"))
    found = several.join(first_of(several, "doc_id", "t", "at"), ["h1", "h2"])
    same = F.col("kept.doc_id").eqNullSafe(F.col("doc_id")) & (F.col("kept.t") == F.col("t"))
    return found.where(~same | (F.col("at") - F.col("kept.at") >= size)).select("doc_id", "t", "at")


def cut_out(text: str, at: list[int], size: int) -> tuple[str, list[int]]:
    """``text`` without the ``size`` words from each of ``at`` on, and first and last code points of what went."""
    at = sorted(set(at))
    spans, now = [], 0
    begins = [m.start() for m in _WORD.finditer(text)] + [len(text)]
    for a in at:
        z = a + size
        if spans and a <= now:
            spans[-1] = begins[z]
        else:
            spans += [begins[a], begins[z]]
        now = z
    edges = [0, *spans, len(text)]
    return "".join(text[a:z] for a, z in zip(edges[::2], edges[1::2], strict=True)), spans


def dedup_passages(docs: DataFrame, span: int = SPAN, window: int = WINDOW, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """``docs`` without the words of repeated stretches; adds n_removed and removed spans."""
    size = span - window + 1

    @F.pandas_udf("struct<text:string,spans:array<int>>")
    def rest(texts: pd.Series, places: pd.Series) -> pd.DataFrame:
        done = [(t, []) if p is None else cut_out(t, p.tolist(), size) for t, p in zip(texts, places, strict=True)]
        return pd.DataFrame(done, columns=["text", "spans"])

    gone = repeated_stretches(docs, span, window, doc_id, text).groupBy("doc_id", "t").agg(F.collect_list("at").alias("gone"))
    return removed_at(docs, gone, rest, doc_id, text)
