"""The ten operators' driver queries, with production parameters, and the SQL of those that SQL can express."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import benchmark_winnowing, cross_parsing, fuzzy_lines, line_blocks, merge_dropout, mpeg_audio, toxicity_kernel, unit_dedup, url_trees, weighted_minhash
from .tables import read


def op1_line_dedup(spark: SparkSession, d: str) -> DataFrame:
    return fuzzy_lines.dedup_lines(read(spark, d, "documents", "doc_id", "text")).select("doc_id", "n_removed", "removed", "text")


def op2_media_columns(spark: SparkSession, d: str) -> DataFrame:
    return mpeg_audio.media_digests(mpeg_audio.encode_texts(read(spark, d, "documents", "doc_id", "text")))


def op3_html_extraction(spark: SparkSession, d: str) -> DataFrame:
    return line_blocks.page_texts(read(spark, d, "pages", "page_id", "url", "html"))


def op4_minhash_near_dedup(spark: SparkSession, d: str) -> DataFrame:
    return weighted_minhash.near_duplicates(read(spark, d, "documents", "doc_id", "text")).select("doc_id", "class_id", "class_size", "n_texts", F.col("first").alias("keep"))


def op5_substring_dedup(spark: SparkSession, d: str) -> DataFrame:
    out = unit_dedup.dedup_passages(read(spark, d, "documents", "doc_id", "text"))
    spans = F.array_join(F.transform("removed", lambda s: F.concat_ws("-", s["first"].cast("string"), s["last"].cast("string"))), ",")
    return out.select("doc_id", "n_removed", spans.alias("removed"), "text")


def op6_language_id(spark: SparkSession, d: str) -> DataFrame:
    docs = read(spark, d, "documents", "doc_id", "text", "lang")
    held_out = cross_parsing.remainder("doc_id", 4) == 2
    found = cross_parsing.identify(docs, cross_parsing.sample_texts(docs, ~held_out))
    return found.select("doc_id", held_out.alias("held_out"), "lang_pred", "score")


def op7_sentencepiece(spark: SparkSession, d: str) -> DataFrame:
    return merge_dropout.encode_docs(read(spark, d, "documents", "doc_id", "text"))


def op8_benchmark_decontamination(spark: SparkSession, d: str) -> DataFrame:
    found = benchmark_winnowing.decontaminate(read(spark, d, "documents", "doc_id", "text"), read(spark, d, "benchmark", "item_id", "text"))
    return found.select("doc_id", "n_words", "n_hit", "n_items", "items_sha256", "contaminated")


def toxic_model(spark: SparkSession, d: str) -> toxicity_kernel.ToxicModel:
    learn = cross_parsing.remainder("doc_id", 5) != 0
    return toxicity_kernel.ToxicModel(*toxicity_kernel.training_texts(read(spark, d, "documents", "doc_id", "text"), read(spark, d, "labels", "doc_id", "toxic"), learn))


def op9_toxicity(spark: SparkSession, d: str) -> DataFrame:
    scored = toxicity_kernel.score(read(spark, d, "documents", "doc_id", "text"), toxic_model(spark, d))
    return scored.select("doc_id", (cross_parsing.remainder("doc_id", 5) == 0).alias("held_out"), "score", (F.col("score") >= 0.5).cast("int").alias("predicted"))


def op10_url_filters(spark: SparkSession, d: str) -> DataFrame:
    return url_trees.judge(read(spark, d, "pages", "page_id", "url")).select("page_id", "host", "path", "rule", "verdict")


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    ops = [op1_line_dedup, op2_media_columns, op3_html_extraction, op4_minhash_near_dedup, op5_substring_dedup, op6_language_id, op7_sentencepiece, op8_benchmark_decontamination, op9_toxicity, op10_url_filters]
    return {f.__name__: f for f in ops}


_WORDS = r"regexp_extract_all(translate(coalesce({}, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+')"

_PARTS = r"\x00-\x2F\x3A-\x40\x5B-\x60\x7B-\x7F"
_SIZE = unit_dedup.SPAN - unit_dedup.WINDOW + 1

_OP5 = rf"""
WITH texts AS (
  SELECT doc_id, regexp_extract(coalesce(text, ''), '^[{_PARTS}]*') AS lead, regexp_extract_all(coalesce(text, ''), '[^{_PARTS}]+[{_PARTS}]*') AS parts FROM documents
), w AS (
  SELECT doc_id, unnest(parts) AS part, unnest(range(len(parts))) AS no, len(parts) AS n, length(lead) AS skip FROM texts
), named AS (
  SELECT *, translate(regexp_extract(part, '[^{_PARTS}]+'), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS word FROM w
), ranked AS (
  SELECT *, substr(md5(word), 1, 16) AS rank, skip + coalesce(sum(length(part)) OVER (PARTITION BY doc_id ORDER BY no ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS first FROM named
), least_ones AS (
  SELECT doc_id, n, no, min(rank || lpad(CAST(99999999 - no AS VARCHAR), 8, '0')) OVER (PARTITION BY doc_id ORDER BY no ROWS BETWEEN CURRENT ROW AND {unit_dedup.WINDOW - 1} FOLLOWING) AS best FROM ranked
), cuts AS (
  SELECT doc_id, n, 99999999 - CAST(right(best, 8) AS BIGINT) AS a FROM least_ones WHERE no + {unit_dedup.WINDOW} <= n
  UNION SELECT doc_id, n, 0 FROM w WHERE n >= {_SIZE} UNION SELECT doc_id, n, n - {_SIZE} FROM w WHERE n >= {_SIZE}
), lists AS (
  SELECT doc_id, list(word ORDER BY no) AS words FROM named GROUP BY doc_id
), stretches AS (
  SELECT doc_id, a, md5(array_to_string(words[a + 1 : a + {_SIZE}], ' ')) AS digest FROM cuts JOIN lists USING (doc_id) WHERE a + {_SIZE} <= n
), placed AS (
  SELECT *, min(ROW(doc_id, a)) OVER (PARTITION BY digest) AS kept FROM stretches
), gone AS (
  SELECT DISTINCT doc_id, unnest(range(a, a + {_SIZE})) AS no FROM placed WHERE kept[1] <> doc_id OR a - kept[2] >= {_SIZE}
), judged AS (
  SELECT r.*, g.no IS NOT NULL AS gone FROM ranked r LEFT JOIN gone g USING (doc_id, no)
), runs AS (
  SELECT doc_id, CAST(min(first) AS BIGINT) AS a, CAST(max(first + length(part)) AS BIGINT) AS z
  FROM (SELECT *, no - row_number() OVER (PARTITION BY doc_id ORDER BY no) AS run FROM judged WHERE gone) GROUP BY doc_id, run
), spans AS (
  SELECT doc_id, count(*) AS n_removed, string_agg(a || '-' || z, ',' ORDER BY a) AS removed FROM runs GROUP BY doc_id
), kept AS (
  SELECT doc_id, string_agg(part, '' ORDER BY no) FILTER (NOT gone) AS rest FROM judged GROUP BY doc_id
)
SELECT t.doc_id, coalesce(n_removed, 0) AS n_removed, coalesce(removed, '') AS removed, lead || coalesce(rest, '') AS text
FROM texts t LEFT JOIN spans USING (doc_id) LEFT JOIN kept USING (doc_id)
"""

_OP8 = f"""
WITH items AS (
  SELECT CAST(item_id AS VARCHAR) AS item_id, {_WORDS.format("text")} AS words FROM benchmark
), windows AS (
  SELECT DISTINCT item_id, least(10, len(words)) AS n, array_to_string(words[i : i + least(10, len(words)) - 1], ' ') AS span
  FROM items, unnest(range(1, len(words) - least(10, len(words)) + 2)) AS t(i) WHERE len(words) > 0
), docs AS (
  SELECT doc_id, {_WORDS.format("text")} AS words FROM documents
), spans AS (
  SELECT doc_id, s.n, i, array_to_string(words[i : i + s.n - 1], ' ') AS span
  FROM docs, (SELECT DISTINCT n FROM windows) AS s, unnest(range(1, greatest(len(words) - s.n + 2, 1))) AS t(i)
), found AS (
  SELECT doc_id, item_id, i, n FROM spans JOIN windows USING (n, span)
), hit AS (
  SELECT doc_id, count(DISTINCT p) AS n_hit FROM (SELECT doc_id, unnest(range(i, i + n)) AS p FROM (SELECT DISTINCT doc_id, i, n FROM found)) GROUP BY doc_id
), named AS (
  SELECT doc_id, count(DISTINCT item_id) AS n_items, string_agg(DISTINCT item_id, ',' ORDER BY item_id) AS ids FROM found GROUP BY doc_id
)
SELECT d.doc_id, CAST(len(d.words) AS BIGINT) AS n_words, coalesce(n_hit, 0) AS n_hit, coalesce(n_items, 0) AS n_items,
  sha256(coalesce(ids, '')) AS items_sha256, coalesce(n_hit, 0) > 0 AS contaminated
FROM docs d LEFT JOIN hit USING (doc_id) LEFT JOIN named USING (doc_id)
"""


def oracle_sql() -> dict[str, str]:
    return {"op5_substring_dedup": _OP5, "op8_benchmark_decontamination": _OP8}
