"""Given tables, and vectors derived from them."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.vectors import normalize


def read(spark: SparkSession, sf_dir: str, name: str, *cols: str) -> DataFrame:
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    return df.select(*cols) if cols else df


def embeddings(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(vec_id, v, label) of the given embeddings, in doubles."""
    return read(spark, sf_dir, "embeddings").select("vec_id", F.col("embedding").cast("array<double>").alias("v"), "label")


def planted(spark: SparkSession, sf_dir: str, copies: int = 4) -> DataFrame:
    """(vec_id, v, label, k): clusters around the embeddings whose ids equal a label, each vector with near copies."""
    emb = embeddings(spark, sf_dir)
    n = F.broadcast(emb.agg(F.count(F.lit(1)).alias("n")))
    anchors = emb.select(F.col("vec_id").alias("label"), F.col("v").alias("anchor"))
    base = emb.crossJoin(n).withColumn("k", F.explode(F.sequence(F.lit(0), F.lit(copies - 1))))
    base = base.withColumn("other", F.pmod(31 * F.col("vec_id") + 17 * F.col("k") + 7, F.col("n")))
    other = emb.select(F.col("vec_id").alias("other"), F.col("v").alias("w"))
    mixed = F.zip_with(F.zip_with("anchor", "v", lambda a, x: a + 0.35 * x), "w", lambda y, w: y + F.when(F.col("k") > 0, 0.05 * w).otherwise(F.lit(0.0)))
    return base.join(anchors, "label").join(other, "other").select((F.col("k") * F.col("n") + F.col("vec_id")).alias("vec_id"), mixed.alias("v"), "label", "k")


def hash_vectors(df: DataFrame, id_col: str, text: str, d: int = 128) -> DataFrame:
    """(vec_id, v): signed square-root term counts hashed into ``d`` places, scaled to unit length; texts without a token have no row."""
    moved = df.select(F.col(id_col).alias("vec_id"), F.col(text).alias("text")).repartition("vec_id")  # the only exchange: all three groupings hold the id
    token = moved.select("vec_id", F.explode(F.split(F.lower("text"), "\\s+")).alias("t")).where("t <> ''")
    h = F.conv(F.substring(F.md5("t"), 1, 8), 16, 10).cast("long")
    term = token.groupBy("vec_id", "t").agg(F.count(F.lit(1)).alias("n")).withColumn("h", h)
    place = term.groupBy("vec_id", F.pmod(F.floor(F.col("h") / 2), F.lit(d)).cast("int").alias("p")).agg(F.sum(F.sqrt("n") * F.when(F.col("h") % 2 == 1, 1.0).otherwise(-1.0)).alias("x"))
    held = place.groupBy("vec_id").agg(F.map_from_entries(F.collect_list(F.struct("p", "x"))).alias("m"))
    return held.select("vec_id", F.transform(F.sequence(F.lit(0), F.lit(d - 1)), lambda i: F.coalesce(F.col("m")[i], F.lit(0.0))).alias("v")).select("vec_id", normalize("v").alias("v"))


def docvec(spark: SparkSession, sf_dir: str) -> DataFrame:
    return hash_vectors(read(spark, sf_dir, "documents", "doc_id", "text"), "doc_id", "text")
