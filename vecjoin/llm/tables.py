"""Reading the given tables, cutting lineage and finding connected groups."""

from __future__ import annotations

import tempfile
import uuid
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def read(spark: SparkSession, sf_dir: str, name: str, *cols: str) -> DataFrame:
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    return df.select(*cols) if cols else df


def folder(spark: SparkSession) -> str:
    """The folder that the session names for checkpoints; a temporary one where it names none."""
    context = spark.sparkContext
    if context.getCheckpointDir() is None:
        context.setCheckpointDir(spark.conf.get("spark.checkpoint.dir", None) or tempfile.mkdtemp(prefix="vecjoin-"))
    return context.getCheckpointDir()


def cut(df: DataFrame) -> DataFrame:
    """``df`` computed once and written, compressed, as a table in the checkpoint folder; it goes when that folder does."""
    path = f"{folder(df.sparkSession)}/cut-{uuid.uuid4().hex}"
    df.write.option("compression", "zstd").parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def maybe_in(df: DataFrame, column: str, keys: DataFrame) -> DataFrame:
    """Rows of ``df`` whose 64-bit ``column`` may be in the one column of ``keys``: all that are, and others by chance.

    The test is a bit map of one megabyte, whatever the size of ``keys``; it saves a join the rows that surely have no partner.
    """
    bit = lambda c: F.pmod(F.xxhash64(c), F.lit(_BITS))
    at = keys.select((bit(keys.columns[0]) + 1).alias("at"))  # position 0 has a bucket of its own
    maps = {r["n"]: bytes(r["map"]) for r in at.groupBy(F.bitmap_bucket_number("at").alias("n")).agg(F.bitmap_construct_agg(F.bitmap_bit_position("at")).alias("map")).collect()}
    whole = b"".join(maps.get(n + 1, bytes(4096)) for n in range(_BITS // 32768))
    names = df.columns

    def keep(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held = np.unpackbits(np.frombuffer(whole, np.uint8), bitorder="little").astype(bool)
        for batch in batches:
            yield batch.filter(pa.array(held[batch.column(len(names)).to_numpy()])).select(names)

    return df.withColumn("__bit", bit(column)).mapInArrow(keep, df.schema)


_BITS = 1 << 23


def components(links: DataFrame) -> DataFrame:
    """Connected groups of undirected ``links`` (a, b: long): one row (id, group) per node, group the smallest id.

    Alternates two kinds of star contraction until nothing changes. Minima come from partial
    aggregates and joins on the node, so a node of very many links needs no task of its own.
    """
    edge = cut(links.where("a <> b").select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")).distinct())
    before = None
    while True:
        both = edge.select("u", "v").union(edge.select(F.col("v").alias("u"), F.col("u").alias("v")))
        low = both.groupBy("u").agg(F.min("v").alias("m")).withColumn("m", F.least("u", "m"))
        large = both.where("v > u").join(low, "u").select(F.col("v").alias("u"), F.col("m").alias("v")).where("u <> v").distinct()
        low = large.groupBy("u").agg(F.min("v").alias("m"))
        small = large.join(low, "u").where("v <> m").select(F.col("v").alias("u"), F.col("m").alias("v")).union(low.select("u", F.col("m").alias("v")))
        edge = cut(small.select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v")).where("u <> v").distinct())
        now = tuple(edge.agg(F.count(F.lit(1)), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first())
        if now == before:
            break
        before = now
    members = edge.select(F.col("u").alias("id"), F.col("v").alias("group"))
    return members.union(edge.select(F.col("v").alias("id"), F.col("v").alias("group")).distinct())
