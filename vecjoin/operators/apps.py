"""Uses of a similarity join: groups of near duplicates, outliers, choice of the distance."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..sources.storage import folder
from .bucketize import matrix


def _cut(df: DataFrame) -> DataFrame:
    folder(df.sparkSession)
    return df.checkpoint()


def groups(pairs: DataFrame) -> DataFrame:
    """(vec_id, group): connected groups of the pairs, named by their smallest id; labels spread along links and jump to their label's label."""
    link = _cut(pairs.select(F.col("id_lo").alias("a"), F.col("id_hi").alias("b")).union(pairs.select(F.col("id_hi").alias("a"), F.col("id_lo").alias("b"))).distinct())
    label = _cut(link.groupBy("a").agg(F.min("b").alias("m")).select(F.col("a").alias("id"), F.least("a", "m").alias("group")))
    while True:
        spread = link.join(label.select(F.col("id").alias("b"), "group"), "b").groupBy(F.col("a").alias("id")).agg(F.min("group").alias("other"))
        nearer = label.join(spread, "id").select("id", F.least("group", "other").alias("group"), F.col("group").alias("was"))
        jump = nearer.select(F.col("id").alias("group"), F.col("group").alias("further"))
        new = _cut(nearer.join(jump, "group", "left").select("id", F.coalesce(F.least("group", "further"), F.col("group")).alias("group"), "was"))
        if new.where("group <> was").isEmpty():
            return new.select(F.col("id").alias("vec_id"), "group")
        label = new.select("id", "group")


def dedupe(vectors: DataFrame, pairs: DataFrame) -> DataFrame:
    """``vectors`` without those that are near a vector of a smaller id in their group."""
    return vectors.join(groups(pairs).where("vec_id <> group"), "vec_id", "left_anti")


def neighbor_counts(vectors: DataFrame, pairs: DataFrame) -> DataFrame:
    both = pairs.select(F.explode(F.array("id_lo", "id_hi")).alias("vec_id")).groupBy("vec_id").agg(F.count(F.lit(1)).alias("neighbors"))
    return vectors.select("vec_id").join(both, "vec_id", "left").select("vec_id", F.coalesce("neighbors", F.lit(0)).alias("neighbors"))


def outliers(vectors: DataFrame, pairs: DataFrame, min_neighbors: int) -> DataFrame:
    """(vec_id, neighbors) of vectors with fewer than ``min_neighbors`` within the distance."""
    return neighbor_counts(vectors, pairs).where(F.col("neighbors") < min_neighbors)


def calibrate_eps(vectors: DataFrame, k: int, sample: int = 500) -> DataFrame:
    """One row eps: the distance within which a vector has ``k`` others on average, midway to the next; from the ``sample`` smallest keyed hashes of ids against all."""
    asked = vectors.orderBy(F.md5(F.col("vec_id").cast("string")), "vec_id").limit(sample).select("vec_id", "v").collect()  # a parameter bounds it
    n, most = len(asked), len(asked) * k + 1
    names, held = np.array([r[0] for r in asked], np.int64), np.array([r[1] for r in asked], dtype=float)

    def smallest(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """The smallest distances of each batch: no other can be among the smallest of all."""
        for batch in batches:
            ids, x, out = batch.column(0).to_numpy(), matrix(batch.column(1)), np.zeros(0)
            for at in range(0, len(ids) if n else 0, 64):
                d = np.sqrt(((x[at : at + 64, None, :] - held[None, :, :]) ** 2).sum(axis=2))[ids[at : at + 64, None] != names[None, :]]
                out = np.append(out, d)
                if len(out) > 4 * most + (1 << 16):
                    out = np.partition(out, most - 1)[:most]
            yield pa.RecordBatch.from_arrays([pa.array(np.partition(out, most - 1)[:most] if len(out) > most else out)], names=["dist"])

    dist = vectors.select("vec_id", "v").mapInArrow(smallest, "dist double")
    # the n*k smallest distances are a stated, bounded number of rows
    last = dist.orderBy("dist").limit(n * k + 1)
    top = last.withColumn("rank", F.row_number().over(Window.orderBy("dist"))).where(F.col("rank") >= n * k)
    return top.agg(F.avg("dist").alias("eps"))
