"""Cost and accuracy measures, as frames."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def recall(exact: DataFrame, found: DataFrame) -> DataFrame:
    """One row: share of the ``exact`` pairs that ``found`` has (1 where there is none), share of ``found`` that is exact, and counts."""
    e, f = exact.select("id_lo", "id_hi").distinct().withColumn("e", F.lit(1)), found.select("id_lo", "id_hi").distinct().withColumn("f", F.lit(1))
    both = e.join(f, ["id_lo", "id_hi"], "full_outer").agg(F.count("e").alias("n_exact"), F.count("f").alias("n_found"), F.count_if(F.col("e").isNotNull() & F.col("f").isNotNull()).alias("n_both"))
    share = lambda n: F.when(F.col(n) > 0, F.col("n_both") / F.col(n)).otherwise(F.lit(1.0))
    return both.select("n_exact", "n_found", share("n_exact").alias("recall"), share("n_found").alias("precision"))


def counted_recall(exact: DataFrame, found: DataFrame) -> DataFrame:
    """``recall`` of numbers (one row n each), where every pair found is told once and is one of the exact ones, as those of verified bucket pairs are."""
    both = exact.select(F.col("n").alias("n_exact")).crossJoin(found.select(F.col("n").alias("n_found")))
    return both.select("n_exact", "n_found", F.when(F.col("n_exact") > 0, F.col("n_found") / F.col("n_exact")).otherwise(F.lit(1.0)).alias("recall"), F.lit(1.0).alias("precision"))


def candidate_counts(edges: DataFrame, buckets: DataFrame) -> DataFrame:
    """One row: buckets, edges, mean degree, vector pairs across and within buckets."""
    size = buckets.select("bucket_id", "n")
    across = edges.join(size.select(F.col("bucket_id").alias("i"), F.col("n").alias("a")), "i").join(size.select(F.col("bucket_id").alias("j"), F.col("n").alias("b")), "j").agg(F.count(F.lit(1)).alias("edges"), F.coalesce(F.sum(F.col("a") * F.col("b")), F.lit(0)).alias("pairs_across"))
    own = size.agg(F.count(F.lit(1)).alias("buckets"), F.coalesce(F.sum((F.col("n") * (F.col("n") - 1) / 2).cast("long")), F.lit(0)).alias("pairs_within"))
    return across.crossJoin(own).select("buckets", "edges", (F.col("edges") / F.col("buckets")).alias("mean_degree"), "pairs_across", "pairs_within")


def traffic(loads: DataFrame, buckets: DataFrame, page: int = 4096) -> DataFrame:
    """One row: loads, bytes read in whole pages, bytes used, amplification, bytes read per vector and over the size of the data.

    ``loads`` has one row (bucket_id) for each load of a plan.
    """
    read = loads.join(buckets.select("bucket_id", "bytes"), "bucket_id").agg(F.count(F.lit(1)).alias("loads"), F.sum(F.ceil(F.col("bytes") / page) * page).alias("read_bytes"), F.sum("bytes").alias("used_bytes"))
    data = buckets.agg(F.sum("n").alias("n"), F.sum("bytes").alias("data_bytes"))
    return read.crossJoin(data).select("loads", "read_bytes", "used_bytes", (F.col("read_bytes") / F.col("used_bytes")).alias("amplification"), (F.col("read_bytes") / F.col("n")).alias("read_per_vector"), (F.col("read_bytes") / F.col("data_bytes")).alias("read_over_data"))


def bucket_skew(buckets: DataFrame, page: int = 4096) -> DataFrame:
    """One row: quartiles and extremes of bucket sizes, and the share of buckets below a page."""
    return buckets.agg(F.min("n").alias("smallest"), F.percentile("n", F.lit(0.5)).alias("median"), F.max("n").alias("largest"), F.avg((F.col("bytes") < page).cast("double")).alias("below_page"))
