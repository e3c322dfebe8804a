"""Buckets whose members lie in order of an attribute, so that a range of values is one stretch of each bucket."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F


def attribute_ranges(assigned: DataFrame, attribute: str) -> DataFrame:
    """(bucket_id, value, first, n): where in a bucket, by its order, the members of each value lie."""
    sizes = assigned.groupBy("bucket_id", F.col(attribute).alias("value")).agg(F.count(F.lit(1)).alias("n"))
    before = F.sum("n").over(Window.partitionBy("bucket_id").orderBy("value").rowsBetween(Window.unboundedPreceding, -1))
    return sizes.select("bucket_id", "value", F.coalesce(before, F.lit(0)).alias("first"), "n")


def write_by_attribute(assigned: DataFrame, attribute: str, path: str, rows: int = 4096) -> None:
    """Members sorted by bucket and attribute; row groups are small, so that a reader of a range skips the others by their bounds."""
    dealt = assigned.repartitionByRange("bucket_id", attribute).sortWithinPartitions("bucket_id", attribute, "vec_id")
    dealt.write.mode("errorifexists").option("parquet.block.row.count.limit", rows).parquet(path)


def read_range(spark: SparkSession, path: str, attribute: str, low: object, high: object) -> DataFrame:
    """Members whose attribute lies from ``low`` to ``high``; the condition goes to the Parquet reader."""
    return spark.read.parquet(path).where(F.col(attribute).between(low, high))
