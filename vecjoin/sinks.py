"""Where pairs go."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession


def write_pairs(pairs: DataFrame, path: str, key: str = "id_lo") -> None:
    """``pairs`` as Parquet in ranges of ``key``, sorted inside, so that a reader of some keys skips the other files."""
    rest = [c for c in pairs.columns if c != key][:1]
    pairs.repartitionByRange(key, *rest).sortWithinPartitions(key, *rest).write.mode("errorifexists").option("compression", "zstd").parquet(path)


def read_pairs(spark: SparkSession, path: str) -> DataFrame:
    return spark.read.parquet(path)
