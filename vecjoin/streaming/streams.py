"""Streaming operators; each helper also runs a stream over stored files to its end for checks."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..config import JoinConfig
from ..operators.join import cross_join, self_join
from ..sources.storage import folder


def event_stream(spark: SparkSession, sf_dir: str) -> DataFrame:
    schema = spark.read.parquet(f"{sf_dir}/events.parquet").schema
    return spark.readStream.schema(schema).option("pathGlobFilter", "events*.parquet").parquet(sf_dir).withColumn("ts", F.col("ts").cast("timestamp"))


def tumbling_counts(events: DataFrame, width: str = "1 day", late: str = "2 days") -> DataFrame:
    """Events and their value by type and window of event time."""
    return events.withWatermark("ts", late).groupBy(F.window("ts", width), "event_type").agg(F.count(F.lit(1)).alias("n"), F.sum("value").alias("total"))


def sliding_counts(events: DataFrame, width: str = "2 days", step: str = "1 day", late: str = "2 days") -> DataFrame:
    return events.withWatermark("ts", late).groupBy(F.window("ts", width, step), "event_type").agg(F.count(F.lit(1)).alias("n"))


def session_counts(events: DataFrame, gap: str = "12 hours", late: str = "2 days") -> DataFrame:
    return events.withWatermark("ts", late).groupBy(F.session_window("ts", gap), "user_id").agg(F.count(F.lit(1)).alias("n"))


def drop_repeats(events: DataFrame, late: str = "2 days") -> DataFrame:
    return events.withWatermark("ts", late).dropDuplicatesWithinWatermark(["event_id"])


def drain(stream: DataFrame, mode: str = "complete") -> DataFrame:
    """What the stream says after all that is there now, by way of Parquet in the session's shared folder.

    complete: the result as it stands after the last batch; append: what the batches added.
    """
    if mode not in ("complete", "append"):
        raise ValueError("mode is complete or append")
    spark = stream.sparkSession
    base = f"{folder(spark)}/drained-{uuid.uuid4().hex}"
    spark.createDataFrame([], stream.schema).write.parquet(f"{base}/out/none")

    def take(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(f"{base}/out/{number if mode == 'append' else 'last'}")  # a retried batch writes the same again

    stream.writeStream.foreachBatch(take).option("checkpointLocation", f"{base}/state").outputMode(mode).trigger(availableNow=True).start().awaitTermination()
    return spark.read.schema(stream.schema).option("recursiveFileLookup", "true").parquet(f"{base}/out")


def incremental_join(vectors: DataFrame, cfg: JoinConfig, batches: int = 3) -> DataFrame:
    """Pairs found batch by batch: each micro-batch is joined with itself and with all before it, and then stored."""
    spark = vectors.sparkSession
    base = f"{folder(spark)}/stream-{uuid.uuid4().hex}"
    dealt = vectors.select("vec_id", "v", F.pmod(F.xxhash64("vec_id"), F.lit(batches)).cast("int").alias("turn"))
    for t in range(batches):
        dealt.where(F.col("turn") == t).drop("turn").coalesce(1).write.mode("append").parquet(f"{base}/in")
    pairs = "id_lo long, id_hi long, dist double"

    def take(batch: DataFrame, number: int) -> None:
        batch = batch.select("vec_id", "v")
        empty = batch.isEmpty()  # an empty batch is written as well: later ones read all before them
        found = spark.createDataFrame([], pairs) if empty else self_join(batch, cfg)
        if number and not empty:
            old = spark.read.schema("vec_id long, v array<double>").parquet(*[f"{base}/seen/{i}" for i in range(number)])
            if not old.isEmpty():
                met = cross_join(batch, old, cfg)
                found = found.union(met.select(F.least("x_id", "y_id").alias("id_lo"), F.greatest("x_id", "y_id").alias("id_hi"), "dist"))
        found.write.mode("overwrite").parquet(f"{base}/pairs/{number}")  # a retried batch writes the same again
        batch.write.mode("overwrite").parquet(f"{base}/seen/{number}")

    query = spark.readStream.schema("vec_id long, v array<double>").option("maxFilesPerTrigger", 1).parquet(f"{base}/in").writeStream.foreachBatch(take).option("checkpointLocation", f"{base}/state").trigger(availableNow=True).start()
    query.awaitTermination()
    return spark.read.schema(pairs).option("recursiveFileLookup", "true").parquet(f"{base}/pairs")
