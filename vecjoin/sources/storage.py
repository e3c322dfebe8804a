"""Buckets on disk: contiguous extents in raw files, found by a table of places; and where such files go."""

from __future__ import annotations

import json
import tempfile
import uuid
from collections.abc import Iterator
from dataclasses import asdict, dataclass
from urllib.parse import urlparse

import numpy as np
import pyarrow as pa
from pyarrow import fs
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

PLACES = "bucket_id long, block_no int, file string, offset long, length long, n long"


def folder(spark: SparkSession) -> str:
    """The folder that the session names for checkpoints; a temporary one where it names none."""
    context = spark.sparkContext
    if context.getCheckpointDir() is None:
        context.setCheckpointDir(spark.conf.get("spark.checkpoint.dir", None) or tempfile.mkdtemp(prefix="vecjoin-"))
    return context.getCheckpointDir()


def stored(df: DataFrame) -> DataFrame:
    """``df`` written once as a table in the checkpoint folder and read from there, so that no later step computes it again."""
    path = f"{folder(df.sparkSession)}/table-{uuid.uuid4().hex}"
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def open_files(path: str) -> tuple[fs.FileSystem, str]:
    """File system and plain path of a local path or URL."""
    if urlparse(path).scheme in ("", "file"):
        return fs.LocalFileSystem(), urlparse(path).path
    return fs.FileSystem.from_uri(path)


@dataclass(frozen=True)
class Manifest:
    """What a stored layout holds; enough to join it again at any distance and recall."""

    d: int
    n: int
    metric: str
    seed: int
    mode: str
    piece_bytes: int | None
    block_rows: int


@dataclass
class StoredLayout:
    path: str
    manifest: Manifest
    buckets: DataFrame  # bucket_id, center, radius, mean_radius, n, bytes
    places: DataFrame  # PLACES: one row for each extent

    @classmethod
    def load(cls, spark: SparkSession, path: str) -> StoredLayout:
        held = json.loads(spark.read.text(f"{path}/manifest", wholetext=True).first()[0])
        return cls(path, Manifest(**held), spark.read.parquet(f"{path}/buckets"), spark.read.schema(PLACES).parquet(f"{path}/places"))

    def extents(self) -> DataFrame:
        """One row: extents, buckets, bytes, and the share of extents below a page."""
        return self.places.agg(F.count(F.lit(1)).alias("extents"), F.count_distinct("bucket_id").alias("buckets"), F.sum("length").alias("bytes"), F.avg((F.col("length") < 4096).cast("double")).alias("below_page"))


def write_extents(assigned: DataFrame, path: str, d: int, mode: str = "clustered", piece_bytes: int | None = None, block_rows: int = 4096) -> DataFrame:
    """Writes ids and vectors of (vec_id, v, bucket_id) and returns the places of their extents.

    clustered puts the members of a block side by side; with ``piece_bytes`` a block falls into extents of about that
    size, dealt in hash order; naive stores single vectors in hash order. A task writes a file of its own name, and
    only places of tasks that ended well are returned, so a repeated task leaves an unused file and no wrong row.
    """
    if mode not in ("clustered", "naive"):
        raise ValueError("mode is clustered or naive")
    rows = max(1, (piece_bytes or 0) // (8 + 8 * d))
    size = assigned.groupBy("bucket_id").agg(F.count(F.lit(1)).alias("size"))
    dealt = assigned.select("bucket_id", "vec_id", "v").join(size, "bucket_id").withColumn("block_no", F.pmod(F.xxhash64("vec_id"), F.ceil(F.col("size") / block_rows)).cast("int"))
    piece = F.col("vec_id") if mode == "naive" else F.pmod(F.xxhash64("vec_id", F.lit(1)), F.ceil(F.col("size") / rows)) if piece_bytes else F.lit(0)
    dealt = dealt.withColumn("piece", piece.cast("long"))
    keys = ["bucket_id", "block_no"] if mode == "clustered" and not piece_bytes else [F.xxhash64("bucket_id", "block_no", "piece")]
    placed = dealt.repartitionByRange(*keys).sortWithinPartitions(*keys, "bucket_id", "block_no", "piece", "vec_id")

    def write(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        files, root = open_files(path)
        files.create_dir(f"{root}/data", recursive=True)
        name = f"data/{uuid.uuid4().hex}.bin"
        offset = 0
        with files.open_output_stream(f"{root}/{name}") as sink:

            def put(bucket: int, block: int, ids: np.ndarray, x: np.ndarray) -> tuple:
                nonlocal offset
                raw = ids.astype("<i8").tobytes() + x.astype("<f8").tobytes()
                sink.write(raw)
                offset += len(raw)
                return bucket, block, name, offset - len(raw), len(raw), len(ids)

            now, ids, xs, out = None, [], [], []
            for batch in batches:
                unit = np.column_stack([batch.column(c).to_numpy().astype(np.int64) for c in range(3)])
                v, x = batch.column(3).to_numpy(), batch.column(4).flatten().to_numpy().reshape(len(unit), -1)
                starts = np.flatnonzero(np.r_[True, (unit[1:] != unit[:-1]).any(axis=1)]) if len(unit) else []
                for s, e in zip(starts, [*starts[1:], len(unit)], strict=True):
                    if now is not None and tuple(unit[s]) != now:
                        out.append(put(*now[:2], np.concatenate(ids), np.concatenate(xs)))
                        ids, xs = [], []
                    now = tuple(unit[s])
                    ids.append(v[s:e]), xs.append(x[s:e])
                if len(out) >= 10_000:
                    yield _places(out)
                    out = []
            if now is not None:
                out.append(put(*now[:2], np.concatenate(ids), np.concatenate(xs)))
        yield _places(out)

    return placed.select("bucket_id", "block_no", "piece", "vec_id", "v").mapInArrow(write, PLACES)


def _places(rows: list[tuple]) -> pa.RecordBatch:
    kinds = (pa.int64(), pa.int32(), pa.string(), pa.int64(), pa.int64(), pa.int64())
    return pa.RecordBatch.from_arrays([pa.array([r[c] for r in rows], t) for c, t in enumerate(kinds)], names=["bucket_id", "block_no", "file", "offset", "length", "n"])


def store(spark: SparkSession, path: str, buckets: DataFrame, places: DataFrame, manifest: Manifest) -> StoredLayout:
    places.write.parquet(f"{path}/places")
    buckets.write.parquet(f"{path}/buckets")
    spark.createDataFrame([(json.dumps(asdict(manifest)),)], "value string").coalesce(1).write.text(f"{path}/manifest")
    return StoredLayout.load(spark, path)


def read_extent(files: fs.FileSystem, root: str, file: str, offset: int, length: int, n: int, sources: dict | None = None) -> tuple[np.ndarray, np.ndarray]:
    """Ids and vectors of an extent; ``sources`` holds the files that the caller keeps open."""
    if sources is None:
        with files.open_input_file(f"{root}/{file}") as source:
            raw = source.read_at(length, offset)
    else:
        if file not in sources:
            sources[file] = files.open_input_file(f"{root}/{file}")
        raw = sources[file].read_at(length, offset)
    return np.frombuffer(raw, "<i8", n), np.frombuffer(raw, "<f8", offset=8 * n).reshape(n, -1)
