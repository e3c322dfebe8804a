"""Raw vector files: each record is a 32-bit count and that many values (fvecs: floats, ivecs: integers, bvecs: bytes), little-endian.

``register`` names the format ``vecs`` in a session: ``spark.read.format("vecs").option("kind", "fvecs").load(path)`` gives
(vec_id, v), the id being a record's place in the files by name. Files are cut into ranges of whole records, so a file of
any size is read by many tasks. An empty file has no records; a file with records of different widths raises.
"""

from __future__ import annotations

import uuid
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyarrow import fs
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql.datasource import DataSource, DataSourceArrowWriter, DataSourceReader, InputPartition, WriterCommitMessage
from pyspark.sql.types import StructType

from ..functions.vectors import VectorSchemaError
from .storage import open_files

KINDS = {"fvecs": "<f4", "ivecs": "<i4", "bvecs": "u1"}
BATCH = 8192


@dataclass
class Range(InputPartition):
    path: str
    offset: int
    records: int
    width: int
    first_id: int


@dataclass
class Written(WriterCommitMessage):
    temporary: str
    final: str


def _kind(options: dict) -> str:
    kind = options.get("kind", "fvecs")
    if kind not in KINDS:
        raise ValueError(f"kind is one of {', '.join(KINDS)}")
    return kind


class VecsSource(DataSource):
    @classmethod
    def name(cls) -> str:
        return "vecs"

    def schema(self) -> str:
        return "vec_id long, v array<double>"

    def reader(self, schema: StructType) -> VecsReader:
        return VecsReader(self.options["path"], _kind(self.options), int(self.options.get("rangebytes", 128 << 20)))

    def writer(self, schema: StructType, overwrite: bool) -> VecsWriter:
        if overwrite:
            raise ValueError("vecs files are only appended to a folder")
        return VecsWriter(self.options["path"], _kind(self.options), schema.fieldNames().index("v"))


class VecsReader(DataSourceReader):
    def __init__(self, path: str, kind: str, range_bytes: int):
        self.path, self.kind, self.range_bytes = path, kind, range_bytes

    def partitions(self) -> list[Range]:
        system, plain = open_files(self.path)
        info = system.get_file_info(plain)
        if info.type == fs.FileType.NotFound:
            raise FileNotFoundError(self.path)
        files = [info] if info.type == fs.FileType.File else sorted((f for f in system.get_file_info(fs.FileSelector(plain)) if f.is_file and not f.base_name.startswith(("_", "."))), key=lambda f: f.path)
        out, seen, item = [], 0, np.dtype(KINDS[self.kind]).itemsize
        for f in files:
            if f.size == 0:
                continue
            with system.open_input_file(f.path) as handle:
                width = int(np.frombuffer(handle.read_at(4, 0).ljust(4, b"\0"), "<i4")[0])
            size = 4 + width * item
            if width < 1 or f.size % size:
                raise VectorSchemaError(f"{f.path}: {f.size} bytes aren't whole records of {width} values")
            n, step = f.size // size, max(1, self.range_bytes // size)
            out += [Range(f.path, at * size, min(step, n - at), width, seen + at) for at in range(0, n, step)]
            seen += n
        return out or [Range("", 0, 0, 1, 0)]

    def read(self, part: Range) -> Iterator[pa.RecordBatch]:
        if not part.records:
            return
        record = np.dtype([("n", "<i4"), ("v", KINDS[self.kind], (part.width,))])
        system, _ = open_files(self.path)
        with system.open_input_file(part.path) as handle:
            for at in range(0, part.records, BATCH):
                many = min(BATCH, part.records - at)
                held = np.frombuffer(handle.read_at(many * record.itemsize, part.offset + at * record.itemsize), record)
                if (held["n"] != part.width).any():
                    raise VectorSchemaError(f"{part.path}: records of different widths")
                v = pa.ListArray.from_arrays(pa.array(np.arange(0, many * part.width + 1, part.width), pa.int32()), pa.array(held["v"].astype(float).reshape(-1)))
                yield pa.RecordBatch.from_arrays([pa.array(part.first_id + at + np.arange(many)), v], names=["vec_id", "v"])


class VecsWriter(DataSourceArrowWriter):
    """A task writes a hidden file; the commit gives it its name, so lost attempts leave nothing that is read."""

    def __init__(self, path: str, kind: str, place: int):
        self.path, self.kind, self.place = path, kind, place

    def write(self, batches: Iterator[pa.RecordBatch]) -> Written:
        from pyspark import TaskContext

        system, plain = open_files(self.path)
        system.create_dir(plain, recursive=True)
        name = f"{TaskContext.get().partitionId():06d}-{uuid.uuid4().hex}.{self.kind}"
        with system.open_output_stream(f"{plain}/.{name}") as out:
            for batch in batches:
                v = batch.column(self.place)
                if v.null_count or v.flatten().null_count:
                    raise VectorSchemaError("a vector or a value is null")
                ends = v.offsets.to_numpy()
                flat = v.values.to_numpy(zero_copy_only=False)
                for lo, hi in zip(ends[:-1], ends[1:], strict=True):
                    out.write(np.int32(hi - lo).astype("<i4").tobytes() + flat[lo:hi].astype(KINDS[self.kind]).tobytes())
        return Written(f"{plain}/.{name}", f"{plain}/{name}")

    def commit(self, messages: list[Written | None]) -> None:
        system, _ = open_files(self.path)
        for m in messages:
            if m is not None:
                system.move(m.temporary, m.final)

    def abort(self, messages: list[Written | None]) -> None:
        system, _ = open_files(self.path)
        for m in messages:
            if m is not None:
                system.delete_file(m.temporary)


def register(spark: SparkSession) -> None:
    spark.dataSource.register(VecsSource)


def read_vecs(spark: SparkSession, path: str, kind: str = "fvecs") -> DataFrame:
    register(spark)
    return spark.read.format("vecs").option("kind", kind).load(path)


def write_vecs(df: DataFrame, path: str, kind: str = "fvecs") -> None:
    """The column v of ``df``, in the order of its partitions; ids are places, so they aren't kept."""
    register(df.sparkSession)
    df.select("v").write.format("vecs").option("kind", kind).mode("append").save(path)
