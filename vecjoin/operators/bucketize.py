"""Buckets: sampled centres, nearest-centre assignment, statistics, and block storage."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.proximity import ProximityGraph

#: Centres of at most so many bytes are sent to every task; beyond that, cells come first.
BROADCAST_BYTES = 64 << 20
#: Scores of vectors against centres that are held at a time.
_SCORES = 1 << 20


def sample_centers(vectors: DataFrame, m: int, seed: int = 42, method: str = "hash") -> DataFrame:
    """(bucket_id, center): ``m`` vectors as centres - by keyed hash of the id (uniform, the same everywhere), the first ids (prefix),
    or each vector by itself with the chance that gives ``m`` on average (bernoulli: a filter, without a sort)."""
    digest = F.md5(F.concat(F.lit(f"{seed}:"), F.col("vec_id").cast("string")))
    out = vectors.select(F.col("vec_id").alias("bucket_id"), F.col("v").alias("center"), "vec_id")
    if method == "bernoulli":
        share = m / max(1, vectors.count())
        return out.where(F.conv(F.substring(digest, 1, 8), 16, 10).cast("long") < share * 2.0**32).drop("vec_id")
    if method not in ("hash", "prefix"):
        raise ValueError("method is hash, prefix or bernoulli")
    return out.orderBy(digest if method == "hash" else F.col("vec_id"), "vec_id").limit(m).drop("vec_id")


def matrix(col: pa.Array) -> np.ndarray:
    """Rows of an array<double> column as a matrix."""
    flat = col.flatten().to_numpy(zero_copy_only=False)
    return flat.reshape(len(col), -1) if len(col) else np.zeros((0, 1))


def nearest(x: np.ndarray, centers: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Nearest centre (of equal ones the first) and distance, by one matrix product and an exact look at close rivals."""
    step = max(1, _SCORES // max(1, len(centers)))
    if len(x) > step:  # so that scores take a bounded part of the memory, however many centres there are
        parts = [nearest(x[a : a + step], centers) for a in range(0, len(x), step)]
        return np.concatenate([p[0] for p in parts]), np.concatenate([p[1] for p in parts])
    score = x @ (-2 * centers).T
    score += (centers * centers).sum(axis=1)
    at = score.argmin(axis=1)
    best = np.take_along_axis(score, at[:, None], axis=1)
    close = score <= best + 1e-9 * (1 + np.abs(best))
    for i in np.flatnonzero(np.count_nonzero(close, axis=1) > 1) if np.count_nonzero(close) > len(x) else ():
        rivals = np.flatnonzero(close[i])
        at[i] = rivals[np.argmin(((x[i] - centers[rivals]) ** 2).sum(axis=1))]
    return at, np.sqrt(((x - centers[at]) ** 2).sum(axis=1))


def assign_buckets(vectors: DataFrame, centers: DataFrame, index: str = "auto", probe: int = 3, degree: int = 16, beam: int = 48) -> DataFrame:
    """``vectors`` with bucket_id and d_center.

    brute compares with all centres, which are sent to the tasks (their size is checked); graph sends a proximity graph
    of as many centres, and a vector sees about ``beam`` x ``degree`` of them; two_level sends about
    sqrt(m) coarse centres only, moves vectors and centres (each to its ``probe`` nearest cells) to cells, and looks there.
    """
    kept = list(vectors.columns)
    size = centers.select(F.count(F.lit(1)).alias("m"), F.coalesce(F.max(F.size("center")), F.lit(0)).alias("d")).first()
    fits = size["m"] * size["d"] * 8 <= BROADCAST_BYTES
    if index == "auto":
        index = "brute" if fits else "two_level"
    if index in ("brute", "graph"):
        if not fits:
            raise ValueError("too many centres to send to every task")
        return _assign_all(vectors, centers, kept) if index == "brute" else _assign_by_graph(vectors, centers, kept, degree, beam)
    if index != "two_level":
        raise ValueError("index is auto, brute, graph or two_level")
    coarse = centers.orderBy(F.xxhash64("bucket_id"), "bucket_id").limit(max(1, round(size["m"] ** 0.5)))
    celled = _assign_all(vectors, coarse, kept).withColumnRenamed("bucket_id", "cell").drop("d_center")
    near = _nearest_cells(centers, coarse, probe)
    pooled = near.groupBy("cell").agg(F.array_sort(F.collect_list(F.struct("bucket_id", "center"))).alias("pool"))  # about probe x sqrt(m) centres
    place = kept.index("v")

    def within(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            cell = batch.column(len(kept)).to_numpy()
            x = matrix(batch.column(place))
            ids, dist = np.zeros(len(x), np.int64), np.zeros(len(x))
            for c in np.unique(cell):
                rows = np.flatnonzero(cell == c)
                pool = batch.column(len(kept) + 1)[int(rows[0])].values
                at, d = nearest(x[rows], matrix(pool.field(1)))
                ids[rows], dist[rows] = pool.field(0).to_numpy()[at], d
            yield pa.RecordBatch.from_arrays([*batch.columns[: len(kept)], pa.array(ids), pa.array(dist)], names=[*kept, "bucket_id", "d_center"])

    schema = vectors.selectExpr("*", "0L AS bucket_id", "0D AS d_center").schema
    return celled.join(pooled, "cell").select(*kept, "cell", "pool").mapInArrow(within, schema)


def _assign_all(vectors: DataFrame, centers: DataFrame, kept: list[str]) -> DataFrame:
    rows = centers.orderBy("bucket_id").collect()  # within BROADCAST_BYTES
    ids = np.array([r["bucket_id"] for r in rows], dtype=np.int64)
    held = np.array([r["center"] for r in rows], dtype=float)
    place = kept.index("v")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            at, d = nearest(matrix(batch.column(place)), held) if batch.num_rows else (np.zeros(0, int), np.zeros(0))
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(ids[at]), pa.array(d)], names=[*kept, "bucket_id", "d_center"])

    return vectors.mapInArrow(run, vectors.selectExpr("*", "0L AS bucket_id", "0D AS d_center").schema)


def _assign_by_graph(vectors: DataFrame, centers: DataFrame, kept: list[str], degree: int, beam: int) -> DataFrame:
    rows = centers.orderBy("bucket_id").collect()  # within BROADCAST_BYTES
    ids = np.array([r["bucket_id"] for r in rows], dtype=np.int64)
    sent = vectors.sparkSession.sparkContext.broadcast(ProximityGraph(np.array([r["center"] for r in rows], dtype=float), degree)) if rows else None
    place = kept.index("v")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            x = matrix(batch.column(place))
            at = np.array([sent.value.search(q, 1, beam)[0][0] for q in x], dtype=int) if batch.num_rows else np.zeros(0, int)
            d = np.sqrt(((x - sent.value.x[at]) ** 2).sum(axis=1)) if batch.num_rows else np.zeros(0)
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(ids[at]), pa.array(d)], names=[*kept, "bucket_id", "d_center"])

    return vectors.mapInArrow(run, vectors.selectExpr("*", "0L AS bucket_id", "0D AS d_center").schema)


def _nearest_cells(centers: DataFrame, coarse: DataFrame, probe: int) -> DataFrame:
    rows = coarse.orderBy("bucket_id").collect()  # about sqrt(m)
    ids, held = np.array([r["bucket_id"] for r in rows], dtype=np.int64), np.array([r["center"] for r in rows], dtype=float)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            x = matrix(batch.column(1))
            p = min(probe, len(ids))
            at = np.argpartition((held * held).sum(axis=1)[None, :] - 2 * (x @ held.T), p - 1, axis=1)[:, :p]
            take = pa.array(np.repeat(np.arange(len(x)), p))
            yield pa.RecordBatch.from_arrays([batch.column(0).take(take), batch.column(1).take(take), pa.array(ids[at].reshape(-1))], names=["bucket_id", "center", "cell"])

    return centers.select("bucket_id", "center").mapInArrow(run, "bucket_id long, center array<double>, cell long")


def bucket_stats(assigned: DataFrame, centers: DataFrame) -> DataFrame:
    """(bucket_id, center, radius, mean_radius, n, bytes) of the buckets that have members."""
    stats = assigned.groupBy("bucket_id").agg(F.max("d_center").alias("radius"), F.avg("d_center").alias("mean_radius"), F.count(F.lit(1)).alias("n"), F.sum(F.size("v") * F.lit(4)).cast("long").alias("bytes"))
    return centers.join(stats, "bucket_id")


def agreement(a: DataFrame, b: DataFrame) -> Column:
    """Share of vectors that two assignments put into one bucket, as a one-row frame."""
    return a.select("vec_id", F.col("bucket_id").alias("x")).join(b.select("vec_id", F.col("bucket_id").alias("y")), "vec_id").agg(F.avg((F.col("x") == F.col("y")).cast("double")).alias("agreement"))


def blocks(assigned: DataFrame, block_rows: int = 4096) -> DataFrame:
    """(bucket_id, block_no, ids, mat: doubles row by row): members of a bucket side by side, large buckets in several blocks of about ``block_rows``, dealt by hash."""
    size = assigned.groupBy("bucket_id").agg(F.ceil(F.count(F.lit(1)) / block_rows).cast("int").alias("parts"))
    dealt = assigned.join(size, "bucket_id").withColumn("block_no", F.pmod(F.xxhash64("vec_id"), F.col("parts")).cast("int"))

    def pack(table: pa.Table) -> pa.Table:
        table = table.sort_by("vec_id")
        x = matrix(table["v"].combine_chunks())
        return pa.table({"bucket_id": table["bucket_id"][:1], "block_no": table["block_no"][:1], "ids": pa.array([table["vec_id"].to_numpy()], pa.list_(pa.int64())), "mat": pa.array([x.tobytes()], pa.binary())})

    return dealt.select("bucket_id", "block_no", "vec_id", "v").groupBy("bucket_id", "block_no").applyInArrow(pack, "bucket_id long, block_no int, ids array<long>, mat binary")


def kmeans_centers(vectors: DataFrame, m: int, iterations: int = 5, seed: int = 42) -> DataFrame:
    """(bucket_id, center): sampled centres moved to the means of their members, one scan of the data for each iteration.

    Tasks send one sum per centre they met; a centre without members stays where it was. The centres' size is checked as in ``assign_buckets``.
    """
    centers = sample_centers(vectors, m, seed)
    for _ in range(iterations):
        assigned = assign_buckets(vectors.select("vec_id", "v"), centers, "brute")

        def sums(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            total: dict[int, np.ndarray] = {}
            n: dict[int, int] = {}
            for batch in batches:
                x, b = matrix(batch.column(0)), batch.column(1).to_numpy()
                for c in np.unique(b).tolist():
                    rows = x[b == c]
                    total[c] = total.get(c, 0) + rows.sum(axis=0)
                    n[c] = n.get(c, 0) + len(rows)
            keys = list(total)
            yield pa.RecordBatch.from_arrays([pa.array(keys, pa.int64()), pa.array([n[k] for k in keys], pa.int64()), pa.array([total[k] for k in keys], pa.list_(pa.float64()))], names=["bucket_id", "n", "total"])

        part = assigned.select("v", "bucket_id").mapInArrow(sums, "bucket_id long, n long, total array<double>")
        size = part.groupBy("bucket_id").agg(F.sum("n").alias("n"))
        place = part.select("bucket_id", F.posexplode("total").alias("p", "x")).groupBy("bucket_id", "p").agg(F.sum("x").alias("x"))
        mean = place.join(size, "bucket_id").groupBy("bucket_id").agg(F.transform(F.array_sort(F.collect_list(F.struct("p", (F.col("x") / F.col("n")).alias("c")))), lambda e: e["c"]).alias("mean"))
        rows = centers.join(mean, "bucket_id", "left").select("bucket_id", F.coalesce("mean", "center").alias("center")).collect()  # within BROADCAST_BYTES
        centers = vectors.sparkSession.createDataFrame(rows, "bucket_id long, center array<double>")
    return centers
