"""Bucket graph: candidate pairs, triangle test, probabilistic pruning, merging."""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..config import JoinConfig
from ..functions.vectors import l2
from ..operators.bucketize import BROADCAST_BYTES, assign_buckets, matrix

#: Squared distances of centres that a task holds at a time.
_HELD = 1 << 20


def mu(d: int) -> float:
    """Factor of the arc in the bound on a ball's part beyond a hyperplane, for dimension d of 2 or more."""
    if d < 2:
        raise ValueError("the bound needs two dimensions")
    return math.exp(math.lgamma((d - 1) / 2) - math.lgamma(d / 2)) / math.sqrt(math.pi)


def cap_share(x: float, d: int) -> float:
    """Exact part of a d-ball beyond a hyperplane at x radii from its centre (0 <= x <= 1), by integration."""
    grid = np.linspace(0.0, math.acos(min(max(x, 0.0), 1.0)), 2001)
    y = np.sin(grid) ** d
    area = float(((y[1:] + y[:-1]) / 2 * np.diff(grid)).sum())
    return area * math.exp(math.lgamma(d / 2 + 1) - math.lgamma((d + 1) / 2)) / math.sqrt(math.pi)


def _sides(buckets: DataFrame) -> tuple[DataFrame, DataFrame]:
    more = [F.col("q_radius").alias("q_i")] if "q_radius" in buckets.columns else []
    left = buckets.select(F.col("bucket_id").alias("i"), F.col("center").alias("ci"), F.col("radius").alias("r_i"), F.col("mean_radius").alias("m_i"), F.col("n").alias("n_i"), *more)
    return left, buckets.select(F.col("bucket_id").alias("j"), F.col("center").alias("cj"), F.col("radius").alias("r_j"), F.col("n").alias("n_j"))


def candidates(buckets: DataFrame, neighbor_limit: int | None = None) -> DataFrame:
    """(i, j, center_dist, r_i, r_j, m_i, n_i, n_j) of ordered pairs of buckets; with a limit, just the nearest ones of each."""
    left, right = _sides(buckets)
    out = left.join(right, F.col("i") != F.col("j")).withColumn("center_dist", l2("ci", "cj")).drop("ci", "cj")
    if neighbor_limit is not None:
        w = Window.partitionBy("i").orderBy("center_dist", "j")
        out = out.withColumn("rn", F.row_number().over(w)).where(F.col("rn") <= neighbor_limit).drop("rn")
    return out


def near_pairs(left: DataFrame, right: DataFrame, eps: float, cells: int | None = None) -> DataFrame:
    """``left`` (i, ci, r_i, ...) with ``right`` (j, cj, r_j, ...) where the balls come within ``eps``, and center_dist.

    Balls go to the nearest of about sqrt(m) centres; only cells whose own balls, grown over all their members, come
    within ``eps`` are opened, so just the cells (about m pairs) are compared each with each. No pair is lost.
    """
    size = left.count()
    picked = left.orderBy(F.xxhash64("i"), "i").limit(cells or max(1, math.ceil(size**0.5))).select(F.col("i").alias("bucket_id"), F.col("ci").alias("center"))
    a = assign_buckets(left.withColumnRenamed("ci", "v"), picked, "brute").withColumnsRenamed({"v": "ci", "bucket_id": "cell_i", "d_center": "d_i"})
    b = assign_buckets(right.withColumnRenamed("cj", "v"), picked, "brute").withColumnsRenamed({"v": "cj", "bucket_id": "cell_j", "d_center": "d_j"})
    wide = a.groupBy("cell_i").agg(F.max(F.col("d_i") + F.col("r_i")).alias("w_i")).join(picked.select(F.col("bucket_id").alias("cell_i"), F.col("center").alias("x")), "cell_i")
    deep = b.groupBy("cell_j").agg(F.max(F.col("d_j") + F.col("r_j")).alias("w_j")).join(picked.select(F.col("bucket_id").alias("cell_j"), F.col("center").alias("y")), "cell_j")
    apart = l2("x", "y") - F.col("w_i") - F.col("w_j")
    opened = wide.join(deep, apart <= F.lit(eps) + 1e-9 * (1 + F.col("w_i") + F.col("w_j"))).select("cell_i", "cell_j")
    met = a.drop("d_i").join(opened, "cell_i").join(b.drop("d_j"), "cell_j").withColumn("center_dist", l2("ci", "cj")).drop("ci", "cj", "cell_i", "cell_j")
    return met.where(F.col("center_dist") - F.col("r_i") - F.col("r_j") <= eps)


def triangle_edges(cand: DataFrame, eps: float) -> DataFrame:
    """Candidates whose balls come within ``eps`` of each other; no other pair can hold a match."""
    return cand.where(F.col("center_dist") - F.col("r_i") - F.col("r_j") <= eps)


def reach(cfg: JoinConfig, r: str = "r_i", m: str = "m_i", q: str = "q_i") -> Column:
    """Radius of the ball whose loss is estimated."""
    eps = F.lit(cfg.distance)
    if cfg.radius_mode == "quantile_plus_eps":
        return F.col(q) + eps
    return {"bucket_plus_eps": F.col(r) + eps, "mean_plus_eps": F.col(m) + eps, "eps": eps, "calibrated": eps + cfg.radius_share * F.col(r)}[cfg.radius_mode]


def prune_edges(edges: DataFrame, cfg: JoinConfig, d: int) -> DataFrame:
    """(i, j, ..., ratio, cum_loss): farthest partners go first, as long as their estimated loss sums below 1 - recall."""
    ratio = F.least(F.col("center_dist") / (2 * reach(cfg)), F.lit(1.0))
    term = F.acos("ratio") * (mu(d) if cfg.scale == "mu" else 1.0)
    if cfg.scale == "cap":
        table = F.array(*(F.lit(cap_share(k / 255, d)) for k in range(256)))
        low = F.least(F.floor(F.col("ratio") * 255), F.lit(254)).cast("int")
        part = F.col("ratio") * 255 - low
        term = F.element_at(table, low + 1) * (1 - part) + F.element_at(table, low + 2) * part
    w = Window.partitionBy("i").orderBy(F.col("center_dist").desc(), "j").rowsBetween(Window.unboundedPreceding, 0)
    summed = edges.withColumn("ratio", ratio).withColumn("cum_loss", F.sum(term).over(w))
    return summed.where((F.col("cum_loss") > 0) & (F.col("cum_loss") >= 1 - cfg.recall))


def estimated_loss(edges: DataFrame, cfg: JoinConfig, d: int) -> DataFrame:
    """(i, loss): estimated loss of each bucket by what ``prune_edges`` drops."""
    every = prune_edges(edges, JoinConfig(**{**cfg.__dict__, "recall": 1.0}), d)
    dropped = every.where(F.col("cum_loss") < 1 - cfg.recall).groupBy("i").agg(F.max("cum_loss").alias("loss"))
    return edges.select("i").distinct().join(dropped, "i", "left").select("i", F.coalesce("loss", F.lit(0.0)).alias("loss"))


def merge_edges(kept: DataFrame, how: str = "union") -> DataFrame:
    """(i, j, center_dist) with i < j: pairs that either bucket keeps, or both."""
    out = kept.groupBy(F.least("i", "j").alias("a"), F.greatest("i", "j").alias("b")).agg(F.max("center_dist").alias("center_dist"), F.count(F.lit(1)).alias("n"))
    return out.where("n = 2" if how == "intersection" else "n > 0").select(F.col("a").alias("i"), F.col("b").alias("j"), "center_dist")


def _partners(x: np.ndarray, r: np.ndarray, ids: np.ndarray, y: np.ndarray, s: np.ndarray, other: np.ndarray, eps: float) -> Iterator[tuple[int, np.ndarray, np.ndarray]]:
    """For each ball (x, r, ids): the rows of the other balls (y, s, other) within ``eps`` of it, and the distances of the centres."""
    ny = (y * y).sum(axis=1)
    step = max(1, _HELD // max(1, len(y)))
    for a in range(0, len(x), step):
        part = x[a : a + step]
        nx = (part * part).sum(axis=1)
        square = nx[:, None] + ny[None, :] - 2 * (part @ y.T)
        wide = r[a : a + step, None] + s[None, :] + eps
        error = 64 * np.finfo(float).eps * (x.shape[1] ** 0.5 + 1) * (nx.max(initial=0) + ny.max(initial=0) + float(wide.max(initial=0)) ** 2)
        near = square <= wide * wide + error
        for k in range(len(part)):
            at = np.flatnonzero(near[k])
            dist = np.sqrt(((part[k] - y[at]) ** 2).sum(axis=1))  # the same from either side
            ok = (dist - r[a + k] - s[at] <= eps) & (other[at] != ids[a + k])
            yield a + k, at[ok], dist[ok]


def graph_by_product(buckets: DataFrame, cfg: JoinConfig, d: int, size: int) -> DataFrame:
    """``bucket_graph`` of centres that fit every task: rows of centres meet all others as matrix products, and a first round tells
    each bucket's last partner that is dropped, so that a second one can tell the kept pairs without an exchange."""
    sides = buckets.select("bucket_id", "center", "radius", reach(cfg, "radius", "mean_radius", "q_radius").alias("reach"))
    held = sides.orderBy("bucket_id").toArrow().combine_chunks()  # within BROADCAST_BYTES
    ids, y = held["bucket_id"].to_numpy(), matrix(held["center"].combine_chunks()) if size else np.zeros((0, d))
    sent = buckets.sparkSession.sparkContext.broadcast((ids, y, held["radius"].to_numpy()))
    eps, prune, least = cfg.distance, cfg.prune and d > 1, 1 - cfg.recall
    factor = mu(d) if prune and cfg.scale == "mu" else 1.0
    dealt = sides.repartition(max(1, min(256, size * size >> 22)), "bucket_id") if size > 2048 else sides.coalesce(1)

    def rows(batch: pa.RecordBatch) -> Iterator[tuple[int, np.ndarray, np.ndarray]]:
        other, y, s = sent.value
        return _partners(matrix(batch.column(1)), batch.column(2).to_numpy(), batch.column(0).to_numpy(), y, s, other, eps)

    def cuts(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        other = sent.value[0]
        for batch in batches:
            far, first = np.full(batch.num_rows, -1.0), np.zeros(batch.num_rows, np.int64)
            wide = batch.column(3).to_numpy()
            for k, at, dist in rows(batch):
                order = np.lexsort((other[at], -dist))
                total = np.cumsum(np.arccos(np.minimum(dist[order] / (2 * wide[k]), 1.0)) * factor)
                kept = np.flatnonzero((total > 0) & (total >= least))
                if len(kept):
                    far[k], first[k] = dist[order[kept[0]]], other[at[order[kept[0]]]]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(far), pa.array(first)], names=["i", "far", "first"])

    cut = None
    if prune:
        told = dealt.mapInArrow(cuts, "i long, far double, first long").orderBy("i").toArrow()  # a row for each centre
        cut = buckets.sparkSession.sparkContext.broadcast((told["far"].to_numpy(), told["first"].to_numpy()))
    both = cfg.edge_merge == "intersection"

    def pairs(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        other = sent.value[0]
        for batch in batches:
            mine = batch.column(0).to_numpy()
            i, j, center_dist, n = [], [], [], 0
            for k, at, dist in rows(batch):
                keep = other[at] > mine[k]
                at, dist = at[keep], dist[keep]
                if cut is not None:
                    far, first = cut.value
                    own = int(np.searchsorted(other, mine[k]))
                    here = (dist < far[own]) | ((dist == far[own]) & (other[at] >= first[own]))
                    there = (dist < far[at]) | ((dist == far[at]) & (mine[k] >= first[at]))
                    keep = here & there if both else here | there
                    at, dist = at[keep], dist[keep]
                i.append(np.full(len(at), mine[k])), j.append(other[at]), center_dist.append(dist)
                n += len(at)
                if n >= 1 << 18:
                    yield _edge_rows(i, j, center_dist)
                    i, j, center_dist, n = [], [], [], 0
            yield _edge_rows(i, j, center_dist)

    return dealt.mapInArrow(pairs, "i long, j long, center_dist double")


def _edge_rows(i: list[np.ndarray], j: list[np.ndarray], dist: list[np.ndarray]) -> pa.RecordBatch:
    whole = [np.concatenate(c) if c else np.zeros(0) for c in (i, j, dist)]
    return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(whole, (pa.int64(), pa.int64(), pa.float64()), strict=True)], names=["i", "j", "center_dist"])


def bucket_graph(buckets: DataFrame, cfg: JoinConfig, d: int) -> DataFrame:
    if cfg.neighbor_limit is None and cfg.scale != "cap":
        size = buckets.count()
        if size * d * 8 <= BROADCAST_BYTES:
            return graph_by_product(buckets, cfg, d, size)
    if cfg.neighbor_limit is None:
        edges = near_pairs(*_sides(buckets), cfg.distance).where("i <> j")
    else:
        edges = triangle_edges(candidates(buckets, cfg.neighbor_limit), cfg.distance)
    return merge_edges(prune_edges(edges, cfg, d) if cfg.prune and d > 1 else edges, cfg.edge_merge)


def access_sequence(tasks: DataFrame) -> DataFrame:
    """(pos, bucket_id, next_use) of tasks (seq, i, j): two accesses each, with the next position that needs the same bucket."""
    acc = tasks.select((2 * F.col("seq")).alias("at"), F.posexplode(F.array("i", "j")).alias("side", "bucket_id")).select((F.col("at") + F.col("side")).cast("long").alias("pos"), "bucket_id")
    return acc.withColumn("next_use", F.lead("pos").over(Window.partitionBy("bucket_id").orderBy("pos")))


def id_order_tasks(edges: DataFrame) -> DataFrame:
    """Tasks grouped by the smaller bucket, in id order: (seq, i, j)."""
    ranged = edges.repartitionByRange("i", "j").sortWithinPartitions("i", "j").select("i", "j", F.spark_partition_id().alias("p"))
    local = ranged.withColumn("n", F.row_number().over(Window.partitionBy("p").orderBy("i", "j")))
    before = local.groupBy("p").agg(F.max("n").alias("size")).withColumn("base", F.coalesce(F.sum("size").over(Window.orderBy("p").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)))
    return local.join(before, "p").select((F.col("base") + F.col("n") - 1).alias("seq"), "i", "j")
