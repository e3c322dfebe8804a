"""Similarity joins by buckets: one set, two sets, and with attribute filters."""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass, replace
from functools import reduce
from operator import add

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..config import JoinConfig
from ..functions.vectors import close_pairs, count_close, l2, normalize
from ..plans import graph, orchestrate, two_sets
from ..sources.storage import stored
from .bucketize import BROADCAST_BYTES, assign_buckets, blocks, bucket_stats, matrix, sample_centers

PAIRS = "id_lo long, id_hi long, dist double"
#: So many edges at most are ordered in one piece; a larger graph is cut by the first bucket's hash.
ORDER_EDGES = 2_000_000
#: Values of a vector that the native executor takes as columns, and rows of a side for each part of its bucket pairs.
NATIVE_WIDTH, NATIVE_PART = 128, 1024


@dataclass
class Layout:
    """Vectors in buckets; doesn't depend on distance or recall, so joins of several settings share one."""

    vectors: DataFrame
    assigned: DataFrame
    buckets: DataFrame
    d: int
    n: int
    nearest: bool = True  # whether every vector is in the bucket of its nearest centre


def build_layout(vectors: DataFrame, cfg: JoinConfig) -> Layout:
    if cfg.metric == "cosine":
        vectors = vectors.withColumn("v", normalize("v"))
    size = vectors.agg(F.count(F.lit(1)), F.max(F.size("v"))).first()
    m = cfg.centers or max(1, round(size[0] * cfg.centers_fraction))
    centers = sample_centers(vectors.select("vec_id", "v"), m, cfg.seed)
    assigned = stored(assign_buckets(vectors, centers))
    exact = m * (size[1] or 1) * 8 <= BROADCAST_BYTES  # beyond that assignment goes by cells
    return Layout(vectors, assigned, stored(bucket_stats(assigned, centers)), size[1] or 1, size[0], exact)


def with_quantile(layout: Layout, q: float) -> DataFrame:
    """The buckets with q_radius: the distance to the centre that a share ``q`` of a bucket's members doesn't exceed (interpolated)."""
    return layout.buckets.join(layout.assigned.groupBy("bucket_id").agg(F.percentile("d_center", F.lit(q)).alias("q_radius")), "bucket_id")


def _unpack(ids: pa.Array, mats: pa.Array, row: int) -> tuple[np.ndarray, np.ndarray]:
    i = ids[row].values.to_numpy()
    return i, np.frombuffer(mats[row].as_py(), np.float64).reshape(len(i), -1)


def _pairs(batch_ids: list, eps: float) -> pa.RecordBatch:
    lo, hi, dist = [], [], []
    for a, x, b, y in batch_ids:
        p, q, d = close_pairs(x, y, eps)
        left, right = a[p], (a if b is None else b)[q]
        lo.append(np.minimum(left, right))
        hi.append(np.maximum(left, right))
        dist.append(d)
    join = lambda parts, kind: pa.array(np.concatenate(parts) if parts else np.zeros(0), kind)
    return pa.RecordBatch.from_arrays([join(lo, pa.int64()), join(hi, pa.int64()), join(dist, pa.float64())], names=["id_lo", "id_hi", "dist"])


def near_border(x: np.ndarray, own: np.ndarray, other: np.ndarray, eps: float) -> np.ndarray:
    """Rows within ``eps`` of the plane halfway between two centres; the rest of a bucket of nearest vectors can't match the other bucket."""
    apart = float(np.sqrt(((own - other) ** 2).sum()))
    if apart == 0:
        return np.ones(len(x), bool)
    beyond = ((x - other) ** 2).sum(axis=1) - ((x - own) ** 2).sum(axis=1)
    return beyond <= 2 * apart * eps * (1 + 1e-9) + 1e-9


def execute_edge_join(layout: Layout, edges: DataFrame, cfg: JoinConfig) -> DataFrame:
    """Blocks meet by two joins on the bucket ids; each pair of blocks is one matrix product."""
    stored = blocks(layout.assigned.select("bucket_id", "vec_id", "v"), cfg.block_rows)
    a = stored.select(F.col("bucket_id").alias("i"), F.col("block_no").alias("bi"), F.col("ids").alias("ia"), F.col("mat").alias("ma"))
    b = stored.select(F.col("bucket_id").alias("j"), F.col("block_no").alias("bj"), F.col("ids").alias("ib"), F.col("mat").alias("mb"))
    none = F.lit(None).cast("array<double>")
    if cfg.margin_filter and layout.nearest:  # the margin holds for nearest centres only
        center = layout.buckets.select("bucket_id", "center")
        edges = edges.join(center.select(F.col("bucket_id").alias("i"), F.col("center").alias("ci")), "i").join(center.select(F.col("bucket_id").alias("j"), F.col("center").alias("cj")), "j")
    else:
        edges = edges.select("i", "j", none.alias("ci"), none.alias("cj"))
    across = edges.select("i", "j", "ci", "cj").join(a, "i").join(b, "j").select("ia", "ma", "ib", "mb", "ci", "cj")
    within = a.join(b, (F.col("i") == F.col("j")) & (F.col("bi") < F.col("bj"))).select("ia", "ma", "ib", "mb", none.alias("ci"), none.alias("cj"))
    alone = a.select("ia", "ma", F.lit(None).cast("array<long>").alias("ib"), F.lit(None).cast("binary").alias("mb"), none.alias("ci"), none.alias("cj"))
    eps = cfg.distance

    def verify(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for r in range(batch.num_rows):
                ia, ma = _unpack(batch.column(0), batch.column(1), r)
                ib, mb = _unpack(batch.column(2), batch.column(3), r) if batch.column(2)[r].is_valid else (None, None)
                if batch.column(4)[r].is_valid:
                    ci, cj = batch.column(4)[r].values.to_numpy(), batch.column(5)[r].values.to_numpy()
                    near_j, near_i = near_border(ma, ci, cj, eps), near_border(mb, cj, ci, eps)
                    ia, ma, ib, mb = ia[near_j], ma[near_j], ib[near_i], mb[near_i]
                yield _pairs([(ia, ma, ib, mb)], eps)

    return across.union(within).union(alone).mapInArrow(verify, PAIRS)


def execute_native(layout: Layout, edges: DataFrame, cfg: JoinConfig) -> DataFrame:
    """One plan of built-in expressions: vectors meet on bucket pairs, row by row.

    A vector's values are columns of their own up to NATIVE_WIDTH, so that the distance is compiled code; the left side of a
    bucket pair is dealt to parts by hash, as there may be fewer bucket pairs than cores.
    """
    parts = max(1, -(-layout.n // NATIVE_PART))
    wide = layout.d <= NATIVE_WIDTH
    # as_vectors let no null through
    values = lambda side: [F.coalesce(F.get("v", F.lit(k)), F.lit(0.0)).alias(f"{side}{k}") for k in range(layout.d)] if wide else [F.col("v").alias(side)]
    own = layout.buckets.select(F.col("bucket_id").alias("i"), F.col("bucket_id").alias("j"))
    a = layout.assigned.select(F.col("bucket_id").alias("i"), F.col("vec_id").alias("x"), F.pmod(F.xxhash64("vec_id"), F.lit(parts)).cast("int").alias("part"), *values("a"))
    b = layout.assigned.select(F.col("bucket_id").alias("j"), F.col("vec_id").alias("y"), F.explode(F.sequence(F.lit(0), F.lit(parts - 1))).alias("part"), *values("b"))
    met = edges.select("i", "j").union(own).join(a, "i").join(b, ["j", "part"]).where((F.col("i") != F.col("j")) | (F.col("x") < F.col("y")))
    if wide:
        dist = F.sqrt(reduce(add, ((F.col(f"a{k}") - F.col(f"b{k}")) * (F.col(f"a{k}") - F.col(f"b{k}")) for k in range(layout.d)), F.lit(0.0)))
    else:
        dist = l2("a", "b")
    return met.select(F.least("x", "y").alias("id_lo"), F.greatest("x", "y").alias("id_hi"), dist.alias("dist")).where(F.col("dist") <= cfg.distance)


def memory_slots(buckets: DataFrame, cfg: JoinConfig) -> int:
    """Buckets that one task may hold: ``memory_fraction`` of all, but no more than fit ``task_bytes`` in doubles at their mean size."""
    n, size = buckets.agg(F.count(F.lit(1)), F.coalesce(F.avg("bytes"), F.lit(0.0))).first()
    return max(2, min(round(n * cfg.memory_fraction), int(cfg.task_bytes // max(1.0, 2 * size))))


def plan_segments(edges: DataFrame, buckets: DataFrame, cfg: JoinConfig) -> DataFrame:
    """(seg, seq, i, j) in planned order, tasks of a bucket with itself among them.

    The graph is cut into parts by the hash of the smaller bucket so that each has about ORDER_EDGES edges; each part is ordered on its own.
    """
    counts = edges.count()
    parts = max(1, -(-counts // ORDER_EDGES))
    slots = memory_slots(buckets, cfg)
    order, every = cfg.order, edges.select("i", "j").union(buckets.select(F.col("bucket_id").alias("i"), F.col("bucket_id").alias("j")))
    cut = every.withColumn("part", F.pmod(F.xxhash64("i"), F.lit(parts)).cast("int"))

    def plan(table: pa.Table) -> pa.Table:
        both = list(zip(table["i"].to_pylist(), table["j"].to_pylist(), strict=True))
        pairs = [e for e in both if e[0] != e[1]]
        tasks = orchestrate.tasks_in_order(pairs, orchestrate.order_nodes(pairs, slots, order)) if pairs else []
        alone = {e[0] for e in both if e[0] == e[1]}
        full = []
        for a, b in tasks:
            full += [(x, x) for x in (a, b) if x in alone]
            alone -= {a, b}
            full.append((a, b))
        full += [(x, x) for x in sorted(alone)]
        part = int(table["part"][0].as_py())
        return pa.table({"seg": pa.array([part * (1 << 32) + s for s in orchestrate.segments(full, slots)], pa.int64()), "seq": pa.array(range(len(full)), pa.int64()), "i": pa.array([e[0] for e in full], pa.int64()), "j": pa.array([e[1] for e in full], pa.int64())})

    return cut.groupBy("part").applyInArrow(plan, "seg long, seq long, i long, j long")


def execute_segment(layout: Layout, edges: DataFrame, cfg: JoinConfig, counts: bool = False) -> DataFrame:
    """Each segment of the planned order is one task that receives each of its buckets once. With ``counts`` it tells how many pairs there are (n) instead of the pairs."""
    tasks = plan_segments(edges, layout.buckets, cfg)
    stored = blocks(layout.assigned.select("bucket_id", "vec_id", "v"), cfg.block_rows)
    need = tasks.select("seg", F.explode(F.array("i", "j")).alias("bucket_id")).distinct().join(stored, "bucket_id").select(F.col("seg").alias("for_seg"), "bucket_id", "ids", "mat")
    eps = cfg.distance

    def run(left: pa.Table, right: pa.Table) -> pa.Table:
        held: dict[int, list[tuple[np.ndarray, np.ndarray]]] = {}
        ids, mats = right["ids"].combine_chunks(), right["mat"].combine_chunks()
        for r, b in enumerate(right["bucket_id"].to_pylist()):
            held.setdefault(b, []).append(_unpack(ids, mats, r))
        work = []
        for i, j in zip(left["i"].to_pylist(), left["j"].to_pylist(), strict=True):
            a, b = held.get(i, []), held.get(j, [])  # a filter may have emptied a bucket
            if i == j:
                work += [(*x, None, None) for x in a] + [(*a[p], *a[q]) for p in range(len(a)) for q in range(p + 1, len(a))]
            else:
                work += [(*x, *y) for x in a for y in b]
        if counts:
            return pa.table({"n": pa.array([sum(count_close(x, y, eps) for _, x, _, y in work)], pa.int64())})
        return pa.Table.from_batches([_pairs(work, eps)])

    return tasks.select("seg", "seq", "i", "j").groupBy("seg").cogroup(need.groupBy("for_seg")).applyInArrow(run, "n long" if counts else PAIRS)


EXECUTORS = {"edge_join": execute_edge_join, "native": execute_native, "segment": execute_segment}


def self_join(vectors: DataFrame, cfg: JoinConfig, layout: Layout | None = None, where: Column | None = None, symmetric: bool = False) -> DataFrame:
    """(id_lo, id_hi, dist) of pairs within the distance; ``where`` filters vectors by their attributes before any distance.

    The margin filter works on single pairs of blocks and goes with the edge join, whatever ``cfg.executor`` says.
    """
    layout = layout or build_layout(vectors, cfg)
    if cfg.radius_mode == "quantile_plus_eps" and "q_radius" not in layout.buckets.columns:
        layout = replace(layout, buckets=with_quantile(layout, cfg.radius_quantile))
    edges = graph.bucket_graph(layout.buckets, cfg, layout.d)
    if where is not None:
        layout = replace(layout, assigned=layout.assigned.where(where))
    out = EXECUTORS["edge_join" if cfg.margin_filter else cfg.executor](layout, edges, cfg)
    if symmetric:
        out = out.union(out.select(F.col("id_hi").alias("id_lo"), F.col("id_lo").alias("id_hi"), "dist"))
    return out


def join_count(vectors: DataFrame, cfg: JoinConfig, layout: Layout | None = None) -> DataFrame:
    """One row n: the number of pairs that ``self_join`` finds by segments, every distance computed and no pair held."""
    layout = layout or build_layout(vectors, cfg)
    out = execute_segment(layout, graph.bucket_graph(layout.buckets, cfg, layout.d), cfg, counts=True)
    return out.agg(F.coalesce(F.sum("n"), F.lit(0)).alias("n"))


def calibrate_radius(layout: Layout, cfg: JoinConfig, sample: int = 500, steps: int = 8) -> JoinConfig:
    """``cfg`` with the smallest share of the bucket radius, by halving, at which sampled vectors keep ``recall`` of their true partners.

    The partners of the ``sample`` vectors of smallest keyed hash are found once among all vectors and counted by pairs of buckets; a step compares counts only.
    """
    asked = layout.assigned.orderBy(F.md5(F.concat(F.lit(f"{cfg.seed}#"), F.col("vec_id").cast("string"))), "vec_id").limit(sample).select("vec_id", "bucket_id", "v").collect()  # a parameter bounds it
    if not asked:
        return replace(cfg, radius_mode="calibrated", radius_share=1.0)
    ids, homes, held = np.array([r[0] for r in asked]), np.array([r[1] for r in asked], np.int64), np.array([r[2] for r in asked], dtype=float)
    eps = cfg.distance

    def meet(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            p, q, _ = close_pairs(matrix(batch.column(2)), held, eps)
            other = batch.column(0).to_numpy()[p] != ids[q]
            here, there = batch.column(1).to_numpy()[p][other], homes[q][other]
            yield pa.RecordBatch.from_arrays([pa.array(np.minimum(here, there), pa.int64()), pa.array(np.maximum(here, there), pa.int64())], names=["i", "j"])

    counts = layout.assigned.select("vec_id", "bucket_id", "v").mapInArrow(meet, "i long, j long").groupBy("i", "j").agg(F.count(F.lit(1)).alias("n")).persist()
    total, own = counts.agg(F.coalesce(F.sum("n"), F.lit(0)), F.coalesce(F.sum(F.when(F.col("i") == F.col("j"), F.col("n"))), F.lit(0))).first()

    def kept(share: float) -> float:
        edges = graph.bucket_graph(layout.buckets, replace(cfg, radius_mode="calibrated", radius_share=share), layout.d)
        return (own + (counts.join(edges.select("i", "j"), ["i", "j"]).agg(F.coalesce(F.sum("n"), F.lit(0))).first()[0])) / total

    low, high = 0.0, 1.0
    if total == 0 or kept(0.0) >= cfg.recall:
        high = 0.0
    for _ in range(steps if high else 0):
        middle = (low + high) / 2
        low, high = (low, middle) if kept(middle) >= cfg.recall else (middle, high)
    counts.unpersist()
    return replace(cfg, radius_mode="calibrated", radius_share=high)


def cross_graph(a: Layout, b: Layout, cfg: JoinConfig) -> DataFrame:
    """(i, j) of the buckets of two layouts that may hold pairs within the distance, pruned as ``cfg`` says."""
    left = a.buckets.select(F.col("bucket_id").alias("i"), F.col("center").alias("ci"), F.col("radius").alias("r_i"), F.col("mean_radius").alias("m_i"))
    right = b.buckets.select(F.col("bucket_id").alias("j"), F.col("center").alias("cj"), F.col("radius").alias("r_j"), F.col("mean_radius").alias("m_j"))
    cand = graph.near_pairs(left, right, cfg.distance)
    if not cfg.prune or a.d < 2:
        return cand.select("i", "j")
    mine = graph.prune_edges(cand.select("i", "j", "center_dist", "r_i", "m_i"), cfg, a.d).select("i", "j")
    theirs = graph.prune_edges(cand.select(F.col("j").alias("i"), F.col("i").alias("j"), "center_dist", F.col("r_j").alias("r_i"), F.col("m_j").alias("m_i")), cfg, a.d).select(F.col("j").alias("i"), F.col("i").alias("j"))
    return mine.union(theirs).distinct() if cfg.edge_merge == "union" else mine.intersect(theirs)


CROSS = "x_id long, y_id long, dist double"


def _met(ia: np.ndarray, ma: np.ndarray, ib: np.ndarray, mb: np.ndarray, eps: float) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    p, q, d = close_pairs(ma, mb, eps)
    return ia[p], ib[q], d


def cross_join(x: DataFrame, y: DataFrame, cfg: JoinConfig, streamed: str | None = None) -> DataFrame:
    """(x_id, y_id, dist) of pairs of two sets within the distance: separate buckets, and a graph between them.

    ``streamed`` is the side whose buckets are taken in order while those of the other are cached: larger, smaller,
    or none, where blocks meet by two joins instead.
    """
    a, b = build_layout(x, cfg), build_layout(y, cfg)
    edges = cross_graph(a, b, cfg)
    eps = cfg.distance
    if streamed is not None:
        return _cross_in_order(a, b, edges, cfg, streamed_side(a, b, streamed))
    sa = blocks(a.assigned.select("bucket_id", "vec_id", "v"), cfg.block_rows).select(F.col("bucket_id").alias("i"), F.col("ids").alias("ia"), F.col("mat").alias("ma"))
    sb = blocks(b.assigned.select("bucket_id", "vec_id", "v"), cfg.block_rows).select(F.col("bucket_id").alias("j"), F.col("ids").alias("ib"), F.col("mat").alias("mb"))

    def verify(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for r in range(batch.num_rows):
                found = _met(*_unpack(batch.column(0), batch.column(1), r), *_unpack(batch.column(2), batch.column(3), r), eps)
                yield pa.RecordBatch.from_arrays([pa.array(c) for c in found], names=["x_id", "y_id", "dist"])

    return edges.join(sa, "i").join(sb, "j").select("ia", "ma", "ib", "mb").mapInArrow(verify, CROSS)


def streamed_side(a: Layout, b: Layout, streamed: str) -> int:
    """0 if the left set is the ``larger`` or ``smaller`` one as asked, else 1."""
    if streamed not in ("larger", "smaller"):
        raise ValueError("streamed is larger or smaller")
    return int((a.n < b.n) == (streamed == "larger"))


def plan_two_sets(edges: DataFrame, buckets: DataFrame, cfg: JoinConfig, side: int) -> DataFrame:
    """(seg, seq, i, j): tasks in planned order, cut into runs that fit one task. A graph of over ORDER_EDGES edges is cut by the hash of the streamed bucket."""
    parts = max(1, -(-edges.count() // ORDER_EDGES))
    slots, order = memory_slots(buckets, cfg), cfg.order

    def plan(table: pa.Table) -> pa.Table:
        tasks = two_sets.two_set_tasks(list(zip(table["i"].to_pylist(), table["j"].to_pylist(), strict=True)), slots, side, order)
        part = table["part"][0].as_py()
        return pa.table({"seg": pa.array([part * (1 << 32) + s for s in two_sets.two_set_segments(tasks, slots)], pa.int64()), "seq": pa.array(range(len(tasks)), pa.int64()), "i": pa.array([t[0] for t in tasks], pa.int64()), "j": pa.array([t[1] for t in tasks], pa.int64())})

    return edges.select("i", "j", F.pmod(F.xxhash64("j" if side else "i"), F.lit(parts)).cast("int").alias("part")).groupBy("part").applyInArrow(plan, "seg long, seq long, i long, j long")


def _cross_in_order(a: Layout, b: Layout, edges: DataFrame, cfg: JoinConfig, side: int) -> DataFrame:
    tasks = stored(plan_two_sets(edges, a.buckets.select("bucket_id", "bytes").union(b.buckets.select("bucket_id", "bytes")), cfg, side))
    held_by = []
    for n, (layout, at) in enumerate(((a, "i"), (b, "j"))):
        need = tasks.select("seg", F.col(at).alias("bucket_id")).distinct().join(blocks(layout.assigned.select("bucket_id", "vec_id", "v"), cfg.block_rows), "bucket_id")
        held_by.append(need.select(F.col("seg").alias("for_seg"), F.lit(n).alias("side"), "bucket_id", "ids", "mat"))
    eps = cfg.distance

    def run(left: pa.Table, right: pa.Table) -> pa.Table:
        held: dict[tuple[int, int], list[tuple[np.ndarray, np.ndarray]]] = {}
        ids, mats = right["ids"].combine_chunks(), right["mat"].combine_chunks()
        for r, key in enumerate(zip(right["side"].to_pylist(), right["bucket_id"].to_pylist(), strict=True)):
            held.setdefault(key, []).append(_unpack(ids, mats, r))
        found = [_met(*p, *q, eps) for i, j in zip(left["i"].to_pylist(), left["j"].to_pylist(), strict=True) for p in held.get((0, i), []) for q in held.get((1, j), [])]
        found.append((np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0)))
        return pa.table({name: pa.array(np.concatenate(c), kind) for name, c, kind in zip(("x_id", "y_id", "dist"), zip(*found, strict=True), (pa.int64(), pa.int64(), pa.float64()), strict=True)})

    return tasks.groupBy("seg").cogroup(held_by[0].union(held_by[1]).groupBy("for_seg")).applyInArrow(run, CROSS)


def side_join(vectors: DataFrame, cfg: JoinConfig, one: Column, other: Column) -> DataFrame:
    """(id_lo, id_hi, dist) of pairs of which one vector meets the condition ``one`` and its partner ``other``; each set has buckets of its own."""
    met = cross_join(vectors.where(one), vectors.where(other), cfg).where("x_id <> y_id")
    return met.groupBy(F.least("x_id", "y_id").alias("id_lo"), F.greatest("x_id", "y_id").alias("id_hi")).agg(F.min("dist").alias("dist"))
