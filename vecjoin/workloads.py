"""Experiments: how time, work and recall of the joins move with each parameter. One frame for each experiment."""

from __future__ import annotations

import time
import uuid
from dataclasses import replace

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .config import JoinConfig
from .operators import apps, baselines, join, metrics, replay
from .plans import graph
from .sources import tables
from .sources.storage import folder, stored

EPS, RADIUS, CENTERS = 0.437245, "eps", 40
BASE = JoinConfig(eps=EPS, recall=0.9, centers=CENTERS, radius_mode=RADIUS, memory_fraction=0.2)


def _stored(spark: SparkSession, vectors: DataFrame, cfg: JoinConfig, **kind) -> replay.StoredLayout:
    return replay.write_layout(vectors, cfg, f"{folder(spark)}/layout-{uuid.uuid4().hex}", **kind)


def _work(counts: DataFrame) -> DataFrame:
    names = ("tasks", "loads", "hits", "reads", "read_bytes", "page_bytes", "distances", "pairs")
    return counts.agg(*(F.sum(n).alias(n) for n in names))


def _sweep(spark: SparkSession, rows: list[tuple[str, DataFrame]], name: str) -> DataFrame:
    out = None
    for label, df in rows:
        one = df.select(F.lit(label).alias(name), "*")
        out = one if out is None else out.unionByName(one)
    return out


def recall_sweep(spark: SparkSession, d: str) -> DataFrame:
    """Recall, pairs compared and edges for each requested recall."""
    v = stored(tables.planted(spark, d))
    layout = join.build_layout(v, BASE)
    exact = stored(baselines.exact_count(v, EPS))
    rows = []
    for wanted in (0.8, 0.9, 0.95, 0.99, 1.0):
        cfg = replace(BASE, recall=wanted)
        cand = metrics.candidate_counts(graph.bucket_graph(layout.buckets, cfg, layout.d), layout.buckets)
        rows.append((str(wanted), metrics.counted_recall(exact, join.join_count(v, cfg, layout)).crossJoin(cand)))
    return _sweep(spark, rows, "wanted")


def memory_sweep(spark: SparkSession, d: str) -> DataFrame:
    """Loads and hits of the replay for each share of the data that fits in memory."""
    layout = _stored(spark, stored(tables.planted(spark, d)), BASE)
    return _sweep(spark, [(str(share), _work(replay.replay_counts(layout, replace(BASE, memory_fraction=share)))) for share in (0.05, 0.1, 0.15, 0.2, 0.5)], "memory")


def distance_sweep(spark: SparkSession, d: str) -> DataFrame:
    """Work with and without pruning for distances that give 1, 2, 5 and 10 neighbours on average."""
    v = stored(tables.planted(spark, d))
    layout = join.build_layout(v, BASE)
    rows = []
    for k in (1, 2, 5, 10):
        eps = apps.calibrate_eps(v, k).first()[0]
        for prune in (True, False):
            cfg = replace(BASE, eps=eps, prune=prune)
            cand = metrics.candidate_counts(graph.bucket_graph(layout.buckets, cfg, layout.d), layout.buckets)
            rows.append((str(k), cand.select(F.lit(prune).alias("pruned"), F.round(F.lit(eps), 6).alias("eps"), "*")))
    return _sweep(spark, rows, "neighbors")


def bucket_sweep(spark: SparkSession, d: str) -> DataFrame:
    """Pairs compared, distances to centres and edges for numbers of buckets between 0.1 % and 10 % of the vectors."""
    v = stored(tables.planted(spark, d))
    n, rows = v.count(), []
    for share in (0.001, 0.005, 0.01, 0.05, 0.1):
        cfg = replace(BASE, centers=max(2, round(n * share)))
        layout = join.build_layout(v, cfg)
        rows.append((str(share), metrics.candidate_counts(graph.bucket_graph(layout.buckets, cfg, layout.d), layout.buckets).withColumn("center_distances", F.lit(n) * F.col("buckets"))))
    return _sweep(spark, rows, "share")


def fragmentation(spark: SparkSession, d: str) -> DataFrame:
    """Extents, reads and bytes in pages of the same join on whole, cut, and scattered buckets."""
    v, rows = stored(tables.planted(spark, d)), []
    for label, kind in (("none", {}), ("16 KiB", {"piece_bytes": 16 << 10}), ("4 KiB", {"piece_bytes": 4 << 10}), ("naive", {"mode": "naive"})):
        layout = _stored(spark, v, BASE, **kind)
        rows.append((label, layout.extents().select("extents", "below_page").crossJoin(_work(replay.replay_counts(layout, BASE)).withColumn("amplification", F.col("page_bytes") / F.col("read_bytes")))))
    return _sweep(spark, rows, "cut")


def orchestration_ablation(spark: SparkSession, d: str) -> DataFrame:
    """Loads of the stored join: oldest use out and id order, furthest next use out, and the planned order besides."""
    layout = _stored(spark, stored(tables.planted(spark, d)), BASE)
    steps = (("lru, id", "lru", "id"), ("opt, id", "opt", "id"), ("opt, overlap", "opt", "overlap"))
    return _sweep(spark, [(label, _work(replay.replay_counts(layout, replace(BASE, policy=p, order=o)))) for label, p, o in steps], "step")


def phases(spark: SparkSession, d: str) -> DataFrame:
    """Seconds of bucketing, of planning, and of execution, the latter also by reading and computing."""
    began = time.time()
    layout = _stored(spark, stored(tables.planted(spark, d)), BASE)
    bucketed = time.time()
    join.plan_segments(graph.bucket_graph(layout.buckets, BASE, layout.manifest.d), layout.buckets, BASE).count()
    planned = time.time()
    io, compute = replay.replay_counts(layout, BASE).agg(F.sum("io_seconds"), F.sum("compute_seconds")).first()
    rows = [("bucketing", bucketed - began), ("planning", planned - bucketed), ("execution", time.time() - planned), ("reading", io), ("computing", compute)]
    return spark.createDataFrame(rows, "phase string, seconds double")


def seeds(spark: SparkSession, d: str, n: int = 5) -> DataFrame:
    """Mean, deviation and extremes of the recall over ``n`` draws of the centres."""
    v = stored(tables.planted(spark, d))
    exact, rows = stored(baselines.exact_count(v, EPS)), []
    for seed in range(n):
        rows.append((str(seed), metrics.counted_recall(exact, join.join_count(v, replace(BASE, seed=seed)))))
    return _sweep(spark, rows, "seed").agg(F.count(F.lit(1)).alias("runs"), F.avg("recall").alias("mean"), F.stddev_samp("recall").alias("deviation"), F.min("recall").alias("lowest"), F.max("recall").alias("highest"))


def growth(spark: SparkSession, d: str) -> DataFrame:
    """Slope of log(distances computed) over log(vectors) of the bucket join, whose buckets keep their mean size, and of a linear scan, for 1, 2 and 4 copies."""
    rows = []
    for copies in (1, 2, 4):
        v = stored(tables.planted(spark, d, copies))
        n = v.count()
        cfg = replace(BASE, eps=0.12, centers=max(2, n // 50))
        layout = join.build_layout(v, cfg)
        c = metrics.candidate_counts(graph.bucket_graph(layout.buckets, cfg, layout.d), layout.buckets).first()
        rows.append(("bucket join", float(n), float(c["pairs_across"] + c["pairs_within"])))
        rows.append(("linear scan", float(n), n * (n - 1) / 2))
    return spark.createDataFrame(rows, "method string, n double, distances double").groupBy("method").agg(F.regr_slope(F.log("distances"), F.log("n")).alias("slope"))


def filtered(spark: SparkSession, d: str) -> DataFrame:
    """Pairs of near documents in English: attribute filter before distances."""
    v = stored(tables.docvec(spark, d).join(tables.read(spark, d, "documents", F.col("doc_id").alias("vec_id"), "lang"), "vec_id"))
    return join.self_join(v, JoinConfig(eps=0.3, recall=1.0, prune=False, centers=32), where=F.col("lang") == "en")


def leakage(spark: SparkSession, d: str) -> DataFrame:
    """Documents near a benchmark item: two-set join of the hashed texts."""
    bench = stored(tables.hash_vectors(tables.read(spark, d, "benchmark", "item_id", "text"), "item_id", "text"))
    return join.cross_join(stored(tables.docvec(spark, d)), bench, JoinConfig(eps=0.8, recall=1.0, prune=False, centers=24))


def layout_reuse(spark: SparkSession, d: str) -> DataFrame:
    """Pairs of several distances and recalls from one stored layout."""
    layout = _stored(spark, stored(tables.planted(spark, d)), BASE)
    return _sweep(spark, [(f"{eps}, {recall}", _work(replay.replay_counts(layout, replace(BASE, eps=eps, recall=recall)))) for eps, recall in ((0.12, 0.9), (0.12, 1.0), (EPS, 0.9), (EPS, 0.99))], "setting")


def queries() -> dict:
    return {f"exp_{f.__name__}": f for f in (recall_sweep, memory_sweep, distance_sweep, bucket_sweep, fragmentation, orchestration_ablation, phases, seeds, growth, filtered, leakage, layout_reuse)}
