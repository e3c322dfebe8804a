"""Queries of plans, measures and joins of two sets, beside those of ``registry``, and their SQL."""

from __future__ import annotations

import uuid
from concurrent.futures import ThreadPoolExecutor
from dataclasses import replace

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from . import registry, sinks, workloads
from .config import JoinConfig
from .operators import apps, baselines, join, metrics
from .operators.bucketize import sample_centers
from .plans import graph, orchestrate, two_sets
from .registry import _EMB, EMB_CENTERS, EMB_EPS, PLANTED_CENTERS, PLANTED_WIDE, Query, _round
from .sources import ranges, storage, tables
from .streaming import streams

SLOTS, WINDOW, RANGE_EPS = (4, 8, 16), 4, 1.2
CROSS = JoinConfig(eps=EMB_EPS, recall=1.0, prune=False, centers=12, memory_fraction=0.4)


def _new_path(spark: SparkSession, kind: str) -> str:
    return f"{storage.folder(spark)}/{kind}-{uuid.uuid4().hex}"


def _two_sets(spark: SparkSession, d: str) -> tuple[DataFrame, DataFrame]:
    emb = tables.embeddings(spark, d)
    return emb.where("vec_id % 3 = 0"), emb.where("vec_id % 3 <> 0")


def _cross(streamed: str) -> Query:
    return lambda s, d: _round(join.cross_join(*_two_sets(s, d), CROSS, streamed), "dist")


def cross_join_exact(spark: SparkSession, d: str) -> DataFrame:
    """Pairs of two sets with every distance computed, by the single set's exact join."""
    emb = tables.embeddings(spark, d)
    pairs = baselines.exact_join_blocks(emb, EMB_EPS).where("(id_lo % 3 = 0) <> (id_hi % 3 = 0)")
    lower = F.col("id_lo") % 3 == 0
    return _round(pairs.select(F.when(lower, F.col("id_lo")).otherwise(F.col("id_hi")).alias("x_id"), F.when(lower, F.col("id_hi")).otherwise(F.col("id_lo")).alias("y_id"), "dist"), "dist")


def exp_two_sets(spark: SparkSession, d: str) -> DataFrame:
    """Loads of the two-set join with either side streamed, in planned and in id order, by the bucket sizes' slots."""
    v = tables.planted(spark, d)
    cfg = replace(workloads.BASE, centers=20)
    a, b = join.build_layout(v.where("k = 0"), cfg), join.build_layout(v.where("k > 0"), replace(cfg, centers=40))
    edges = sorted((r[0], r[1]) for r in join.cross_graph(a, b, cfg).collect())  # at most 20 x 40
    rows = []
    for streamed in ("larger", "smaller"):
        side = join.streamed_side(a, b, streamed)
        for order, policy in (("overlap", "opt"), ("id", "opt"), ("id", "lru")):
            tasks = two_sets.two_set_tasks(edges, 8, side, order)
            m = two_sets.two_set_loads(tasks, 8, policy)
            led = len({t[side] for t in tasks})
            rows.append((streamed, order, policy, len(tasks), m["loads"], led, m["loads"] - led))
    return spark.createDataFrame(rows, "streamed string, ordering string, policy string, tasks long, loads long, streamed_loads long, cached_loads long")


def load_lower_bound(spark: SparkSession, d: str) -> DataFrame:
    """Every bucket with an edge is loaded once at least; twice the edges is what no cache at all loads."""
    layout, cfg = registry._planted_layout(spark, d)
    e = graph.bucket_graph(layout.buckets, cfg, layout.d)
    nodes = e.select(F.explode(F.array("i", "j")).alias("b")).agg(F.count_distinct("b").alias("lower_bound"))
    return nodes.crossJoin(e.agg(F.count(F.lit(1)).alias("edges"))).select("lower_bound", "edges", (2 * F.col("edges")).alias("uncached"))


def ordering_score_id(spark: SparkSession, d: str) -> DataFrame:
    """Partners shared by buckets at most ``WINDOW`` places apart in id order."""
    shared = registry.neighbor_overlap(spark, d)
    layout, cfg = registry._planted_layout(spark, d)
    nodes = graph.bucket_graph(layout.buckets, cfg, layout.d).select(F.explode(F.array("i", "j")).alias("b")).distinct().select("b", F.row_number().over(Window.orderBy("b")).alias("r"))
    met = shared.join(nodes.select(F.col("b").alias("x"), F.col("r").alias("rx")), "x").join(nodes.select(F.col("b").alias("y"), F.col("r").alias("ry")), "y")
    return met.where(F.col("ry") - F.col("rx") <= WINDOW).agg(F.coalesce(F.sum("shared"), F.lit(0)).alias("score"))


def lru_loads(spark: SparkSession, d: str) -> DataFrame:
    """Loads of the id order with the least recently used bucket out, for several numbers of slots."""
    edges, _ = registry._edges(spark, d)
    rows = [(slots, orchestrate.plan_cache(edges, slots, "lru", pin=False)[1]["loads"]) for slots in SLOTS]
    return spark.createDataFrame(rows, "slots long, loads long")


def memory_plan(spark: SparkSession, d: str) -> DataFrame:
    """What is left of the memory for buckets after centres and one write page for each bucket, and how many of mean size that is."""
    layout, cfg = registry._planted_layout(spark, d)
    return layout.buckets.agg(F.sum("bytes").alias("data"), F.count(F.lit(1)).alias("m"), F.avg("bytes").alias("mean")).select(
        "data", F.floor(F.col("data") * 0.5).alias("budget"), (F.col("m") * 4 * layout.d).alias("index_bytes"), (F.col("m") * 4096).alias("page_bytes")
    ).withColumn("left_over", F.greatest(F.lit(0), F.col("budget") - F.col("index_bytes") - F.col("page_bytes"))).crossJoin(layout.buckets.agg(F.avg("bytes").alias("mean"))).withColumn("slots", F.greatest(F.lit(2), F.floor(F.col("left_over") / F.col("mean")))).drop("mean")


def bucket_components(spark: SparkSession, d: str) -> DataFrame:
    """Connected parts of the bucket graph; they share no bucket, so each can be ordered by itself."""
    layout, cfg = registry._planted_layout(spark, d)
    e = graph.bucket_graph(layout.buckets, replace(cfg, radius_mode="eps", recall=0.5), layout.d)
    return apps.groups(e.select(F.col("i").alias("id_lo"), F.col("j").alias("id_hi"))).select(F.col("vec_id").alias("bucket_id"), "group")


def edges_pruned_quantile(spark: SparkSession, d: str) -> DataFrame:
    layout, cfg = registry._planted_layout(spark, d)
    cfg = replace(cfg, radius_mode="quantile_plus_eps")
    return _round(graph.bucket_graph(join.with_quantile(layout, cfg.radius_quantile), cfg, layout.d), "center_dist")


def _emb_layout(spark: SparkSession, d: str) -> tuple[join.Layout, JoinConfig]:
    cfg = JoinConfig(eps=RANGE_EPS, recall=1.0, prune=False, centers=EMB_CENTERS)
    return join.build_layout(tables.embeddings(spark, d), cfg), cfg


def attribute_ranges(spark: SparkSession, d: str) -> DataFrame:
    return ranges.attribute_ranges(_emb_layout(spark, d)[0].assigned, "label")


def filtered_range_contiguous(spark: SparkSession, d: str) -> DataFrame:
    """A join of labels 2 to 5 that reads those stretches of the buckets only."""
    layout, cfg = _emb_layout(spark, d)
    path = _new_path(spark, "ranges")
    ranges.write_by_attribute(layout.assigned, "label", path)
    return _round(join.self_join(layout.vectors, cfg, replace(layout, assigned=ranges.read_range(spark, path, "label", 2, 5))), "dist")


def pair_sink(spark: SparkSession, d: str) -> DataFrame:
    path = _new_path(spark, "pairs")
    sinks.write_pairs(baselines.exact_join_blocks(tables.embeddings(spark, d), EMB_EPS), path)
    return _round(sinks.read_pairs(spark, path), "dist")


def distance_histogram(spark: SparkSession, d: str) -> DataFrame:
    pairs = baselines.exact_join_blocks(tables.embeddings(spark, d), 1.25)
    return pairs.groupBy(F.floor(F.col("dist") * 40).cast("long").alias("bin")).agg(F.count(F.lit(1)).alias("n"))


def recall_sampled(spark: SparkSession, d: str) -> DataFrame:
    """Recall over the partners of every twentieth vector only (by keyed hash): the measure for sets too large for all true pairs."""
    v = tables.planted(spark, d)
    asked = v.where(F.conv(F.substring(F.md5(F.concat(F.lit("ask:"), F.col("vec_id").cast("string"))), 1, 8), 16, 10).cast("long") % 20 == 0).select(F.col("vec_id").alias("q"))
    found = join.self_join(v, JoinConfig(eps=PLANTED_WIDE, recall=0.9, centers=PLANTED_CENTERS))
    exact = baselines.exact_join_blocks(v, PLANTED_WIDE)
    some = lambda p: p.select(F.explode(F.array("id_lo", "id_hi")).alias("q"), "id_lo", "id_hi").join(asked, "q").select("id_lo", "id_hi")
    return _round(metrics.recall(some(exact), some(found)), "recall", "precision")


def seeds_50(spark: SparkSession, d: str) -> DataFrame:
    """Pairs left to compare over 50 draws of centres, with mean and deviation, as the spread of the work."""
    v = storage.stored(tables.planted(spark, d))
    storage.folder(spark)

    def work(seed: int) -> tuple[int, int]:
        cfg = replace(workloads.BASE, seed=seed)
        layout = join.build_layout(v, cfg)
        c = metrics.candidate_counts(graph.bucket_graph(layout.buckets, cfg, layout.d), layout.buckets).first()
        return seed, c["pairs_across"] + c["pairs_within"]

    with ThreadPoolExecutor(8) as pool:  # many small jobs: they overlap
        rows = list(pool.map(work, range(50)))
    return spark.createDataFrame(rows, "seed long, work long").agg(F.count(F.lit(1)).alias("draws"), F.avg("work").alias("mean"), F.stddev_samp("work").alias("deviation"))


def methods(spark: SparkSession, d: str) -> DataFrame:
    """Recall and distances computed of the bucket join (.995 asked for) and of the comparators, on the same vectors and distance."""
    v = storage.stored(tables.planted(spark, d))
    eps, n = registry.PLANTED_EPS, v.count()
    exact = storage.stored(baselines.exact_join_blocks(v, eps))
    cfg = JoinConfig(eps=eps, recall=0.995, centers=PLANTED_CENTERS)
    layout = join.build_layout(v, cfg)
    work = metrics.candidate_counts(graph.bucket_graph(layout.buckets, cfg, layout.d), layout.buckets).select((F.col("pairs_across") + F.col("pairs_within")).alias("distances"))
    rows = (("bucket join", join.self_join(v, cfg, layout), work), ("cell replication", baselines.cell_replication_join(v, eps, PLANTED_CENTERS), None), ("hash tables", baselines.lsh_join(v, eps), None), ("linear scan", exact, spark.createDataFrame([(n * (n - 1) // 2,)], "distances long")))
    out = None
    for name, found, cost in rows:
        one = metrics.recall(exact, found).select(F.lit(name).alias("method"), "recall", "precision")
        one = one.crossJoin(cost) if cost is not None else one.withColumn("distances", F.lit(None).cast("long"))
        out = one if out is None else out.unionByName(one)
    return out


def queries() -> dict[str, Query]:
    return {
        "cross_join_exact": cross_join_exact,
        "cross_join_larger_streamed": _cross("larger"),
        "cross_join_smaller_streamed": _cross("smaller"),
        "exp_two_sets": exp_two_sets,
        "exp_methods": methods,
        "exp_seeds_50": seeds_50,
        "side_filtered_join": lambda s, d: _round(join.side_join(tables.embeddings(s, d), replace(CROSS, eps=RANGE_EPS), F.col("label") < 4, F.col("label") >= 3), "dist"),
        "filtered_range_contiguous": filtered_range_contiguous,
        "attribute_ranges": attribute_ranges,
        "centers_bernoulli": lambda s, d: sample_centers(tables.embeddings(s, d), EMB_CENTERS, method="bernoulli").select("bucket_id"),
        "edges_pruned_quantile": edges_pruned_quantile,
        "bucket_components": bucket_components,
        "load_lower_bound": load_lower_bound,
        "ordering_score_id": ordering_score_id,
        "lru_loads": lru_loads,
        "memory_plan": memory_plan,
        "pair_sink": pair_sink,
        "distance_histogram": distance_histogram,
        "recall_sampled": recall_sampled,
        "benchmark_leak": lambda s, d: _round(workloads.leakage(s, d), "dist", digits=4),
        "stream_session": lambda s, d: streams.drain(streams.session_counts(streams.event_stream(s, d))).select("user_id", F.date_format("session_window.start", "yyyy-MM-dd HH:mm:ss").alias("begins"), "n"),
    }


def oracle_sql() -> dict[str, str]:
    mu = repr(graph.mu(64))
    safe = f"a.radius + {PLANTED_WIDE}"
    planted = registry._graph(mu, safe)
    cross = f"WITH {_EMB} SELECT a.vec_id AS x_id, b.vec_id AS y_id, round(list_distance(a.v, b.v), 5) AS dist FROM emb a JOIN emb b ON a.vec_id % 3 = 0 AND b.vec_id % 3 <> 0 WHERE list_distance(a.v, b.v) <= {EMB_EPS}"
    quantile = registry._graph(mu, f"a.q + {PLANTED_WIDE}").replace("max(d_center) AS radius", "quantile_cont(d_center, 0.9) AS q, max(d_center) AS radius")
    access = f"""{planted}, tasks AS (SELECT row_number() OVER (ORDER BY i, j) - 1 AS seq, i, j FROM edges),
  access AS (SELECT 2 * seq AS pos, i AS bucket_id FROM tasks UNION ALL SELECT 2 * seq + 1, j FROM tasks),
  b AS (SELECT pos, bucket_id, lag(pos) OVER (PARTITION BY bucket_id ORDER BY pos) AS before FROM access),
  depth AS (SELECT b.pos, b.before, count(DISTINCT a.bucket_id) AS distance FROM b LEFT JOIN access a ON a.pos > b.before AND a.pos < b.pos GROUP BY b.pos, b.before)"""
    bench = registry._DOCVEC.replace("documents", "benchmark").replace("doc_id", "item_id")
    for name in ("tok", "term", "place", "held", "vecs"):
        bench = bench.replace(f"{name} AS (", f"b_{name} AS (").replace(f"FROM {name}", f"FROM b_{name}")
    found = "met AS (SELECT i, j FROM edges UNION ALL SELECT bucket_id, bucket_id FROM buckets), f AS (SELECT least(a.vec_id, b.vec_id) AS lo, greatest(a.vec_id, b.vec_id) AS hi FROM met JOIN assign a ON a.bucket_id = i JOIN assign b ON b.bucket_id = j WHERE (i <> j OR a.vec_id < b.vec_id) AND list_distance(a.v, b.v) <= " + repr(PLANTED_WIDE) + ")"
    exact = f"e AS (SELECT a.vec_id AS lo, b.vec_id AS hi FROM vecs a JOIN vecs b ON a.vec_id < b.vec_id WHERE list_distance(a.v, b.v) <= {PLANTED_WIDE})"
    counted = "SELECT count(e) AS n_exact, count(f) AS n_found, count(*) FILTER (e AND f) AS n_both FROM (SELECT true AS e, lo, hi FROM {}) x FULL JOIN (SELECT true AS f, lo, hi FROM {}) y USING (lo, hi)"
    asked = "ask AS (SELECT vec_id AS q FROM vecs WHERE CAST('0x' || substr(md5('ask:' || vec_id), 1, 8) AS BIGINT) % 20 = 0), se AS (SELECT DISTINCT lo, hi FROM e JOIN ask ON q IN (lo, hi)), sf AS (SELECT DISTINCT lo, hi FROM f JOIN ask ON q IN (lo, hi))"
    return {
        "cross_join_exact": cross,
        "cross_join_larger_streamed": cross,
        "cross_join_smaller_streamed": cross,
        "side_filtered_join": f"WITH {_EMB} SELECT DISTINCT least(a.vec_id, b.vec_id) AS id_lo, greatest(a.vec_id, b.vec_id) AS id_hi, round(list_distance(a.v, b.v), 5) AS dist FROM emb a JOIN emb b ON a.label < 4 AND b.label >= 3 AND a.vec_id <> b.vec_id WHERE list_distance(a.v, b.v) <= {RANGE_EPS}",
        "filtered_range_contiguous": registry._exact(_EMB, RANGE_EPS, "WHERE label BETWEEN 2 AND 5"),
        "attribute_ranges": f"WITH {registry._buckets(_EMB, EMB_CENTERS)}, s AS (SELECT bucket_id, label AS value, count(*) AS n FROM assign JOIN emb USING (vec_id) GROUP BY 1, 2) SELECT bucket_id, value, CAST(coalesce(sum(n) OVER (PARTITION BY bucket_id ORDER BY value ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS BIGINT) AS first, n FROM s",
        "centers_bernoulli": f"SELECT vec_id AS bucket_id FROM embeddings WHERE CAST('0x' || substr(md5('42:' || vec_id), 1, 8) AS BIGINT) < {EMB_CENTERS} / (SELECT count(*) FROM embeddings) * {2.0**32}",
        "edges_pruned_quantile": f"WITH {quantile} SELECT i, j, round(cd, 5) AS center_dist FROM edges",
        "bucket_components": f"WITH RECURSIVE {registry._graph(mu, repr(PLANTED_WIDE), recall=0.5)}, u AS (SELECT i AS a, j AS b FROM edges UNION SELECT j, i FROM edges), reach(a, b) AS (SELECT a, a FROM u UNION SELECT r.a, u.b FROM reach r JOIN u ON r.b = u.a) SELECT a AS bucket_id, min(b) AS \"group\" FROM reach GROUP BY a",
        "load_lower_bound": f"WITH {planted} SELECT (SELECT count(DISTINCT b) FROM (SELECT i AS b FROM edges UNION SELECT j FROM edges)) AS lower_bound, count(*) AS edges, 2 * count(*) AS uncached FROM edges",
        "ordering_score_id": f"WITH {planted}, u AS (SELECT i, j FROM edges UNION ALL SELECT j, i FROM edges), r AS (SELECT i, row_number() OVER (ORDER BY i) AS r FROM (SELECT DISTINCT i FROM u)) SELECT CAST(count(*) AS BIGINT) AS score FROM u a JOIN u b ON a.j = b.j AND a.i < b.i JOIN r p ON p.i = a.i JOIN r q ON q.i = b.i WHERE q.r - p.r <= {WINDOW}",
        "lru_loads": f"WITH {access} SELECT CAST(slots AS BIGINT) AS slots, count(*) FILTER (before IS NULL OR distance >= slots) AS loads FROM depth, (SELECT unnest({list(SLOTS)}) AS slots) GROUP BY 1",
        "memory_plan": f"WITH {registry._buckets(registry._PLANTED, PLANTED_CENTERS)}, t AS (SELECT CAST(sum(bytes) AS BIGINT) AS data, count(*) AS m, avg(bytes) AS mean FROM buckets), p AS (SELECT data, CAST(floor(data * 0.5) AS BIGINT) AS budget, m * 4 * 64 AS index_bytes, m * 4096 AS page_bytes, mean FROM t) SELECT data, budget, index_bytes, page_bytes, greatest(0, budget - index_bytes - page_bytes) AS left_over, CAST(greatest(2, floor(greatest(0, budget - index_bytes - page_bytes) / mean)) AS BIGINT) AS slots FROM p",
        "pair_sink": registry._exact(_EMB, EMB_EPS),
        "distance_histogram": f"WITH p AS ({registry._exact(_EMB, 1.25, digits=12)}) SELECT CAST(floor(dist * 40) AS BIGINT) AS bin, count(*) AS n FROM p GROUP BY 1",
        "recall_report": f"WITH {planted}, {found}, {exact}, c AS ({counted.format('e', 'f')}) SELECT n_exact, n_found, n_both / n_exact AS recall, n_both / n_found AS precision FROM c",
        "recall_sampled": f"WITH {planted}, {found}, {exact}, {asked}, c AS ({counted.format('se', 'sf')}) SELECT n_exact, n_found, round(n_both / n_exact, 5) AS recall, round(n_both / n_found, 5) AS precision FROM c",
        "stream_session": "WITH e AS (SELECT user_id, ts, CASE WHEN ts - lag(ts) OVER w <= INTERVAL 12 HOURS THEN 0 ELSE 1 END AS new FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)), s AS (SELECT *, sum(new) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS k FROM e) SELECT user_id, strftime(min(ts), '%Y-%m-%d %H:%M:%S') AS begins, count(*) AS n FROM s GROUP BY user_id, k",
        "benchmark_leak": f"WITH {registry._DOCVEC}, {bench} SELECT a.vec_id AS x_id, b.vec_id AS y_id, round(list_distance(a.v, b.v), 4) AS dist FROM vecs a, b_vecs b WHERE list_distance(a.v, b.v) <= 0.8",
    }
