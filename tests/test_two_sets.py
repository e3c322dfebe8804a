"""Order and cache of two sets, bounds on loads, and joins on filtered buckets."""

import random
from dataclasses import replace

import pytest
from pyspark.sql import functions as F

from vecjoin import registry, surface
from vecjoin.config import JoinConfig
from vecjoin.operators import join
from vecjoin.plans import two_sets
from vecjoin.sources import tables


def test_tasks_cover_all_edges():
    rng = random.Random(1)
    for _ in range(30):
        edges = sorted({(rng.randrange(12), rng.randrange(9)) for _ in range(40)})
        for side in (0, 1):
            tasks = two_sets.two_set_tasks(edges, 4, side)
            assert sorted(tasks) == edges
            lead = [t[side] for t in tasks]
            assert len({x for x, y in zip(lead, lead[1:], strict=False) if x != y} | set(lead[-1:])) == len(set(lead)) and sum(x != y for x, y in zip(lead, lead[1:], strict=False)) == len(set(lead)) - 1
            every = len({("l", i) for i, _ in edges} | {("r", j) for _, j in edges})
            opt, lru = (two_sets.two_set_loads(tasks, 4, p)["loads"] for p in ("opt", "lru"))
            assert every <= opt <= lru <= 2 * len(edges)
            cut = two_sets.two_set_segments(tasks, 4)
            assert all(len({("l", i) for (i, _), s in zip(tasks, cut, strict=True) if s == k} | {("r", j) for (_, j), s in zip(tasks, cut, strict=True) if s == k}) <= 4 for k in set(cut))
    assert two_sets.two_set_tasks([], 4) == []


def test_planned_order_saves_loads(spark, mid):
    loads = {(r.streamed, r.ordering, r.policy): r.loads for r in surface.exp_two_sets(spark, mid).collect()}
    for way in ("larger", "smaller"):
        assert loads[way, "overlap", "opt"] < loads[way, "id", "opt"] < loads[way, "id", "lru"]


def test_filter_that_empties_buckets(spark, mid):
    v = tables.embeddings(spark, mid)
    cfg = JoinConfig(eps=1.25, recall=1.0, prune=False, centers=100, memory_fraction=0.1)
    few = F.col("vec_id") < 40
    got = {(r.id_lo, r.id_hi) for r in join.self_join(v, cfg, where=few).collect()}
    want = {(r.id_lo, r.id_hi) for r in registry.baselines.exact_join(v.where(few), 1.25).collect()}
    assert got == want and got
    assert join.cross_join(v.where("vec_id < 3"), v.where("vec_id < 0"), cfg, "larger").count() == 0


def test_slots_follow_bytes(spark, mid):
    layout = join.build_layout(tables.embeddings(spark, mid), JoinConfig(eps=1.0, centers=20))
    assert join.memory_slots(layout.buckets, JoinConfig(eps=1.0, memory_fraction=0.5)) == 10
    assert join.memory_slots(layout.buckets, JoinConfig(eps=1.0, memory_fraction=0.5, task_bytes=1)) == 2


def test_margin_needs_nearest_centres(spark, mid):
    """Where assignment is approximate the margin filter is left off, so that no pair is lost."""
    v = tables.embeddings(spark, mid)
    cfg = JoinConfig(eps=registry.EMB_EPS, recall=1.0, prune=False, centers=16, margin_filter=True)
    layout = join.build_layout(v, cfg)
    moved = layout.assigned.withColumn("bucket_id", F.when(F.col("vec_id") % 5 == 0, F.lit(layout.buckets.first()["bucket_id"])).otherwise(F.col("bucket_id")))
    center = layout.buckets.select("bucket_id", "center")
    from vecjoin.functions.vectors import l2
    from vecjoin.operators.bucketize import bucket_stats

    moved = moved.join(center, "bucket_id").withColumn("d_center", l2("v", "center")).drop("center")
    astray = replace(layout, assigned=moved, buckets=bucket_stats(moved, center), nearest=False)
    assert join.self_join(v, cfg, astray).count() == 250


def test_streamed_side():
    a, b = (join.Layout(None, None, None, 2, n) for n in (3, 5))
    assert [join.streamed_side(a, b, s) for s in ("larger", "smaller")] == [1, 0]
    with pytest.raises(ValueError):
        join.streamed_side(a, b, "left")
