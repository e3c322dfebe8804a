"""Counts of pairs without holding them, and the bucket graph by matrix products against its plan of expressions."""

from __future__ import annotations

from dataclasses import replace

import numpy as np
import pytest
from pyspark.sql import functions as F

from vecjoin.config import JoinConfig
from vecjoin.functions.vectors import close_pairs, count_close
from vecjoin.operators import baselines, bucketize, join, replay
from vecjoin.plans import graph
from vecjoin.sources import storage, tables


@pytest.fixture(scope="module")
def planted(spark, mid):
    return storage.stored(tables.planted(spark, mid))


def test_count_close_is_the_number_of_pairs():
    rng = np.random.default_rng(1)
    a, b = rng.normal(size=(700, 8)), np.round(rng.normal(size=(600, 8)), 1)
    b[:50] = b[50:100] + 0.5 * np.eye(8)[0]  # distances that are the bound itself
    for eps in (0.5, 1.7, 3.0):
        for x, y in ((a, None), (a, b), (b, None)):
            every = np.sqrt((((x[:, None] - (x if y is None else y)[None]) ** 2)).sum(axis=2))
            true = int((np.triu(every <= eps, 1) if y is None else every <= eps).sum())
            assert count_close(x, y, eps, 100) == len(close_pairs(x, y, eps, 130)[0]) == true


@pytest.mark.parametrize("far", [0.0, 1e3, 1e17])
def test_count_close_of_far_vectors(far):
    """Where single precision can't tell, as for vectors far from the origin, double precision proposes."""
    rng = np.random.default_rng(3)
    a = rng.normal(size=(300, 4)) + far
    a[:, 0] += np.arange(300) * 1e-3
    every = np.sqrt(((a[:, None] - a[None]) ** 2).sum(axis=2))
    true = int(np.triu(every <= 0.8, 1).sum())
    assert count_close(a, None, 0.8) == len(close_pairs(a, None, 0.8)[0]) == true


def test_counts_of_joins(planted):
    cfg = JoinConfig(eps=0.437245, recall=0.9, centers=40, radius_mode="eps", memory_fraction=0.2)
    layout = join.build_layout(planted, cfg)
    assert join.join_count(planted, cfg, layout).first()[0] == join.self_join(planted, cfg, layout).count()
    assert baselines.exact_count(planted, 0.437245).first()[0] == baselines.exact_join_blocks(planted, 0.437245).count() == 10_000


@pytest.mark.parametrize("change", [{}, {"scale": "unit"}, {"radius_mode": "eps"}, {"radius_mode": "mean_plus_eps"}, {"edge_merge": "intersection", "radius_mode": "eps"}, {"prune": False}, {"recall": 1.0}, {"radius_mode": "calibrated", "radius_share": 0.3}])
def test_graph_by_product_is_the_graph(planted, change):
    cfg = replace(JoinConfig(eps=0.437245, recall=0.9, centers=40), **change)
    layout = join.build_layout(planted, cfg)
    edges = graph.near_pairs(*graph._sides(layout.buckets), cfg.distance).where("i <> j")
    plain = graph.merge_edges(graph.prune_edges(edges, cfg, layout.d) if cfg.prune else edges, cfg.edge_merge)
    told = lambda df: sorted((r.i, r.j, round(r.center_dist, 9)) for r in df.collect())
    assert told(graph.bucket_graph(layout.buckets, cfg, layout.d)) == told(plain)


def test_runs_end_by_distances(planted, tmp_path, monkeypatch):
    """Many short runs count the same pairs and distances as one; each begins with an empty cache."""
    cfg = JoinConfig(eps=0.437245, recall=0.9, centers=40, radius_mode="eps", memory_fraction=0.2)
    stored = replay.write_layout(planted, cfg, str(tmp_path / "layout"))
    whole = replay.replay_counts(stored, cfg).collect()
    monkeypatch.setattr(replay, "RUN_DISTANCES", 20_000)
    short = replay.replay_counts(stored, cfg).collect()
    assert len(short) > len(whole) == 1
    assert sum(r.pairs for r in short) == whole[0].pairs and sum(r.distances for r in short) == whole[0].distances
    assert sum(r.loads for r in short) >= whole[0].loads


def test_lsh_cells_by_blocks(planted):
    """Cells cut into blocks lose no pair."""
    told = lambda rows: sorted(tuple(r)[:2] for r in baselines.lsh_join(planted, 0.12, rows=rows).collect())
    found = told(8192)
    assert found == told(20) and len(found) > 2500


def test_nearest_by_tiles(monkeypatch):
    rng = np.random.default_rng(2)
    x, c = rng.normal(size=(500, 8)), rng.normal(size=(60, 8))
    at, d = bucketize.nearest(x, c)
    monkeypatch.setattr(bucketize, "_SCORES", 600)
    again, e = bucketize.nearest(x, c)
    assert (at == again).all() and np.allclose(d, e)


def test_runs_spread_over_tasks(spark, planted, monkeypatch):
    """Runs of a stored join are dealt to several tasks, though their descriptions are few bytes; scattered extents count as whole ones do."""
    monkeypatch.setattr(replay, "RUN_DISTANCES", 1 << 14)
    cfg = JoinConfig(eps=0.437245, recall=0.9, centers=40, radius_mode="eps", memory_fraction=0.2)
    told = []
    for kind in ({}, {"mode": "naive"}):
        layout = replay.write_layout(planted, cfg, f"{storage.folder(spark)}/spread-{len(told)}", **kind)
        counts = replay.replay_counts(layout, cfg).withColumn("task", F.spark_partition_id()).collect()
        assert len(counts) > 4 and len({r.task for r in counts}) > 1
        told.append([sum(r[c] for r in counts) for c in ("tasks", "loads", "distances", "pairs")])
        assert sum(r.page_bytes for r in counts) >= sum(r.read_bytes for r in counts) > 0
    assert told[0] == told[1]
