"""Orders, cache plans, pruning arithmetic, kernels, configuration."""

import itertools
import math
import random

import numpy as np
import pytest

from vecjoin.config import JoinConfig
from vecjoin.functions.vectors import VectorSchemaError, as_vectors, close_pairs
from vecjoin.operators import apps, baselines, bucketize, join
from vecjoin.plans import graph, orchestrate

SMALL = {"k4": ([(0, 1), (0, 2), (0, 3), (1, 2), (1, 3), (2, 3)], 7), "c4": ([(0, 1), (1, 2), (2, 3), (3, 0)], 5), "p4": ([(0, 1), (1, 2), (2, 3)], 4), "star4": ([(0, 1), (0, 2), (0, 3)], 4), "paw": ([(0, 1), (1, 2), (2, 0), (0, 3)], 5), "diamond": ([(0, 1), (1, 2), (2, 3), (3, 0), (0, 2)], 6)}


@pytest.mark.parametrize("name", list(SMALL))
def test_fewest_loads(name):
    edges, best = SMALL[name]
    assert orchestrate.optimal_loads(edges, 2) == best
    for order in itertools.permutations(range(4)):
        got = orchestrate.plan_cache(orchestrate.tasks_in_order(edges, list(order)), 2)[1]
        assert got["loads"] >= best and got["uncovered"] == 0 and got["loads"] <= 4 + len(edges)


def geometric(n=200, seed=1, near=0.15):
    x = np.random.default_rng(seed).random((n, 2))
    d = ((x[:, None] - x[None]) ** 2).sum(axis=2) ** 0.5
    return [(i, j) for i in range(n) for j in range(i + 1, n) if d[i, j] < near]


def test_ablation_on_geometric_graph():
    edges = geometric()
    ids, over = orchestrate.order_nodes(edges, 20, "id"), orchestrate.order_nodes(edges, 20)
    assert sorted(over) == ids and over == orchestrate.order_nodes_naive(edges, 20)
    near = orchestrate.neighbours(edges)
    assert len(near[over[0]]) == max(map(len, near.values()))
    w = orchestrate.window_width(edges, 20)
    assert orchestrate.ordering_score(edges, over, w) > 2 * orchestrate.ordering_score(edges, ids, w)
    loads = {(o, p): orchestrate.plan_cache(orchestrate.tasks_in_order(edges, order), 20, p)[1] for o, order in (("id", ids), ("over", over)) for p in ("lru", "opt", "fifo", "lfu", "lifo")}
    assert loads["id", "lru"]["loads"] > loads["id", "opt"]["loads"] > loads["over", "opt"]["loads"] >= 200 - 5
    assert all(m["uncovered"] == 0 for m in loads.values())
    assert orchestrate.plan_cache(orchestrate.tasks_in_order(edges, ids), 20, "opt", pin=False)[1]["uncovered"] > 0
    everything = orchestrate.plan_cache(orchestrate.tasks_in_order(edges, ids), 1000)[1]
    assert everything["loads"] == len(near)
    tasks = orchestrate.tasks_in_order(edges, over)
    seg = orchestrate.segments(tasks, 20)
    for s in set(seg):
        assert len({x for t, k in zip(tasks, seg, strict=True) if k == s for x in t}) <= 20


def test_furthest_next_use_is_optimal():
    rng = random.Random(3)
    for _ in range(60):
        tasks = [(a, a + 100) for a in (rng.randint(0, 4) for _ in range(5))]
        access = [x for t in tasks for x in t]
        got = orchestrate.plan_cache(tasks, 3, "opt", pin=False)[1]["loads"]
        assert got == orchestrate.opt_misses_brute(access, 3)
        assert all(got <= orchestrate.plan_cache(tasks, 3, p, pin=False)[1]["loads"] for p in ("lru", "fifo", "lfu", "lifo"))


def test_independent_set_reaches_the_bound():
    kernel, leaves = [0, 1, 2], list(range(3, 9))
    edges = [(0, 1), (1, 2)] + [(k, x) for x in leaves for k in kernel]
    tasks = [(0, 1), (1, 2)] + [(k, x) for x in leaves for k in kernel]
    _, m = orchestrate.plan_cache(tasks, 9 - len(leaves) + 1, "lifo")
    assert m["loads"] == 9 and m["uncovered"] == 0 and len(edges) == len(tasks)


def test_bytes_as_capacity():
    edges = geometric(60, 2, 0.25)
    sizes = {x: 1 + x % 3 for x in range(60)}
    _, m = orchestrate.plan_cache(orchestrate.tasks_in_order(edges, orchestrate.order_nodes(edges, 10)), 24, sizes=sizes)
    assert m["uncovered"] == 0 and m["loads"] >= len(orchestrate.neighbours(edges))


def test_bound_factors():
    for d, want in ((2, 1.0), (3, 0.63662), (64, 0.10092), (96, 0.08208), (128, 0.07094)):
        assert abs(graph.mu(d) - want) < 1e-4
    assert abs(graph.cap_share(0, 64) - 0.5) < 1e-6 and graph.cap_share(1, 64) < 1e-9
    assert abs(graph.cap_share(0.1, 64) - 0.210) < 2e-3 and abs(graph.cap_share(0.2, 64) - 0.052) < 2e-3
    assert abs(graph.cap_share(0.3, 3) - (2 - 0.9 + 0.027) / 4) < 1e-4
    with pytest.raises(ValueError):
        graph.mu(1)


def test_kernel_survives_cancellation():
    rng = np.random.default_rng(0)
    x = rng.normal(size=(300, 16)) * 0.01 + 1e4
    true = ((x[:, None] - x[None]) ** 2).sum(axis=2) ** 0.5
    eps = float(np.quantile(true[np.triu_indices(300, 1)], 0.05))
    i, j, d = close_pairs(x, None, eps, tile=64)
    p, q = np.nonzero(np.triu(true <= eps, 1))
    assert set(zip(i.tolist(), j.tolist(), strict=True)) == set(zip(p.tolist(), q.tolist(), strict=True)) and np.allclose(d, true[i, j])


def test_configuration():
    for bad in ({"eps": 0}, {"eps": 1, "recall": 0}, {"eps": 1, "memory_fraction": 0}, {"eps": 1, "centers": 0}, {"eps": 1, "policy": "x"}):
        with pytest.raises(ValueError):
            JoinConfig(**bad)
    with pytest.raises(ValueError):
        orchestrate.plan_cache([(0, 1)], 1)
    assert math.isclose(JoinConfig(eps=4.0, eps_is_squared=True).distance, 2.0)


def vectors(spark, x):
    return spark.createDataFrame([(i, [float(c) for c in v]) for i, v in enumerate(x)], "vec_id long, v array<double>")


def test_odd_vectors(spark):
    schema = "id long, e array<double>"
    for rows in ([(1, [1.0]), (2, None)], [(1, [1.0]), (2, [1.0, 2.0])], [(1, [float("nan")])], [(1, [1.0]), (1, [2.0])], [(1, [None])]):
        with pytest.raises(VectorSchemaError):
            as_vectors(spark.createDataFrame(rows, schema), "id", "e")
    assert as_vectors(spark.createDataFrame([], schema), "id", "e").count() == 0
    same = vectors(spark, np.ones((6, 3)))
    for executor in ("native", "edge_join", "segment"):
        assert join.self_join(same, JoinConfig(eps=0.1, centers=2, executor=executor)).count() == 15
    assert join.self_join(vectors(spark, np.ones((1, 3))), JoinConfig(eps=0.1, centers=1)).count() == 0
    assert join.self_join(vectors(spark, np.arange(12.0).reshape(12, 1)), JoinConfig(eps=1.0, centers=4)).count() == 11
    few = vectors(spark, np.random.default_rng(0).normal(size=(40, 4)))
    assert join.self_join(few, JoinConfig(eps=100.0, centers=40)).count() == 780


def test_small_blocks_and_filters(spark):
    x = np.random.default_rng(5).normal(size=(240, 6))
    df = vectors(spark, x)
    want = {(r.id_lo, r.id_hi) for r in baselines.exact_join(df, 1.2).collect()}
    for executor in ("edge_join", "segment"):
        cfg = JoinConfig(eps=1.2, recall=1.0, centers=9, executor=executor, block_rows=7, memory_fraction=0.5)
        assert {(r.id_lo, r.id_hi) for r in join.self_join(df, cfg).collect()} == want
    assert {(r.id_lo, r.id_hi) for r in baselines.cell_replication_join(df, 1.2, 9).collect()} == want
    assert {(r.id_lo, r.id_hi) for r in baselines.band_join(df, 1.2).collect()} == want
    layout = join.build_layout(df, JoinConfig(eps=1, centers=9))
    for eps in (0.8, 1.0):  # one layout, several distances
        assert join.self_join(df, JoinConfig(eps=eps, recall=1.0, centers=9), layout=layout).count() == baselines.exact_join(df, eps).count()
    brute = bucketize.assign_buckets(df, bucketize.sample_centers(df, 30))
    assert bucketize.agreement(brute, bucketize.assign_buckets(df, bucketize.sample_centers(df, 30), "two_level")).first()[0] > 0.85


def test_groups(spark):
    pairs = spark.createDataFrame([(i, i + 1, 0.1) for i in range(30)] + [(50, 60, 0.1)], "id_lo long, id_hi long, dist double")
    got = dict(apps.groups(pairs).collect())
    assert all(got[i] == 0 for i in range(31)) and got[60] == 50


def test_native_distance_is_compiled(spark, monkeypatch):
    """The native executor's distance has no function called for each value, in parts and in one, and finds what a plain join finds."""
    for width, part in ((1, 1024), (64, 1024), (64, 50), (130, 50)):
        monkeypatch.setattr(join, "NATIVE_PART", part)
        x = np.random.default_rng(width).normal(size=(120, width))
        df, eps = vectors(spark, x), 1.3 * width**0.5
        got = join.self_join(df, JoinConfig(eps=eps, recall=1.0, prune=False, centers=5, executor="native"))
        assert ("lambda" not in got._jdf.queryExecution().optimizedPlan().toString()) == (width <= join.NATIVE_WIDTH)
        apart = np.sqrt(((x[:, None] - x[None]) ** 2).sum(axis=2))
        want = [(i, j) for i, j in zip(*np.nonzero(np.triu(apart <= eps, 1)), strict=True)]
        rows = got.collect()
        assert want and sorted((r.id_lo, r.id_hi) for r in rows) == want
        assert all(abs(r.dist - apart[r.id_lo, r.id_hi]) < 1e-9 for r in rows)
