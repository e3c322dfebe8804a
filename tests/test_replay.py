"""Stored layouts, replay, margin slices, calibration, means and codes."""

from dataclasses import replace

import numpy as np

from tests.test_plans import vectors
from vecjoin import workloads
from vecjoin.config import JoinConfig
from vecjoin.operators import baselines, bucketize, join, replay
from vecjoin.sources.storage import StoredLayout


def pairs(df):
    rows = [(r.id_lo, r.id_hi) for r in df.collect()]
    assert len(rows) == len(set(rows))
    return set(rows)


def test_stored_join_is_exact(spark, tmp_path):
    x = np.random.default_rng(7).normal(size=(260, 5))
    x[:120] *= 0.01  # a hot bucket of many blocks
    df = vectors(spark, x)
    cfg = JoinConfig(eps=0.6, recall=1.0, prune=False, centers=8, block_rows=16, memory_fraction=0.4)
    want = pairs(baselines.exact_join(df, 0.6))
    for n, kind in enumerate(({}, {"piece_bytes": 200}, {"mode": "naive"})):
        stored = replay.write_layout(df, cfg, f"{tmp_path}/{n}", **kind)
        for policy in ("opt", "lru"):
            assert pairs(replay.self_join_on(stored, replace(cfg, policy=policy), run_tasks=25)) == want
        c = replay.replay_counts(stored, cfg).groupBy().sum().first().asDict()
        assert c["sum(pairs)"] == len(want) and c["sum(loads)"] + c["sum(hits)"] == 2 * c["sum(tasks)"] and c["sum(page_bytes)"] >= c["sum(read_bytes)"]
        size = stored.extents().first()
        assert size["bytes"] == 260 * (8 + 8 * 5) and (size["extents"] == 260) == (kind == {"mode": "naive"})
    again = StoredLayout.load(spark, f"{tmp_path}/0")
    assert again.manifest.n == 260 and again.manifest.d == 5
    assert pairs(replay.self_join_on(again, replace(cfg, eps=0.3))) == pairs(baselines.exact_join(df, 0.3))


def test_margin_drops_no_pair(spark):
    df = vectors(spark, np.random.default_rng(8).normal(size=(200, 4)))
    cfg = JoinConfig(eps=0.9, recall=1.0, prune=False, centers=10, margin_filter=True)
    assert pairs(join.self_join(df, cfg)) == pairs(baselines.exact_join(df, 0.9))
    rows = np.array([[0.0, 0.0], [0.49, 0.0], [-1.0, 0.0]])
    assert join.near_border(rows, np.zeros(2), np.array([1.0, 0.0]), 0.2).tolist() == [False, True, False]


def test_calibrated_radius_keeps_recall(spark):
    df = vectors(spark, np.random.default_rng(9).normal(size=(400, 3)))
    cfg = JoinConfig(eps=0.5, recall=0.95, centers=20)
    layout = join.build_layout(df, cfg)
    chosen = join.calibrate_radius(layout, cfg, sample=400)  # all vectors: exact
    exact = pairs(baselines.exact_join(df, 0.5))
    got = pairs(join.self_join(df, chosen, layout))
    assert got <= exact and len(got) >= 0.95 * len(exact) and 0 <= chosen.radius_share <= 1


def test_means_and_codes(spark):
    x = np.random.default_rng(10).normal(size=(300, 8))
    df = vectors(spark, x)
    spread = [bucketize.assign_buckets(df, bucketize.kmeans_centers(df, 6, n)).selectExpr("avg(d_center * d_center)").first()[0] for n in (0, 1, 4)]
    assert spread[0] > spread[1] >= spread[2]
    codes = baselines.ProductCodes(x, 8, 64)
    near = codes.distances(x[0], codes.encode(x))
    true = ((x - x[0]) ** 2).sum(axis=1)
    assert np.corrcoef(near, true)[0, 1] > 0.97 and codes.encode(x).nbytes == 300 * 8
    few, many = (len(pairs(baselines.code_probe_join(df, 1.5, 2, c, 8))) for c in (1, 8))
    assert few < many <= len(pairs(baselines.exact_join(df, 1.5)))


def test_experiments_move_as_reported(spark, mid):
    recall = {float(r.wanted): r for r in workloads.recall_sweep(spark, mid).collect()}
    assert all(r.recall >= w - 0.05 and r.precision == 1 for w, r in recall.items()) and recall[0.8].pairs_across <= recall[0.99].pairs_across
    assert (recall[0.9].edges, recall[0.9].pairs_across) == (68, 96_402)  # FIXTURES.md
    loads = [r.loads for r in workloads.memory_sweep(spark, mid).orderBy("memory").collect()]
    assert loads == sorted(loads, reverse=True)
    step = {r.step: r.loads for r in workloads.orchestration_ablation(spark, mid).collect()}
    assert step["lru, id"] > step["opt, id"] > step["opt, overlap"]
    cut = {r.cut: r for r in workloads.fragmentation(spark, mid).collect()}
    assert cut["none"].amplification < cut["4 KiB"].amplification < cut["naive"].amplification and len({r.pairs for r in cut.values()}) == 1
    slope = dict(workloads.growth(spark, mid).collect())
    assert slope["bucket join"] < 1.3 < 1.9 < slope["linear scan"]
