"""Baselines that compare blocks of rows: results against all pairs, and plans without row-by-row nested loops."""

import numpy as np

from vecjoin.functions.proximity import ProximityGraph, near_links
from vecjoin.operators import apps, baselines
from vecjoin.sources import storage


def vectors(spark, x):
    return spark.createDataFrame([(i, [float(c) for c in v]) for i, v in enumerate(x)], "vec_id long, v array<double>")


def distances(x):
    return ((x[:, None] - x[None]) ** 2).sum(axis=2) ** 0.5


def nested(df):
    plan = df._jdf.queryExecution().executedPlan().toString()
    return "NestedLoop" in plan or "Cartesian" in plan


def test_exact_join(spark):
    x = np.random.default_rng(1).normal(size=(150, 5))
    found = baselines.exact_join(vectors(spark, x), 1.3)
    i, j = np.nonzero(np.triu(distances(x) <= 1.3, 1))
    assert not nested(found) and {(r.id_lo, r.id_hi) for r in found.collect()} == set(zip(i.tolist(), j.tolist(), strict=True))


def test_knn_join(spark):
    x = np.repeat(np.random.default_rng(2).normal(size=(60, 4)), 3, axis=0)  # ties: every vector has two copies
    found = baselines.knn_join(vectors(spark, x), 4)
    d = distances(x)
    np.fill_diagonal(d, np.inf)
    want = {(i, r + 1, int(n)) for i in range(len(x)) for r, n in enumerate(np.lexsort((np.arange(len(x)), d[i]))[:4])}
    assert not nested(found) and {(r.vec_id, r["rank"], r.neighbor) for r in found.collect()} == want
    assert baselines.knn_join(vectors(spark, x[:3]), 5).count() == 6 and baselines.knn_join(vectors(spark, x[:1]), 5).count() == 0


def test_band_join(spark):
    x = np.random.default_rng(3).normal(size=(200, 3))
    i, j = np.nonzero(np.triu(distances(x) <= 0.4, 1))
    want = list(zip(i.tolist(), j.tolist(), strict=True))
    for rows in (7, 16_384):  # several blocks of a cell, and one
        found = baselines.band_join(vectors(spark, x), 0.4, rows=rows)
        assert sorted((r.id_lo, r.id_hi) for r in found.collect()) == want
    assert not nested(found)
    assert baselines.band_join(vectors(spark, x).where("vec_id < 0"), 0.4).count() == 0


def test_probe_places_and_tuned_k(spark):
    """One walk tells the pairs of every smaller k."""
    df = vectors(spark, np.random.default_rng(4).normal(size=(160, 6)))
    ranks = storage.stored(baselines.graph_probe_ranks(df, 2.0, 47))
    for k in (1, 4, 16):
        assert {(r[0], r[1]) for r in baselines.graph_probe_join(df, 2.0, k).collect()} == {(r[0], r[1]) for r in ranks.where(f"place <= {k}").collect()}
    k, got = baselines.tune_k(df, 2.0, 0.95, baselines.exact_join(df, 2.0))
    assert got >= 0.95 and k > 1


def test_calibrated_distance(spark):
    x = np.random.default_rng(5).normal(size=(300, 4))
    df = vectors(spark, x)
    held = [r[0] for r in df.selectExpr("vec_id", "md5(cast(vec_id as string)) AS h").orderBy("h").limit(40).collect()]
    d = np.sort(np.concatenate([np.delete(distances(x)[i], i) for i in held]))
    found = apps.calibrate_eps(df, 3, sample=40)
    assert not nested(found) and abs(found.first()[0] - (d[119] + d[120]) / 2) < 1e-12


def test_vectors_of_texts_are_computed_once(spark, small, monkeypatch):
    """The joins of hashed texts read stored vectors, and copies collapse before the join."""
    from vecjoin import registry, workloads
    from vecjoin.operators import join

    plans, sizes = [], []
    plain_self, plain_cross = join.self_join, join.cross_join
    monkeypatch.setattr(join, "self_join", lambda v, *a, **k: (plans.append(v._jdf.queryExecution().optimizedPlan().toString()), sizes.append((v.count(), v.select("v").distinct().count())), plain_self(v, *a, **k))[2])
    monkeypatch.setattr(join, "cross_join", lambda x, y, *a, **k: (plans.extend(z._jdf.queryExecution().optimizedPlan().toString() for z in (x, y)), plain_cross(x, y, *a, **k))[1])
    workloads.filtered(spark, small), workloads.leakage(spark, small), registry.dedupe_documents(spark, small)
    assert len(plans) == 4 and not any("Aggregate" in p or "Generate" in p for p in plans)
    assert sizes[-1][0] == sizes[-1][1]


def test_walks_side_by_side():
    """Many walks of a proximity graph at a time read what each reads alone, for beams and k of any length, and links are found in runs."""
    rng = np.random.default_rng(5)
    x = np.concatenate([rng.normal(size=(300, 8)), rng.normal(size=(100, 8)) * 0.05])
    graph = ProximityGraph(x, 6)
    assert ProximityGraph(x, 6, near=near_links(x, 0, 150, 6) + near_links(x, 150, 400, 6)).links == graph.links
    q = np.concatenate([x[::7], rng.normal(size=(20, 8))])
    for k, beam in ((1, 4), (5, 12), (40, 12), (500, 12)):
        got = [[] for _ in q]
        for row, node, square in graph.search_many(q, k, beam, 16):
            for i, j, d in zip(row.tolist(), node.tolist(), square.tolist(), strict=True):
                got[i].append(j)
                assert d == ((x[j] - q[i]) ** 2).sum()
        assert got == [graph.search(one, k, beam)[0] for one in q]
    one = ProximityGraph(x[:1])
    assert [r.tolist() for r in next(one.search_many(x[:2], 3, 4))[:2]] == [[0, 1], [0, 0]]
