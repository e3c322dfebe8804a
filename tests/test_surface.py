"""Raw vector files, SQL functions, bucket pairs by cells, centres by graph."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from vecjoin.config import JoinConfig
from vecjoin.functions import sql
from vecjoin.functions.vectors import VectorSchemaError, l2
from vecjoin.operators import bucketize, join
from vecjoin.plans import graph, orchestrate
from vecjoin.sources import tables, vecs


@pytest.mark.parametrize(("kind", "values"), [("fvecs", [[0.5, -1.25], [3.0, 4.0], [1e9, 0.0]]), ("ivecs", [[-7.0, 2.0]]), ("bvecs", [[0.0, 255.0], [1.0, 2.0]])])
def test_vecs_round_trip(spark, tmp_path, kind, values):
    df = spark.createDataFrame([(v,) for v in values], "v array<double>").coalesce(1)
    vecs.write_vecs(df, str(tmp_path / "x"), kind)
    back = vecs.read_vecs(spark, str(tmp_path / "x"), kind).orderBy("vec_id").collect()
    assert [r["v"] for r in back] == values and [r["vec_id"] for r in back] == list(range(len(values)))


def test_vecs_ranges_bytes_and_errors(spark, tmp_path):
    x = np.random.default_rng(3).random((1000, 5)).astype("<f4")
    records = np.zeros(1000, dtype=[("n", "<i4"), ("v", "<f4", (5,))])
    records["n"], records["v"] = 5, x
    (tmp_path / "a").mkdir()
    (tmp_path / "a" / "one.fvecs").write_bytes(records[:600].tobytes())
    (tmp_path / "a" / "two.fvecs").write_bytes(records[600:].tobytes())
    (tmp_path / "a" / "zero.fvecs").write_bytes(b"")
    vecs.register(spark)
    df = spark.read.format("vecs").option("rangeBytes", 24 * 7).load(str(tmp_path / "a"))
    assert df.rdd.getNumPartitions() > 100
    rows = df.orderBy("vec_id").collect()
    assert [r["vec_id"] for r in rows] == list(range(1000))
    assert np.array_equal(np.array([r["v"] for r in rows]), x.astype(float))
    (tmp_path / "b.fvecs").write_bytes(records.tobytes()[:-1])
    with pytest.raises(Exception, match="whole records"):
        vecs.read_vecs(spark, str(tmp_path / "b.fvecs")).count()
    (tmp_path / "c").mkdir()
    assert vecs.read_vecs(spark, str(tmp_path / "c")).count() == 0
    with pytest.raises(ValueError, match="kind"):
        vecs._kind({"kind": "other"})
    assert issubclass(VectorSchemaError, ValueError)


def test_sql_functions(spark, small):
    sql.register(spark)
    emb = tables.embeddings(spark, small).withColumn("part", F.col("vec_id") % 3)
    emb.createOrReplaceTempView("emb_parts")
    got = {(r["id_lo"], r["id_hi"]) for r in spark.sql("SELECT id_lo, id_hi FROM eps_neighbors(TABLE(SELECT vec_id, v, part FROM emb_parts) PARTITION BY (part), 1.2)").collect()}
    want = {(r["a"], r["b"]) for r in spark.sql("SELECT a.vec_id AS a, b.vec_id AS b FROM emb_parts a JOIN emb_parts b ON a.part = b.part AND a.vec_id < b.vec_id WHERE l2_of(a.v, b.v) <= 1.2").collect()}
    assert got == want and got
    edges = [(0, 1), (1, 2), (0, 2), (2, 3)]
    spark.createDataFrame([(0, s, i, j) for s, (i, j) in enumerate(edges)], "g int, seq long, i long, j long").createOrReplaceTempView("work")
    log = spark.sql("SELECT task, op, bucket_id, victim FROM cache_replay(TABLE(work) PARTITION BY (g) ORDER BY (seq), 2, 'opt')").collect()
    assert [tuple(r) for r in log] == orchestrate.plan_cache(edges, 2)[0]
    assert spark.sql("SELECT cosine_of(array(1D, 0D), array(0D, 2D)) AS c, l2_of(array(0D), NULL) AS n").first() == (0.0, None)


@pytest.mark.parametrize("cells", [None, 1, 7, 60])
@pytest.mark.parametrize("eps", [0.01, 0.12])
def test_near_pairs_loses_nothing(spark, eps, cells):
    rng = np.random.default_rng(5)
    rows = [(i, c.tolist(), float(rng.random() * 0.1)) for i, c in enumerate(rng.random((60, 2)))]
    left = spark.createDataFrame(rows, "i long, ci array<double>, r_i double")
    right = spark.createDataFrame(rows[::-1], "j long, cj array<double>, r_j double")
    want = left.join(right, l2("ci", "cj") - F.col("r_i") - F.col("r_j") <= eps).select("i", "j").collect()
    got = graph.near_pairs(left, right, eps, cells).select("i", "j").collect()
    assert sorted(map(tuple, got)) == sorted(map(tuple, want))


def test_near_pairs_of_nothing(spark):
    left = spark.createDataFrame([], "i long, ci array<double>, r_i double")
    right = spark.createDataFrame([], "j long, cj array<double>, r_j double")
    assert graph.near_pairs(left, right, 0.1).count() == 0


def test_centres_by_graph(spark, small):
    emb = tables.embeddings(spark, small).select("vec_id", "v")
    centers = bucketize.sample_centers(emb, 40)
    share = bucketize.agreement(bucketize.assign_buckets(emb, centers, "brute"), bucketize.assign_buckets(emb, centers, "graph")).first()[0]
    assert share >= 0.95
    one = bucketize.assign_buckets(emb, centers.limit(1), "graph")
    assert one.select("bucket_id").distinct().count() == 1 and one.count() == emb.count()


def test_stored_layout_is_read_not_computed(spark, small):
    layout = join.build_layout(tables.embeddings(spark, small), JoinConfig(eps=1.1, centers=8))
    plan = layout.buckets._jdf.queryExecution().executedPlan().toString()
    assert "MapInArrow" not in plan and "FileScan parquet" in plan
