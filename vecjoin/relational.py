"""Relational operators around the joins, one query each with its SQL: kinds of joins, groupings, windows, sets, nested values."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .functions.vectors import l2
from .sources.tables import embeddings, read

Query = Callable[[SparkSession, str], DataFrame]
#: A side is sent to every task if the optimiser's estimate of it is at most so many bytes.
SMALL_BYTES = 32 << 20


def send_if_small(df: DataFrame, most: int = SMALL_BYTES) -> DataFrame:
    """``df`` marked for broadcast if its estimated size allows; as it is otherwise, for a join by shuffle."""
    size = int(str(df._jdf.queryExecution().optimizedPlan().stats().sizeInBytes()))
    return F.broadcast(df) if size <= most else df


def overlaps(left: DataFrame, right: DataFrame, width: int, begin: Column, end: Column, begin2: Column, end2: Column, on: tuple[str, ...] = ()) -> DataFrame:
    """Rows that agree in ``on`` and whose closed ranges of integers meet: both go to the cells of ``width`` that they touch, and a pair is met in the first cell they share."""
    cells = lambda a, z: F.explode(F.sequence(F.floor(a / width), F.floor(z / width)))
    a = left.withColumns({"_a": begin, "_z": end}).withColumn("_cell", cells(F.col("_a"), F.col("_z")))
    b = right.withColumns({"_a2": begin2, "_z2": end2}).withColumn("_cell", cells(F.col("_a2"), F.col("_z2")))
    met = a.join(b, [*on, "_cell"]).where("_a <= _z2 AND _a2 <= _z")
    return met.where(F.col("_cell") == F.floor(F.greatest("_a", "_a2") / width)).drop("_cell", "_a", "_z", "_a2", "_z2")


def interval_orders(s: SparkSession, d: str) -> DataFrame:
    """Orders of one customer placed within 30 days of each other."""
    o = read(s, d, "orders", "o_orderkey", "o_custkey", F.datediff("o_orderdate", F.lit("1970-01-01").cast("date")).alias("day"))
    a, b = o.select("o_custkey", F.col("o_orderkey").alias("a"), F.col("day").alias("da")), o.select("o_custkey", F.col("o_orderkey").alias("b"), F.col("day").alias("db"))
    return overlaps(a, b, 30, F.col("da"), F.col("da") + 30, F.col("db"), F.col("db"), ("o_custkey",)).where("a <> b").select("a", "b")


def queries() -> dict[str, Query]:
    return {
        "rel_join_broadcast": lambda s, d: read(s, d, "customer", "c_custkey", "c_nationkey").join(send_if_small(read(s, d, "nation", "n_nationkey", "n_name")), F.col("c_nationkey") == F.col("n_nationkey")).groupBy("n_name").agg(F.count(F.lit(1)).alias("n")),
        "rel_join_shuffled_hash": lambda s, d: read(s, d, "orders", "o_orderkey", "o_custkey").join(read(s, d, "customer", "c_custkey", "c_mktsegment").hint("shuffle_hash"), F.col("o_custkey") == F.col("c_custkey")).groupBy("c_mktsegment").agg(F.count(F.lit(1)).alias("n")),
        "rel_join_sort_merge": lambda s, d: read(s, d, "lineitem", "l_orderkey", "l_quantity").join(read(s, d, "orders", "o_orderkey", "o_orderpriority").hint("merge"), F.col("l_orderkey") == F.col("o_orderkey")).groupBy("o_orderpriority").agg(F.sum("l_quantity").cast("double").alias("quantity")),
        "rel_join_full_outer": lambda s, d: read(s, d, "documents", "doc_id").join(read(s, d, "labels", "doc_id", "quality"), "doc_id", "full_outer").groupBy("quality").agg(F.count(F.lit(1)).alias("n")),
        "rel_join_left_semi": lambda s, d: read(s, d, "customer", "c_custkey").join(read(s, d, "orders", "o_custkey"), F.col("c_custkey") == F.col("o_custkey"), "left_semi"),
        "rel_join_interval": interval_orders,
        "rel_join_theta_vectors": lambda s, d: (lambda e: e.alias("a").join(e.alias("b"), (F.col("a.label") == F.col("b.label")) & (F.col("a.vec_id") < F.col("b.vec_id")) & (l2("a.v", "b.v") <= 1.2)).select(F.col("a.vec_id").alias("id_lo"), F.col("b.vec_id").alias("id_hi")))(embeddings(s, d)),
        "rel_join_null_safe": lambda s, d: (lambda e: e.select(F.nullif(F.col("quality"), F.lit(0)).alias("q")).groupBy("q").agg(F.count(F.lit(1)).alias("n")).alias("a").join(e.select(F.nullif(F.col("toxic"), F.lit(0)).alias("t")).groupBy("t").agg(F.count(F.lit(1)).alias("m")).alias("b"), F.col("q").eqNullSafe(F.col("t"))).select("q", "n", "m"))(read(s, d, "labels")),
        "rel_rollup_lines": lambda s, d: read(s, d, "lineitem").rollup("l_returnflag", "l_linestatus").agg(F.count(F.lit(1)).alias("n"), F.grouping_id().cast("int").alias("level")),
        "rel_grouping_sets": lambda s, d: read(s, d, "documents").groupingSets([("lang",), ("source",), ()], "lang", "source").agg(F.count(F.lit(1)).alias("n")).select("lang", "source", "n"),
        "rel_pivot_events": lambda s, d: read(s, d, "events").groupBy("user_id").pivot("event_type", ["purchase", "view"]).agg(F.count(F.lit(1))).select("user_id", F.coalesce("purchase", F.lit(0)).alias("purchases"), F.coalesce("view", F.lit(0)).alias("views")).where("purchases + views > 0"),
        "rel_median_price": lambda s, d: read(s, d, "orders").groupBy("o_orderpriority").agg(F.round(F.percentile(F.col("o_totalprice").cast("double"), F.lit(0.5)), 4).alias("median")),
        "rel_window_rank": lambda s, d: read(s, d, "part", "p_partkey", "p_brand", "p_retailprice").withColumns({"rank": F.rank().over(w := Window.partitionBy("p_brand").orderBy(F.col("p_retailprice").desc())), "dense": F.dense_rank().over(w)}).select("p_partkey", "rank", "dense"),
        "rel_window_lag": lambda s, d: read(s, d, "events").select("event_id", F.lag("event_type").over(Window.partitionBy("user_id").orderBy("ts", "event_id")).alias("before")),
        "rel_running_sum": lambda s, d: read(s, d, "orders").select("o_orderkey", F.round(F.sum(F.col("o_totalprice").cast("double")).over(Window.partitionBy("o_custkey").orderBy("o_orderdate", "o_orderkey").rowsBetween(Window.unboundedPreceding, 0)), 3).alias("so_far")),
        "rel_union_keys": lambda s, d: read(s, d, "customer", F.col("c_nationkey").alias("k")).union(read(s, d, "supplier", F.col("s_nationkey").alias("k"))).distinct(),
        "rel_intersect_keys": lambda s, d: read(s, d, "documents", "doc_id").intersect(read(s, d, "labels", "doc_id")),
        "rel_except_all": lambda s, d: read(s, d, "customer", F.col("c_nationkey").alias("k")).exceptAll(read(s, d, "supplier", F.col("s_nationkey").alias("k"))),
        "rel_explode_words": lambda s, d: read(s, d, "benchmark").select(F.explode(F.split(F.lower("text"), " ")).alias("word")).groupBy("word").agg(F.count(F.lit(1)).alias("n")).where("n > 5"),
        "rel_having_users": lambda s, d: read(s, d, "events").groupBy("user_id").agg(F.count_distinct("event_type").alias("kinds"), F.max("value").alias("most")).where("kinds >= 3").select("user_id", "kinds", F.round("most", 4).alias("most")),
        "rel_date_parts": lambda s, d: read(s, d, "orders").groupBy(F.year("o_orderdate").alias("y"), F.quarter("o_orderdate").alias("q")).agg(F.count(F.lit(1)).alias("n")),
    }


def oracle_sql() -> dict[str, str]:
    return {
        "rel_join_broadcast": "SELECT n_name, count(*) AS n FROM customer JOIN nation ON c_nationkey = n_nationkey GROUP BY n_name",
        "rel_join_shuffled_hash": "SELECT c_mktsegment, count(*) AS n FROM orders JOIN customer ON o_custkey = c_custkey GROUP BY 1",
        "rel_join_sort_merge": "SELECT o_orderpriority, CAST(sum(l_quantity) AS DOUBLE) AS quantity FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY 1",
        "rel_join_full_outer": "SELECT quality, count(*) AS n FROM documents FULL JOIN labels USING (doc_id) GROUP BY 1",
        "rel_join_left_semi": "SELECT c_custkey FROM customer WHERE c_custkey IN (SELECT o_custkey FROM orders)",
        "rel_join_interval": "SELECT a.o_orderkey AS a, b.o_orderkey AS b FROM orders a JOIN orders b ON a.o_custkey = b.o_custkey AND a.o_orderkey <> b.o_orderkey AND CAST(b.o_orderdate AS DATE) BETWEEN CAST(a.o_orderdate AS DATE) AND CAST(a.o_orderdate AS DATE) + 30",
        "rel_join_theta_vectors": "WITH e AS (SELECT vec_id, label, CAST(embedding AS DOUBLE[]) AS v FROM embeddings) SELECT a.vec_id AS id_lo, b.vec_id AS id_hi FROM e a JOIN e b ON a.label = b.label AND a.vec_id < b.vec_id AND list_distance(a.v, b.v) <= 1.2",
        "rel_join_null_safe": "SELECT q, n, m FROM (SELECT nullif(quality, 0) AS q, count(*) AS n FROM labels GROUP BY 1) JOIN (SELECT nullif(toxic, 0) AS t, count(*) AS m FROM labels GROUP BY 1) ON q IS NOT DISTINCT FROM t",
        "rel_rollup_lines": "SELECT l_returnflag, l_linestatus, count(*) AS n, CAST(grouping(l_returnflag, l_linestatus) AS INT) AS level FROM lineitem GROUP BY ROLLUP (l_returnflag, l_linestatus)",
        "rel_grouping_sets": "SELECT lang, source, count(*) AS n FROM documents GROUP BY GROUPING SETS ((lang), (source), ())",
        "rel_pivot_events": "SELECT user_id, count(*) FILTER (event_type = 'purchase') AS purchases, count(*) FILTER (event_type = 'view') AS views FROM events GROUP BY user_id HAVING purchases + views > 0",
        "rel_median_price": "SELECT o_orderpriority, round(quantile_cont(CAST(o_totalprice AS DOUBLE), 0.5), 4) AS median FROM orders GROUP BY 1",
        "rel_window_rank": "SELECT p_partkey, CAST(rank() OVER w AS INT) AS rank, CAST(dense_rank() OVER w AS INT) AS dense FROM part WINDOW w AS (PARTITION BY p_brand ORDER BY p_retailprice DESC)",
        "rel_window_lag": "SELECT event_id, lag(event_type) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS before FROM events",
        "rel_running_sum": "SELECT o_orderkey, round(sum(CAST(o_totalprice AS DOUBLE)) OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey ROWS UNBOUNDED PRECEDING), 3) AS so_far FROM orders",
        "rel_union_keys": "SELECT c_nationkey AS k FROM customer UNION SELECT s_nationkey FROM supplier",
        "rel_intersect_keys": "SELECT doc_id FROM documents INTERSECT SELECT doc_id FROM labels",
        "rel_except_all": "SELECT c_nationkey AS k FROM customer EXCEPT ALL SELECT s_nationkey FROM supplier",
        "rel_explode_words": "SELECT word, count(*) AS n FROM (SELECT unnest(string_split(lower(text), ' ')) AS word FROM benchmark) GROUP BY word HAVING count(*) > 5",
        "rel_having_users": "SELECT user_id, count(DISTINCT event_type) AS kinds, round(max(value), 4) AS most FROM events GROUP BY user_id HAVING count(DISTINCT event_type) >= 3",
        "rel_date_parts": "SELECT CAST(year(CAST(o_orderdate AS DATE)) AS INT) AS y, CAST(quarter(CAST(o_orderdate AS DATE)) AS INT) AS q, count(*) AS n FROM orders GROUP BY 1, 2",
    }
