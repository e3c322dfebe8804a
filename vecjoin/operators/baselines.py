"""What the bucket join is compared with."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.proximity import ProximityGraph, near_links
from ..functions.vectors import close_pairs, count_close, dot
from ..sources.storage import stored
from .bucketize import matrix, sample_centers

PAIRS = "id_lo long, id_hi long, dist double"


def exact_join(vectors: DataFrame, eps: float) -> DataFrame:
    """All pairs within ``eps``, every distance computed; the yardstick. Blocks of rows meet as matrix products."""
    return exact_join_blocks(vectors, eps)


def exact_count(vectors: DataFrame, eps: float, parts: int = 8) -> DataFrame:
    """One row n: the number of pairs within ``eps``, every distance computed and no pair held."""
    return exact_join_blocks(vectors, eps, parts, counts=True).agg(F.coalesce(F.sum("n"), F.lit(0)).alias("n"))


def exact_join_blocks(vectors: DataFrame, eps: float, parts: int = 8, counts: bool = False) -> DataFrame:
    """All pairs within ``eps``: rows are dealt to ``parts`` blocks, and each pair of blocks is a task. With ``counts`` a task tells their number."""
    dealt = vectors.select("vec_id", "v", F.pmod(F.xxhash64("vec_id"), F.lit(parts)).cast("int").alias("own"))
    paired = dealt.withColumn("other", F.explode(F.sequence(F.lit(0), F.lit(parts - 1)))).select("vec_id", "v", "own", F.least("own", "other").alias("p"), F.greatest("own", "other").alias("q"))

    def compare(table: pa.Table) -> pa.Table:
        own, ids, x = table["own"].to_numpy(), table["vec_id"].to_numpy(), matrix(table["v"].combine_chunks())
        p, q = table["p"][0].as_py(), table["q"][0].as_py()
        a, b = own == p, own == q
        if counts:
            return pa.table({"n": pa.array([count_close(x[a], None if p == q else x[b], eps)], pa.int64())})
        i, j, d = close_pairs(x[a], None if p == q else x[b], eps)
        left, right = ids[a][i], ids[b][j]
        return pa.table({"id_lo": np.minimum(left, right), "id_hi": np.maximum(left, right), "dist": d})

    return paired.groupBy("p", "q").applyInArrow(compare, "n long" if counts else PAIRS)


def cell_replication_join(vectors: DataFrame, eps: float, anchors: int, seed: int = 42) -> DataFrame:
    """Exact join by cells of nearest anchors: a vector is copied to every cell whose border is within ``eps``, and cells are joined alone."""
    held = sample_centers(vectors, anchors, seed).orderBy("bucket_id").collect()  # the anchors' number is a parameter
    c = np.array([r["center"] for r in held], dtype=float)
    apart = np.sqrt(np.maximum(((c[:, None, :] - c[None, :, :]) ** 2).sum(axis=2), 0))

    def deal(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            x = matrix(batch.column(1))
            sq = np.maximum((x * x).sum(axis=1)[:, None] + (c * c).sum(axis=1)[None, :] - 2 * x @ c.T, 0)
            home = sq.argmin(axis=1)
            gap = sq - sq[np.arange(len(x)), home][:, None]
            border = np.divide(gap, 2 * apart[home], out=np.zeros_like(gap), where=apart[home] > 0)
            row, cell = np.nonzero(border <= eps + 1e-7)
            take = pa.array(row)
            yield pa.RecordBatch.from_arrays([pa.array(cell.astype(np.int32)), pa.array(home[row].astype(np.int32)), batch.column(0).take(take), batch.column(1).take(take)], names=["cell", "home", "vec_id", "v"])

    dealt = vectors.select("vec_id", "v").mapInArrow(deal, "cell int, home int, vec_id long, v array<double>")

    def join(table: pa.Table) -> pa.Table:
        cell, home = table["cell"][0].as_py(), table["home"].to_numpy()
        ids, x = table["vec_id"].to_numpy(), matrix(table["v"].combine_chunks())
        own, guest = home == cell, home > cell  # a pair of two homes is seen in both cells; the smaller one tells it
        parts = [(ids[own], x[own], None, None), (ids[own], x[own], ids[guest], x[guest])]
        lo, hi, dist = [], [], []
        for a, xa, b, xb in parts:
            i, j, d = close_pairs(xa, xb, eps)
            left, right = a[i], (a if b is None else b)[j]
            lo.append(np.minimum(left, right)), hi.append(np.maximum(left, right)), dist.append(d)
        return pa.table({"id_lo": np.concatenate(lo), "id_hi": np.concatenate(hi), "dist": np.concatenate(dist)})

    return dealt.groupBy("cell").applyInArrow(join, PAIRS)


def lsh_join(vectors: DataFrame, eps: float, tables: int = 8, hashes: int = 4, width: float | None = None, seed: int = 42, rows: int = 8192) -> DataFrame:
    """Vectors that share a bucket of random projections in any table, verified: a part of the exact join."""
    d = vectors.select(F.size("v")).first()[0]
    rng = np.random.default_rng(seed)
    w = width or 4 * eps
    planes, shift = rng.normal(size=(tables * hashes, d)), rng.random(tables * hashes) * w

    def keys(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            cell = np.floor((matrix(batch.column(1)) @ planes.T + shift) / w).astype(np.int64).reshape(batch.num_rows, tables, hashes)
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(cell.tolist(), pa.list_(pa.list_(pa.int64())))], names=["vec_id", "v", "cells"])

    keyed = vectors.select("vec_id", "v").mapInArrow(keys, "vec_id long, v array<double>, cells array<array<long>>").select("vec_id", "v", F.posexplode("cells").alias("t", "cell"))
    # the vectors of a cell meet as matrix products, those of a large one block by block; only verified pairs leave a task
    size = keyed.groupBy("t", "cell").agg(F.ceil(F.count(F.lit(1)) / rows).cast("int").alias("n"), F.count(F.lit(1)).alias("size")).where("size > 1").drop("size")
    dealt = keyed.join(size, ["t", "cell"]).withColumn("own", F.pmod(F.xxhash64("vec_id"), F.col("n")).cast("int"))
    paired = dealt.withColumn("other", F.explode(F.sequence(F.lit(0), F.col("n") - 1))).select("t", "cell", F.least("own", "other").alias("i"), F.greatest("own", "other").alias("j"), "own", "vec_id", "v")

    def compare(table: pa.Table) -> pa.Table:
        ids, x, i, j = table["vec_id"].to_numpy(), matrix(table["v"].combine_chunks()), table["i"][0].as_py(), table["j"][0].as_py()
        left, right = (table["own"].to_numpy() == k for k in (i, j))
        p, q, dist = close_pairs(x[left], None if i == j else x[right], eps)
        a, b = ids[left][p], ids[right][q]
        return pa.table({"id_lo": np.minimum(a, b), "id_hi": np.maximum(a, b), "dist": dist})

    return paired.groupBy("t", "cell", "i", "j").applyInArrow(compare, PAIRS).groupBy("id_lo", "id_hi").agg(F.min("dist").alias("dist"))


def knn_join(vectors: DataFrame, k: int, parts: int = 8) -> DataFrame:
    """(vec_id, rank, neighbor, dist) of the k nearest others of every vector, exactly; of equally near ones the smaller id first.

    Rows are dealt to ``parts`` blocks; each ordered pair of blocks is a task that tells the k nearest within the second block.
    """
    from pyspark.sql import Window

    dealt = vectors.select("vec_id", "v", F.pmod(F.xxhash64("vec_id"), F.lit(parts)).cast("int").alias("own"))
    asks = dealt.select(F.col("own").alias("p"), F.explode(F.sequence(F.lit(0), F.lit(parts - 1))).alias("q"), F.lit(True).alias("asks"), "vec_id", "v")
    holds = dealt.select(F.explode(F.sequence(F.lit(0), F.lit(parts - 1))).alias("p"), F.col("own").alias("q"), F.lit(False).alias("asks"), "vec_id", "v")

    def nearest_in(table: pa.Table) -> pa.Table:
        ids, x, asking = table["vec_id"].to_numpy(), matrix(table["v"].combine_chunks()), table["asks"].to_numpy()
        return k_nearest(ids[asking], x[asking], ids[~asking], x[~asking], k)

    near = asks.union(holds).groupBy("p", "q").applyInArrow(nearest_in, "vec_id long, neighbor long, dist double")
    return near.withColumn("rank", F.row_number().over(Window.partitionBy("vec_id").orderBy("dist", "neighbor"))).where(F.col("rank") <= k)


def k_nearest(ids: np.ndarray, x: np.ndarray, other: np.ndarray, y: np.ndarray, k: int, rows: int = 256) -> pa.Table:
    """(vec_id, neighbor, dist) of the k rows of ``y`` nearest to each row of ``x`` but itself: a matrix product proposes, with slack for its rounding, and differences decide."""
    found: list[tuple[np.ndarray, np.ndarray, np.ndarray]] = [(np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0))]
    sq = (y * y).sum(axis=1)
    for at in range(0, len(x) if len(y) else 0, rows):
        block = x[at : at + rows]
        own = (block * block).sum(axis=1)
        score = own[:, None] + sq[None, :] - 2 * block @ y.T
        score[ids[at : at + rows, None] == other[None, :]] = np.inf
        bound = np.partition(score, min(k, len(y)) - 1, axis=1)[:, min(k, len(y)) - 1]
        slack = 256 * np.finfo(float).eps * (x.shape[1] ** 0.5 + 1) * (own + sq.max())
        r, c = np.nonzero((score <= (bound + slack)[:, None]) & (score < np.inf))
        d = np.sqrt(((block[r] - y[c]) ** 2).sum(axis=1))
        order = np.lexsort((other[c], d, r))
        r, c, d = r[order], c[order], d[order]
        keep = np.arange(len(r)) - np.searchsorted(r, r) < k
        found.append((ids[at + r[keep]], other[c[keep]], d[keep]))
    return pa.table({name: np.concatenate([f[i] for f in found]) for i, name in enumerate(("vec_id", "neighbor", "dist"))})


def graph_probe_join(vectors: DataFrame, eps: float, k: int, beam: int = 48, degree: int = 16, parts: int = 4, graphs: DataFrame | None = None) -> DataFrame:
    """Every vector asks a proximity graph for its k nearest and keeps those within ``eps``: one graph for each part of the data, every query sent to all parts.

    Recall rises with k, which bounds how many partners a query can find in a part.
    """
    return graph_probe_ranks(vectors, eps, k, beam, degree, parts, graphs=graphs).drop("place")


def probe_graphs(vectors: DataFrame, degree: int = 16, parts: int = 4, shares: int = 8) -> DataFrame:
    """Rows (part, at, vec_id, v, near) of one proximity graph for each part: place and near neighbours' places. Each of ``shares`` tasks of a part finds the neighbours of a run of its nodes."""
    dealt = vectors.select(F.pmod(F.xxhash64("vec_id"), F.lit(parts)).cast("int").alias("part"), F.explode(F.sequence(F.lit(0), F.lit(shares - 1))).alias("share"), "vec_id", "v")

    def link(table: pa.Table) -> pa.Table:
        ids, x = table["vec_id"].to_numpy(), matrix(table["v"].combine_chunks())
        order = np.lexsort([*x.T[::-1], ids])  # the same in every share
        ids, x, share = ids[order], x[order], table["share"][0].as_py()
        a, z = len(ids) * share // shares, len(ids) * (share + 1) // shares
        near = near_links(x, a, z, degree)
        return pa.table({"part": pa.array([table["part"][0].as_py()] * (z - a), pa.int32()), "at": pa.array(np.arange(a, z)), "vec_id": pa.array(ids[a:z], pa.int64()), "v": pa.array(list(x[a:z]), pa.list_(pa.float64())), "near": pa.array(near, pa.list_(pa.int32()))})

    return _by_task(dealt, shares, parts, link, "part int, at long, vec_id long, v array<double>, near array<int>")


def _by_task(dealt: DataFrame, shares: int, parts: int, work: Callable[[pa.Table], pa.Table], schema: str) -> DataFrame:
    """``work`` on the rows of each (part, share), every one of them a task: dealt by hash some tasks would have several, and adaptive execution would merge them."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held = [b for b in batches if b.num_rows]
        if held:
            yield from work(pa.Table.from_batches(held)).to_batches()

    return dealt.repartitionById(parts * shares, F.col("part") * shares + F.col("share")).mapInArrow(run, schema)


def graph_probe_ranks(vectors: DataFrame, eps: float, k: int, beam: int = 48, degree: int = 16, parts: int = 4, shares: int = 8, graphs: DataFrame | None = None) -> DataFrame:
    """The pairs of ``graph_probe_join`` with ``place``: the smallest k that finds them, if the beam is no shorter than k + 1. The queries to a part are dealt to ``shares`` tasks.

    ``graphs``: stored rows of ``probe_graphs``, for several calls.
    """
    graphs = stored(probe_graphs(vectors, degree, parts, shares)) if graphs is None else graphs
    asks = vectors.select(F.explode(F.sequence(F.lit(0), F.lit(parts - 1))).alias("part"), F.pmod(F.xxhash64("vec_id", F.lit(3)), F.lit(shares)).cast("int").alias("share"), F.lit(-1).cast("long").alias("at"), "vec_id", "v", F.lit(None).cast("array<int>").alias("near"))
    holds = graphs.select("part", F.explode(F.sequence(F.lit(0), F.lit(shares - 1))).alias("share"), "at", "vec_id", "v", "near")

    def probe(table: pa.Table) -> pa.Table:
        at = table["at"].to_numpy()
        ids, x, asking = table["vec_id"].to_numpy(), matrix(table["v"].combine_chunks()), np.flatnonzero(at < 0)
        nodes = np.flatnonzero(at >= 0)
        nodes = nodes[np.argsort(at[nodes])]
        graph, own, q = ProximityGraph(x[nodes], degree, near=table["near"].take(pa.array(nodes)).to_pylist()), ids[nodes], x[asking]
        out = [np.zeros(0, np.int64)], [np.zeros(0, np.int64)], [np.zeros(0)], [np.zeros(0, np.int64)]
        for row, node, square in graph.search_many(q, k + 1, beam, limit=eps * eps * (1 + 1e-9)) if len(own) else ():
            head = np.append(True, row[1:] != row[:-1])
            place = np.arange(len(row)) - np.flatnonzero(head)[np.cumsum(head) - 1]
            me, other, dist = ids[asking][row], own[node], np.sqrt(square)
            keep = (dist <= eps) & (me != other)
            for c, v in zip(out, (np.minimum(me, other), np.maximum(me, other), dist, place), strict=True):
                c.append(v[keep])
        return pa.table(dict(zip(("id_lo", "id_hi", "dist", "place"), map(np.concatenate, out), strict=True)))

    found = _by_task(asks.unionByName(holds), shares, parts, probe, PAIRS + ", place long")
    return found.groupBy("id_lo", "id_hi").agg(F.min("dist").alias("dist"), F.min("place").alias("place"))


def band_join(vectors: DataFrame, eps: float, seed: int = 42, rows: int = 16_384) -> DataFrame:
    """Exact join with a one-dimensional prefilter: projections on a unit direction of close vectors differ by at most ``eps``.

    Cells of width ``eps`` are dealt to blocks of about ``rows``; a block meets those of its own cell and of the next one.
    """
    d = vectors.select(F.size("v")).first()
    if d is None:
        return vectors.sparkSession.createDataFrame([], PAIRS)
    u = np.random.default_rng(seed).normal(size=d[0])
    u /= np.sqrt((u * u).sum())
    direction = F.array(*(F.lit(float(c)) for c in u))
    keyed = vectors.select("vec_id", "v", F.floor(dot("v", direction) / (eps * (1 + 1e-9))).alias("cell"))
    size = keyed.groupBy("cell").agg(F.ceil(F.count(F.lit(1)) / rows).cast("int").alias("n"))
    after = size.select((F.col("cell") - 1).alias("cell"), F.col("n").alias("n_next"))
    before = size.select((F.col("cell") + 1).alias("cell"), F.col("n").alias("n_before"))
    dealt = keyed.join(size, "cell").join(after, "cell", "left").join(before, "cell", "left").withColumn("own", F.pmod(F.xxhash64("vec_id"), F.col("n")).cast("int"))
    # (cell, block, whether the other block is of the next cell, that block): left and right of a task
    met = lambda cell, i, ahead, j, left: F.struct(cell.alias("cell"), i.cast("int").alias("i"), F.lit(ahead).alias("ahead"), j.cast("int").alias("j"), F.lit(left).alias("left"))
    each = lambda n: F.when(F.coalesce(n, F.lit(0)) > 0, F.sequence(F.lit(0), n - 1)).otherwise(F.array().cast("array<int>"))
    own, cell = F.col("own"), F.col("cell")
    tasks = F.concat(
        F.transform(F.sequence(own, F.col("n") - 1), lambda j: met(cell, own, False, j, True)),
        F.transform(F.filter(each(F.col("n")), lambda i: i < own), lambda i: met(cell, i, False, own, False)),
        F.transform(each(F.col("n_next")), lambda j: met(cell, own, True, j, True)),
        F.transform(each(F.col("n_before")), lambda i: met(cell - 1, i, True, own, False)),
    )

    def compare(table: pa.Table) -> pa.Table:
        ids, x, left = table["vec_id"].to_numpy(), matrix(table["v"].combine_chunks()), table["left"].to_numpy()
        alone = not table["ahead"][0].as_py() and table["i"][0].as_py() == table["j"][0].as_py()
        a, b, dist = close_pairs(x[left], None if alone else x[~left], eps)
        p, q = ids[left][a], (ids[left] if alone else ids[~left])[b]
        return pa.table({"id_lo": np.minimum(p, q), "id_hi": np.maximum(p, q), "dist": dist})

    return dealt.select("vec_id", "v", F.explode(tasks).alias("t")).select("t.*", "vec_id", "v").groupBy("cell", "i", "ahead", "j").applyInArrow(compare, PAIRS)


class ProductCodes:
    """Vectors as one byte for each of ``parts`` slices: the nearest of up to 256 words of the slice's book, learned by a few rounds of means on a bounded sample."""

    def __init__(self, sample: np.ndarray, parts: int = 8, words: int = 256, rounds: int = 8, seed: int = 42):
        rng = np.random.default_rng(seed)
        self.slices = np.array_split(np.arange(sample.shape[1]), parts)
        self.books = []
        for at in self.slices:
            x = sample[:, at]
            book = x[rng.permutation(len(x))[:words]].copy()
            for _ in range(rounds):
                near = self._near(x, book)
                for w in np.unique(near):
                    book[w] = x[near == w].mean(axis=0)
            self.books.append(book)

    @staticmethod
    def _near(x: np.ndarray, book: np.ndarray) -> np.ndarray:
        return ((book * book).sum(axis=1)[None, :] - 2 * x @ book.T).argmin(axis=1)

    def encode(self, x: np.ndarray) -> np.ndarray:
        return np.column_stack([self._near(x[:, at], book) for at, book in zip(self.slices, self.books, strict=True)]).astype(np.uint8)

    def distances(self, q: np.ndarray, codes: np.ndarray) -> np.ndarray:
        """Squared distances of one uncoded query to coded vectors, by a table for each slice."""
        return sum(((book - q[at]) ** 2).sum(axis=1)[codes[:, s]] for s, (at, book) in enumerate(zip(self.slices, self.books, strict=True)))


def code_probe_join(vectors: DataFrame, eps: float, k: int, code_bytes: int = 8, words: int = 256, sample: int = 10_000, parts: int = 4, ask: float = 1.0) -> DataFrame:
    """Every vector ranks the codes of each part of the data, and its ``k`` best there are verified; few code bytes cap the recall.

    ``ask`` takes that share of the queries by hash, for estimates of time or recall. The books come from at most ``sample`` vectors.
    """
    seen = vectors.orderBy(F.md5(F.col("vec_id").cast("string")), "vec_id").limit(sample).select("v").collect()  # bounded by a parameter
    if not seen:
        return vectors.sparkSession.createDataFrame([], PAIRS)
    codes = ProductCodes(np.array([r[0] for r in seen], dtype=float), code_bytes, words)
    dealt = vectors.select("vec_id", "v", F.pmod(F.xxhash64("vec_id"), F.lit(parts)).cast("int").alias("own"), (F.pmod(F.xxhash64("vec_id", F.lit(5)), F.lit(1_000_000)) < ask * 1_000_000).alias("asks"))
    sent = dealt.withColumn("part", F.explode(F.sequence(F.lit(0), F.lit(parts - 1)))).where("asks OR own = part")

    def probe(table: pa.Table) -> pa.Table:
        ids, x, mine = table["vec_id"].to_numpy(), matrix(table["v"].combine_chunks()), table["own"].to_numpy() == table["part"][0].as_py()
        own, held, coded = ids[mine], x[mine], codes.encode(x[mine])
        lo, hi, dist = [], [], []
        for i in np.flatnonzero(table["asks"].to_numpy()) if len(own) else ():
            guess = codes.distances(x[i], coded)
            take = np.argpartition(guess, min(k, len(guess) - 1))[: k + 1]
            d = np.sqrt(((held[take] - x[i]) ** 2).sum(axis=1))
            for j, e in zip(take[d <= eps].tolist(), d[d <= eps].tolist(), strict=True):
                if own[j] != ids[i]:
                    lo.append(min(ids[i], own[j])), hi.append(max(ids[i], own[j])), dist.append(e)
        return pa.table({"id_lo": pa.array(lo, pa.int64()), "id_hi": pa.array(hi, pa.int64()), "dist": pa.array(dist, pa.float64())})

    return sent.groupBy("part").applyInArrow(probe, PAIRS).groupBy("id_lo", "id_hi").agg(F.min("dist").alias("dist"))


def tune_k(vectors: DataFrame, eps: float, wanted: float, exact: DataFrame, limit: int = 1024) -> tuple[int, float]:
    """The first k of 1, 2, 4, ... at which the graph probe's recall of the ``exact`` pairs reaches ``wanted``, and that recall (of ``limit`` where none does)."""
    exact, beam = stored(exact), 48
    graphs = stored(probe_graphs(vectors))
    pairs = exact.select("id_lo", "id_hi").distinct()
    n, k = pairs.count(), 1
    # every k below the beam walks the graph alike
    known = {r["place"]: r["count"] for r in pairs.join(graph_probe_ranks(vectors, eps, beam - 1, beam, graphs=graphs), ["id_lo", "id_hi"]).groupBy("place").count().collect()}
    while True:
        found = sum(c for place, c in known.items() if place <= k) if k < beam else pairs.join(graph_probe_join(vectors, eps, k, beam, graphs=graphs), ["id_lo", "id_hi"]).count()
        got = found / n if n else 1.0
        if got >= wanted or k >= limit:
            return k, got
        k *= 2
