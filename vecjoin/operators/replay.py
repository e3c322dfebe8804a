"""Joins of a stored layout: tasks follow a planned order and load blocks from disk as a cache plan says."""

from __future__ import annotations

import time

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..config import JoinConfig
from ..functions.vectors import close_pairs, count_close
from ..plans import graph, orchestrate
from ..sources.storage import Manifest, StoredLayout, open_files, read_extent, store, write_extents
from .join import PAIRS, build_layout, memory_slots, plan_segments

COUNTS = "run long, tasks long, loads long, hits long, reads long, read_bytes long, page_bytes long, used_bytes long, distances long, pairs long, io_seconds double, compute_seconds double"
PAGE = 4096
#: A run ends after about so many distances; the next one begins with an empty cache.
RUN_DISTANCES = 1 << 28


def write_layout(vectors: DataFrame, cfg: JoinConfig, path: str, mode: str = "clustered", piece_bytes: int | None = None) -> StoredLayout:
    """Buckets, extents and a manifest under ``path``; neither distance nor recall has a part in them."""
    layout = build_layout(vectors, cfg)
    places = write_extents(layout.assigned, path, layout.d, mode, piece_bytes, cfg.block_rows)
    return store(vectors.sparkSession, path, layout.buckets, places, Manifest(layout.d, layout.n, cfg.metric, cfg.seed, mode, piece_bytes, cfg.block_rows))


def _replay(stored: StoredLayout, cfg: JoinConfig, run_tasks: int, counts: bool) -> DataFrame:
    edges = graph.bucket_graph(stored.buckets, cfg, stored.manifest.d)
    slots = memory_slots(stored.buckets, cfg)
    planned = plan_segments(edges, stored.buckets, cfg).withColumn("part", F.shiftright("seg", 32)).drop("seg")
    parts = stored.places.groupBy("bucket_id").agg((F.max("block_no") + 1).alias("parts"), F.sum("n").alias("size"))
    # a bucket of many blocks is met block by block, and its tasks go to runs of their own
    sized = planned.join(parts.select(F.col("bucket_id").alias("i"), F.col("parts").alias("pi"), F.col("size").alias("ni")), "i").join(parts.select(F.col("bucket_id").alias("j"), F.col("parts").alias("pj"), F.col("size").alias("nj")), "j")
    before = F.coalesce(F.sum(F.col("ni") * F.col("nj")).over(Window.partitionBy("part").orderBy("seq").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    sized = sized.withColumn("stretch", F.floor(before / RUN_DISTANCES)).withColumn("at", F.floor(F.col("seq") / run_tasks))
    met = sized.withColumn("bi", F.explode(F.sequence(F.lit(0), F.col("pi") - 1))).withColumn("bj", F.explode(F.sequence(F.lit(0), F.col("pj") - 1))).where("i <> j OR bi <= bj")
    block_tasks = max(1, min(run_tasks, RUN_DISTANCES // stored.manifest.block_rows**2))
    chunk = F.floor((F.col("bi") * F.col("pj") + F.col("bj")) / block_tasks)
    tasks = met.withColumn("run", F.xxhash64("part", "at", "stretch", chunk)).select("run", "seq", "i", "bi", "j", "bj")
    # by number, or the few bytes that describe all the runs would be merged into one task
    spread = int(tasks.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    need = tasks.select("run", F.explode(F.array(F.struct(F.col("i").alias("b"), F.col("bi").alias("k")), F.struct(F.col("j").alias("b"), F.col("bj").alias("k")))).alias("u")).distinct()
    located = need.select("run", F.col("u.b").alias("bucket_id"), F.col("u.k").alias("block_no")).join(stored.places, ["bucket_id", "block_no"])
    found = located.select(F.col("run").alias("for_run"), "bucket_id", "block_no", "file", "offset", "length", "n")
    eps, policy, pin, path = cfg.distance, cfg.policy, cfg.pin_partner, stored.path

    def run(left: pa.Table, right: pa.Table) -> pa.Table:
        files, root = open_files(path)
        # extents stay columns, as scattered buckets have one for each vector
        right = right.sort_by([(c, "ascending") for c in ("bucket_id", "block_no", "file", "offset")])
        unit = np.column_stack([right[c].to_numpy() for c in ("bucket_id", "block_no")])
        head = np.flatnonzero(np.append(True, (unit[1:] != unit[:-1]).any(axis=1)))
        places = {(int(unit[h, 0]), int(unit[h, 1])): slice(h, e) for h, e in zip(head.tolist(), [*head[1:].tolist(), len(unit)], strict=True)}
        offset, length, rows = (right[c].to_numpy() for c in ("offset", "length", "n"))
        file = right["file"].combine_chunks().dictionary_encode()
        file, of = file.dictionary.to_pylist(), file.indices.to_numpy()
        left = left.sort_by([("seq", "ascending"), ("bi", "ascending"), ("bj", "ascending")])
        units = {u: n for n, u in enumerate(sorted(places))}
        names = list(units)
        todo = [(units[i, a], units[j, b]) for i, a, j, b in zip(*(left[c].to_pylist() for c in ("i", "bi", "j", "bj")), strict=True)]
        log, m = orchestrate.plan_cache(todo, slots, policy, pin)
        steps: dict[int, list[tuple]] = {}
        for t, op, u, _ in log:
            steps.setdefault(t, []).append((op, u))
        held: dict[int, tuple[np.ndarray, np.ndarray]] = {}
        lo, hi, dist = [np.zeros(0, np.int64)], [np.zeros(0, np.int64)], [np.zeros(0)]
        reads = read_bytes = page_bytes = distances = pairs = 0
        sources: dict[str, object] = {}
        io = compute = 0.0
        for t, (a, b) in enumerate(todo):
            began = time.perf_counter()
            for op, u in steps.get(t, ()):
                if op == "evict":
                    held.pop(u, None)
                    continue
                at = places[names[u]]
                got = [read_extent(files, root, file[f], o, n, r, sources) for f, o, n, r in zip(*(c[at].tolist() for c in (of, offset, length, rows)), strict=True)]
                held[u] = (np.concatenate([g[0] for g in got]), np.concatenate([g[1] for g in got]))
                reads += len(got)
                read_bytes += int(length[at].sum())
                page_bytes += int((-(-(offset[at] + length[at]) // PAGE) - offset[at] // PAGE).sum()) * PAGE
            between = time.perf_counter()
            ia, xa = held[a]
            ib, xb = held[b]
            distances += len(ia) * (len(ia) - 1) // 2 if a == b else len(ia) * len(ib)
            if counts:
                pairs += count_close(xa, None if a == b else xb, eps)
            else:
                p, q, d = close_pairs(xa, None if a == b else xb, eps)
                x, y = ia[p], ib[q]
                lo.append(np.minimum(x, y)), hi.append(np.maximum(x, y)), dist.append(d)
            io, compute = io + between - began, compute + time.perf_counter() - between
        for source in sources.values():
            source.close()
        if counts:
            row = (left["run"][0].as_py(), len(todo), m["loads"], m["hits"], reads, read_bytes, page_bytes, read_bytes, distances, pairs, io, compute)
            return pa.table({name.split()[0]: [v] for name, v in zip(COUNTS.split(", "), row, strict=True)})
        return pa.table({"id_lo": np.concatenate(lo), "id_hi": np.concatenate(hi), "dist": np.concatenate(dist)})

    return tasks.repartition(spread, "run").groupBy("run").cogroup(found.groupBy("for_run")).applyInArrow(run, COUNTS if counts else PAIRS)


def self_join_on(stored: StoredLayout, cfg: JoinConfig, run_tasks: int = 4096) -> DataFrame:
    """(id_lo, id_hi, dist) of a stored layout's pairs within the distance. A run of tasks keeps ``memory_fraction`` of the buckets, and reads each extent in one piece."""
    return _replay(stored, cfg, run_tasks, counts=False)


def replay_counts(stored: StoredLayout, cfg: JoinConfig, run_tasks: int = 4096) -> DataFrame:
    """One row per run of the same work: loads, hits, reads, bytes (also in whole pages), distances, pairs, and seconds of reading and of computing. Pairs are counted and not held."""
    return _replay(stored, cfg, run_tasks, counts=True)
