"""Functions for SQL: ``register`` adds them to a session.

``cosine_of(a, b)`` and ``l2_of(a, b)`` are Arrow functions over pairs of vectors. The table functions take ``TABLE(...) PARTITION BY (...)``:
``eps_neighbors(t, eps)`` with rows (vec_id, v) gives the pairs within ``eps`` inside each partition, which should be a bucket or a
block of one; ``cache_replay(t, slots, policy)`` with rows (seq, i, j), ordered by seq, gives what a plan loads and evicts.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import Row, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import DoubleType

from ..plans.orchestrate import plan_cache
from ..sources import vecs
from .vectors import close_pairs


@F.pandas_udf(DoubleType())
def l2_of(a: pd.Series, b: pd.Series) -> pd.Series:
    return pd.Series([None if x is None or y is None else float(np.sqrt(((np.asarray(x, float) - np.asarray(y, float)) ** 2).sum())) for x, y in zip(a, b, strict=True)], dtype=float)


@F.pandas_udf(DoubleType())
def cosine_of(a: pd.Series, b: pd.Series) -> pd.Series:
    def one(x: np.ndarray | None, y: np.ndarray | None) -> float | None:
        if x is None or y is None:
            return None
        size = float(np.sqrt(np.dot(x, x) * np.dot(y, y)))
        return float(np.dot(x, y)) / size if size else None

    return pd.Series([one(x, y) for x, y in zip(a, b, strict=True)], dtype=float)


class EpsNeighbors:
    def __init__(self) -> None:
        self.ids: list[int] = []
        self.rows: list[list[float]] = []
        self.eps = 0.0

    def eval(self, row: Row, eps: float) -> None:
        self.eps = float(eps)
        if row["vec_id"] is not None and row["v"] is not None:
            self.ids.append(row["vec_id"])
            self.rows.append(row["v"])

    def terminate(self) -> Iterator[tuple[int, int, float]]:
        if len(self.ids) > 1:
            p, q, d = close_pairs(np.array(self.rows, dtype=float), None, self.eps)
            for a, b, x in zip(p.tolist(), q.tolist(), d.tolist(), strict=True):
                yield min(self.ids[a], self.ids[b]), max(self.ids[a], self.ids[b]), x


class CacheReplay:
    def __init__(self) -> None:
        self.tasks: list[tuple[int, int]] = []
        self.settings = (2, "opt")

    def eval(self, row: Row, slots: int, policy: str) -> None:
        self.settings = (slots, policy)
        self.tasks.append((row["i"], row["j"]))

    def terminate(self) -> Iterator[tuple[int, str, int, int | None]]:
        yield from plan_cache(self.tasks, *self.settings)[0]


def register(spark: SparkSession) -> None:
    spark.udf.register("l2_of", l2_of)
    spark.udf.register("cosine_of", cosine_of)
    spark.udtf.register("eps_neighbors", F.udtf(EpsNeighbors, returnType="id_lo long, id_hi long, dist double"))
    spark.udtf.register("cache_replay", F.udtf(CacheReplay, returnType="task long, op string, bucket_id long, victim long"))
    vecs.register(spark)
