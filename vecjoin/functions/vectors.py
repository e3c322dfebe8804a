"""Vectors as array columns: checks, expressions, and the matrix kernel that verifies blocks."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


class VectorSchemaError(ValueError):
    """Rows that aren't vectors of one width."""


def sum_of(parts: Column) -> Column:
    return F.aggregate(parts, F.lit(0.0), lambda acc, x: acc + x)


def l2_sq(a: str | Column, b: str | Column) -> Column:
    return sum_of(F.zip_with(a, b, lambda x, y: (x - y) * (x - y)))


def l2(a: str | Column, b: str | Column) -> Column:
    return F.sqrt(l2_sq(a, b))


def dot(a: str | Column, b: str | Column) -> Column:
    return sum_of(F.zip_with(a, b, lambda x, y: x * y))


def norm(a: str | Column) -> Column:
    return F.sqrt(sum_of(F.transform(a, lambda x: x * x)))


def cosine(a: str | Column, b: str | Column) -> Column:
    return dot(a, b) / (norm(a) * norm(b))


def normalize(a: str | Column) -> Column:
    """Unit length; a zero vector stays."""
    size = norm(a)
    return F.when(size > 0, F.transform(a, lambda x: x / size)).otherwise(F.col(a) if isinstance(a, str) else a)


def as_vectors(df: DataFrame, id_col: str, vector: str, *attributes: str) -> DataFrame:
    """(vec_id, v: array<double>, attributes...), checked by one aggregate: no null, not-a-number, second width or repeated id."""
    out = df.select(F.col(id_col).cast("long").alias("vec_id"), F.col(vector).cast("array<double>").alias("v"), *attributes)
    found = out.agg(F.count(F.lit(1)).alias("n"), F.count_distinct("vec_id").alias("ids"), F.min(F.size("v")).alias("lo"), F.max(F.size("v")).alias("hi"), F.count_if(F.col("v").isNull() | F.exists("v", lambda x: x.isNull() | F.isnan(x))).alias("bad")).first()
    if found["n"] and (found["bad"] or found["lo"] != found["hi"] or found["ids"] != found["n"] or found["lo"] < 1):
        raise VectorSchemaError(f"{found['n']} rows, {found['ids']} ids, widths {found['lo']} to {found['hi']}, {found['bad']} with nulls or not-a-number")
    return out


def _proposals(a: np.ndarray, b: np.ndarray | None, eps: float, tile: int) -> Iterator[tuple[int, int, np.ndarray, float]]:
    """(first row, first column, squared distances by a matrix product, their possible error) of each tile; of ``a`` with itself what isn't above the diagonal is infinite."""
    own = b is None
    right = a if own else b
    if not len(a) or not len(right):
        return
    na, nb = (a * a).sum(axis=1), (right * right).sum(axis=1)
    slack, kind = 64 * (a.shape[1] ** 0.5 + 1), np.float64
    most = float(na.max() + nb.max())
    if most < 1e30 and slack * np.finfo(np.float32).eps * (most + eps * eps) < 0.1 * eps * eps:  # single precision leaves few pairs open
        kind = np.float32
    slack *= np.finfo(kind).eps
    # norms go along as two more columns, so that the product is the squared distance itself
    x = np.column_stack([-2 * a, na, np.ones(len(a))]).astype(kind)
    y = np.column_stack([right, np.ones(len(right)), nb]).astype(kind)
    for i in range(0, len(a), tile):
        for j in range(i if own else 0, len(right), tile):
            square = x[i : i + tile] @ y[j : j + tile].T
            if own and i == j:
                square[np.tril_indices(len(square))] = np.inf
            yield i, j, square, slack * (na[i : i + tile].max() + nb[j : j + tile].max() + eps * eps)


def close_pairs(a: np.ndarray, b: np.ndarray | None, eps: float, tile: int = 512) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Row numbers and distances of the rows of ``a`` and ``b`` within ``eps`` (of ``a`` with itself, upper triangle, where b is None).

    A matrix product proposes, with slack for its rounding; the distance is then computed from the differences.
    """
    right = a if b is None else b
    rows, cols, dist = [np.zeros(0, int)], [np.zeros(0, int)], [np.zeros(0)]
    for i, j, square, error in _proposals(a, b, eps, tile):
        p, q = np.nonzero(square <= eps * eps + error)
        for c in range(0, len(p), 1 << 16):
            r, s = p[c : c + (1 << 16)] + i, q[c : c + (1 << 16)] + j
            d = np.sqrt(((a[r] - right[s]) ** 2).sum(axis=1))
            ok = d <= eps
            rows.append(r[ok]), cols.append(s[ok]), dist.append(d[ok])
    return np.concatenate(rows), np.concatenate(cols), np.concatenate(dist)


def count_close(a: np.ndarray, b: np.ndarray | None, eps: float, tile: int = 512) -> int:
    """How many pairs ``close_pairs`` tells, without holding them: differences decide only where the product's rounding could."""
    right, n = a if b is None else b, 0
    for i, j, square, error in _proposals(a, b, eps, tile):
        sure = int(np.count_nonzero(square < eps * eps - error))
        n += sure
        if np.count_nonzero(square <= eps * eps + error) > sure:
            p, q = np.nonzero((square <= eps * eps + error) & (square >= eps * eps - error))
            for c in range(0, len(p), 1 << 16):
                r, s = p[c : c + (1 << 16)] + i, q[c : c + (1 << 16)] + j
                n += int(np.count_nonzero(np.sqrt(((a[r] - right[s]) ** 2).sum(axis=1)) <= eps))
    return n
