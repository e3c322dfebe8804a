"""Runs a query and its SQL side by side and compares rows without order."""

from __future__ import annotations

import glob
import math
import os

import duckdb


def connect(sf_dir: str):
    con = duckdb.connect()
    for path in glob.glob(f"{sf_dir}/*.parquet"):
        name = os.path.basename(path).removesuffix(".parquet")
        con.execute(f"CREATE VIEW {name} AS SELECT * FROM read_parquet('{path}')")
    return con


def plain(value):
    if isinstance(value, float):
        return "nan" if math.isnan(value) else round(value, 6)
    return value


def rows(cols, data):
    order = sorted(range(len(cols)), key=lambda i: cols[i])
    return sorted(([plain(r[i]) for i in order] for r in data), key=lambda r: tuple((v is not None, str(v)) for v in r))


def compare(spark, sf_dir: str, query, sql: str) -> int:
    df = query(spark, sf_dir)
    got = rows(df.columns, [tuple(r) for r in df.collect()])
    rel = connect(sf_dir).execute(sql)
    cols = [d[0] for d in rel.description]
    want = rows(cols, rel.fetchall())
    assert sorted(df.columns) == sorted(cols), (df.columns, cols)
    assert len(got) == len(want), (len(got), len(want))
    for g, w in zip(got, want, strict=True):
        for a, b in zip(g, w, strict=True):
            same = a == b or (isinstance(a, (int, float)) and isinstance(b, (int, float)) and not isinstance(a, bool) and abs(float(a) - float(b)) <= 1e-6 * max(1.0, abs(float(b))))
            assert same or str(a) == str(b), (g, w)
    return len(got)
