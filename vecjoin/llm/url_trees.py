"""URL filter: host and path rules first, then gradient-boosted trees on lexical features.

A rule fits its host and all subdomains if the path starts with the rule's path; of several the longest wins.
URLs that a rule fits are the labelled ones: trees are trained on a bounded sample of them (``sample`` rows,
smallest keyed hash first) and judge all others. Features: lengths, depth, labels, digit ratio, entropy,
parameters, punctuation, scheme, and of the host's last one and two labels how frequent they are and how often they are blocked among
the training URLs. Where no URL is labelled, or all alike, the verdict is that one, or else allow.

Rows: a null URL, or one without "://", has an empty host and path, fits no rule and is judged by the trees as an
empty URL; rows are independent.
"""

from __future__ import annotations

import re
from collections import Counter
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: (verdict, rule)
RULES = (("allow", "org/"), ("block", "example.org/es/"), ("block", "example.org/en/1"), ("allow", "com/fr/"), ("block", "com/de/"))
SAMPLE, TREES, DEPTH, RATE = 20_000, 40, 3, 0.2
_PARTS = re.compile(r"^(.*?)://([^/?#]*)([^?#]*)(\?[^#]*)?(#.*)?$", re.S)
_UPPER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ"


def host_of(url: str) -> Column:
    return F.translate(F.coalesce(F.regexp_extract(url, "://([^/?#]*)", 1), F.lit("")), _UPPER, _UPPER.lower())


def path_of(url: str) -> Column:
    return F.coalesce(F.regexp_extract(url, "://[^/?#]*([^?#]*)", 1), F.lit(""))


def ruled(host: str, path: str, rules=RULES) -> Column:
    """The longest fitting rule as a struct (rule, verdict), or null."""
    out = F.lit(None).cast("struct<rule:string,verdict:string>")
    for verdict, rule in sorted(rules, key=lambda r: (len(r[1]), r[1])):
        name, slash, rest = rule.partition("/")
        fits = ((F.col(host) == name) | F.col(host).endswith(f".{name}")) & F.col(path).startswith(slash + rest)
        out = F.when(fits, F.struct(F.lit(rule).alias("rule"), F.lit(verdict).alias("verdict"))).otherwise(out)
    return out


def lexical(urls: list[str | None]) -> tuple[np.ndarray, list[tuple[str, str]]]:
    """Feature rows, and the last and last two labels of each host."""
    rows, ends = [], []
    for url in urls:
        m = _PARTS.match(url or "")
        scheme, host, path, query, mark = (m.groups() if m else ("", "", "", "", ""))
        host, query, mark, whole = host.lower(), query or "", mark or "", url or ""
        labels = host.split(".")
        count = np.array(list(Counter(whole).values()), dtype=float) / max(1, len(whole))
        digits, names = sum(c.isdigit() for c in whole), sum(c.isdigit() for c in host)
        rows.append((len(whole), len(host), len(path), len(query), path.count("/"), len(labels), max(map(len, labels)), digits / max(1, len(whole)), names / max(1, len(host)), float(-(count * np.log2(count)).sum()) if len(count) else 0.0, query.count("&") + bool(query), whole.count("-"), whole.count("_") + whole.count("%") + whole.count("@"), scheme == "https", bool(mark), host.startswith("www."), path.endswith("/"), max((len(s) for s in path.split("/")), default=0), sum(map(str.isdigit, path.rsplit("/", 1)[-1]))))
        ends.append((labels[-1], ".".join(labels[-2:])))
    return np.array(rows, dtype=float).reshape(len(rows), 19), ends


class BoostedTrees:
    """Logistic gradient boosting with depth-limited trees over quantile bins."""

    def __init__(self, x: np.ndarray, y: np.ndarray, trees: int = TREES, depth: int = DEPTH, rate: float = RATE, bins: int = 32):
        self.depth = depth
        self.cuts = [np.unique(np.quantile(x[:, f], np.linspace(0, 1, bins + 1)[1:-1])) for f in range(x.shape[1])]
        binned = self._bin(x)
        p = (y.sum() + 1) / (len(y) + 2)
        self.start, self.trees = float(np.log(p / (1 - p))), []
        score = np.full(len(y), self.start)
        for _ in range(trees):
            prob = 1 / (1 + np.exp(-score))
            tree = self._grow(binned, y - prob, prob * (1 - prob), rate)
            self.trees.append(tree)
            score += self._leaf(tree, binned)

    def _bin(self, x: np.ndarray) -> np.ndarray:
        return np.stack([np.searchsorted(c, x[:, f], "left") for f, c in enumerate(self.cuts)], axis=1).astype(np.int16) if len(x) else np.zeros((0, len(self.cuts)), np.int16)

    def _grow(self, b, g, h, rate):
        """Arrays by node: feature (-1: leaf), bin, value; children of i are 2i+1 and 2i+2."""
        size = 2 ** (self.depth + 1) - 1
        feature, split, value = np.full(size, -1), np.zeros(size, int), np.zeros(size)
        node = np.zeros(len(g), int)
        for i in range(size):
            here = node == i
            if not here.any():
                continue
            gs, hs = g[here], h[here]
            value[i] = rate * gs.sum() / (hs.sum() + 1)
            if i >= 2**self.depth - 1:
                continue
            best, parent = 1e-6, gs.sum() ** 2 / (hs.sum() + 1)
            for f, c in enumerate(self.cuts):
                if not len(c):
                    continue
                gl = np.cumsum(np.bincount(b[here, f], weights=gs, minlength=len(c) + 1))[:-1]
                hl = np.cumsum(np.bincount(b[here, f], weights=hs, minlength=len(c) + 1))[:-1]
                gain = gl**2 / (hl + 1) + (gs.sum() - gl) ** 2 / (hs.sum() - hl + 1) - parent
                j = int(np.argmax(gain))
                if gain[j] > best:
                    best, feature[i], split[i] = gain[j], f, j
            if feature[i] >= 0:
                node[here] = np.where(b[here, feature[i]] <= split[i], 2 * i + 1, 2 * i + 2)
        return feature, split, value

    def _leaf(self, tree, b):
        feature, split, value = tree
        node = np.zeros(len(b), int)
        for _ in range(self.depth):
            f = feature[node]
            go = f >= 0
            left = b[np.arange(len(b)), np.maximum(f, 0)] <= split[node]
            node = np.where(go, np.where(left, 2 * node + 1, 2 * node + 2), node)
        return value[node]

    def __call__(self, x: np.ndarray) -> np.ndarray:
        b = self._bin(x)
        score = np.full(len(x), self.start) + sum((self._leaf(t, b) for t in self.trees), np.zeros(len(x)))
        return 1 / (1 + np.exp(-score))


class UrlModel:
    """Trees with the suffix statistics of their training URLs."""

    def __init__(self, urls: list[str], blocked: np.ndarray):
        x, ends = lexical(urls)
        self.mean = float(blocked.mean()) if len(blocked) else 0.0
        self.seen, self.bad = [Counter(), Counter()], [Counter(), Counter()]
        for e, y in zip(ends, blocked.tolist(), strict=True):
            for level in (0, 1):
                self.seen[level][e[level]] += 1
                self.bad[level][e[level]] += y
        self.n = max(1, len(urls))
        self.trees = BoostedTrees(self._with(x, ends), blocked.astype(float)) if len(urls) and 0 < self.mean < 1 else None

    def _with(self, x, ends):
        more = [[v for level in (0, 1) for v in (self.seen[level][e[level]] / self.n, (self.bad[level][e[level]] + 10 * self.mean) / (self.seen[level][e[level]] + 10))] for e in ends]
        return np.hstack([x, np.array(more, dtype=float).reshape(len(x), 4)])

    def __call__(self, urls: list[str | None]) -> np.ndarray:
        """Probability that a URL is to be blocked."""
        if self.trees is None:
            return np.full(len(urls), self.mean)
        return self.trees(self._with(*lexical(urls)))


def train(urls: DataFrame, sample: int = SAMPLE) -> UrlModel:
    """A model from a bounded sample of the labelled ``urls`` (url, verdict)."""
    rows = urls.where("url is not null").groupBy("url").agg(F.max("verdict").alias("verdict")).orderBy(F.xxhash64("url", F.lit(7)), "url").limit(sample).toPandas()
    return UrlModel(rows["url"].tolist(), (rows["verdict"] == "block").to_numpy())


def judge(pages: DataFrame, rules=RULES, sample: int = SAMPLE, page_id: str = "page_id", url: str = "url") -> DataFrame:
    """page_id, url, host, path, rule, verdict, score (of blocking; null where a rule decides)."""
    parts = pages.select(F.col(page_id).cast("long").alias("page_id"), F.col(url).cast("string").alias("url")).withColumns({"host": host_of("url"), "path": path_of("url")}).withColumn("_r", ruled("host", "path", rules))
    known = parts.select("page_id", "url", "host", "path", F.col("_r.rule").alias("rule"), F.col("_r.verdict").alias("verdict"))
    model = train(known.where("verdict is not null").select("url", "verdict"), sample)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            verdict = batch.column(5).to_pylist()
            open_ = [i for i, v in enumerate(verdict) if v is None]
            urls = batch.column(1).to_pylist()
            score: list[float | None] = [None] * len(verdict)
            for i, p in zip(open_, model([urls[i] for i in open_]).tolist(), strict=True):
                score[i], verdict[i] = p, "block" if p >= 0.5 else "allow"
            yield pa.RecordBatch.from_arrays([*batch.columns[:5], pa.array(verdict, pa.string()), pa.array(score, pa.float64())], names=["page_id", "url", "host", "path", "rule", "verdict", "score"])

    return known.mapInArrow(run, "page_id long, url string, host string, path string, rule string, verdict string, score double")
