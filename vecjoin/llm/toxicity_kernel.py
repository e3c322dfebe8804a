"""Toxicity by a subsequence string kernel with Nyström landmarks.

The kernel of order three compares two words by the letter triples that they share as subsequences, each weighted by
``DECAY`` to the power of the span it covers, so an insult with letters put between or left out stays near. Words are what white space parts;
marks inside them are dropped, look-alike digits and signs read as letters, and letters typed one by one joined.

Training, on labelled documents: their sentences' words are the instances. Words of toxic documents that hold letter
groups, or are words, typical of toxic documents are the first positives, words of clean documents negatives; a linear
support vector machine on the Nyström features of ``LANDMARKS`` words is fitted, the words of toxic documents past its
margin and the clean words that look like them join in, and the machine is fitted again. The three largest margins of its words are a document's,
mapped to a probability on a quarter of the training documents that the machine hasn't seen. As the machine is linear in the kernel, the weights of all landmarks are folded into one
tensor over letter triples, and a word costs one look-up per triple.

It learns from a bounded sample: ``sample`` labelled documents of each class, by smallest keyed hash of doc_id.

Rows: null and empty texts get the score of a text without words; with no labelled document, or just one class, the score is
the share of toxic ones; a doc_id labelled twice is toxic if any label says so; other columns are ignored.
"""

from __future__ import annotations

import re
from collections import Counter
from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .lines import slices

SAMPLE, LANDMARKS, DECAY, ROUNDS, LONGEST = 2_000, 384, 0.6, 4, 20
_LETTERS = 32
_ALIKE = str.maketrans("013457@$!|", "oieastasil")
_SPELT = re.compile(r"(?<!\S)\w(?:[ .*_-]{1,2}\w){2,}(?!\S)")
#: What a word of fewer than three letters scores.
NOTHING = -1.5


def words(text: str) -> set[str]:
    """The different words of a text as typed, lower-cased; letters typed one by one also as one word."""
    low = text.lower()
    out = set(low.split())
    if any(len(w) == 1 for w in out):
        out.update("".join(c for c in m if c.isalnum()) for m in _SPELT.findall(low))
    return out


def letters(word: str) -> list[str]:
    """Pieces of at most LONGEST characters of a word, half overlapping; ``^`` and ``$`` mark where it begins and ends."""
    plain = word if word.isalpha() else "".join(c for c in word.rstrip(".,;:!?)").translate(_ALIKE) if c.isalpha())
    if len(plain) < 3:
        return []
    plain = f"^{plain}$"
    if len(plain) <= LONGEST:
        return [plain]
    return [plain[i : i + LONGEST] for i in range(0, len(plain) - LONGEST // 2, LONGEST // 2)]


@lru_cache(maxsize=64)
def _triples(n: int) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Places i < j < k in a word of n letters, and DECAY to the power of the span."""
    i, j, k = (np.array(x) for x in zip(*((i, j, k) for i in range(n) for j in range(i + 1, n) for k in range(j + 1, n)), strict=True))
    return i, j, k, DECAY ** (k - i + 1.0)


class Kernel:
    """Subsequence features of words over an alphabet of the 31 most frequent letters and one for all others."""

    def __init__(self, alphabet: str):
        self.code = {c: i for i, c in enumerate(alphabet[: _LETTERS - 1])}

    def blocks(self, pieces: list[str], most: int = 1 << 21) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
        """Places in ``pieces``, triple numbers and triple weights (scaled to unit length), for words of one length at a time."""
        size = np.array([len(p) for p in pieces])
        for n in range(3, LONGEST + 1):
            at = np.flatnonzero(size == n)
            if not len(at):
                continue
            i, j, k, decay = _triples(n)
            step = max(1, most // len(i))
            for a in range(0, len(at), step):
                own = at[a : a + step]
                get = self.code.get
                c = np.array([[get(x, _LETTERS - 1) for x in pieces[p]] for p in own.tolist()], dtype=np.int32)
                key = (c[:, i] * _LETTERS + c[:, j]) * _LETTERS + c[:, k]
                yield own, key, decay[None, :] / self.norm(c)[:, None]

    @staticmethod
    def norm(c: np.ndarray) -> np.ndarray:
        """Length of each word's feature vector, by the kernel's recursion of a word with itself."""
        n, m = c.shape
        same = [[(c[:, a] == c[:, b]).astype(float) for b in range(m)] for a in range(m)]
        # ends[a][b]: weight of common subsequences so far that end exactly at a and b
        ends = [[same[a][b] * DECAY**2 for b in range(m)] for a in range(m)]
        for _ in range(2):
            after = [[np.zeros(n) for _ in range(m)] for _ in range(m)]
            reach = [[np.zeros(n) for _ in range(m + 1)] for _ in range(m + 1)]
            for a in range(m):
                for b in range(m):
                    # everything that ends before both, decayed by the gap
                    after[a][b] = same[a][b] * DECAY**2 * reach[a][b]
                    reach[a + 1][b + 1] = ends[a][b] + DECAY * (reach[a][b + 1] + reach[a + 1][b]) - DECAY**2 * reach[a][b]
            ends = after
        return np.sqrt(sum(x for row in ends for x in row))


    def tensors(self, pieces: list[str]) -> np.ndarray:
        """The tensors of several words, one per column."""
        out = np.zeros((_LETTERS**3, len(pieces)), np.float32)
        for n, piece in enumerate(pieces):
            for _, key, weight in self.blocks([piece]):
                np.add.at(out[:, n], key[0], weight[0])
        return out

    def against(self, pieces: list[str], tensors: np.ndarray) -> np.ndarray:
        """Kernel values of each word with each of the ``tensors`` (one per column)."""
        out = np.zeros((len(pieces), tensors.shape[1]), np.float32)
        for own, key, weight in self.blocks(pieces, 1 << 14):
            out[own] = np.einsum("wtl,wt->wl", tensors[key], weight.astype(np.float32))
        return out

    def folded(self, pieces: list[str], tensor: np.ndarray) -> np.ndarray:
        """Product of each word with one tensor; 0 for words of fewer than three letters."""
        out = np.zeros(len(pieces))
        for own, key, weight in self.blocks(pieces):
            out[own] = (tensor[key] * weight).sum(axis=1)
        return out


def hinge(x: np.ndarray, y: np.ndarray, weight: np.ndarray, c: float = 2.0, steps: int = 40) -> np.ndarray:
    """Weights and bias of a linear support vector machine with squared hinge loss (y: -1 or 1), by Newton steps on the rows inside the margin."""
    x = np.hstack([x, np.ones((len(x), 1), x.dtype)])
    w = np.zeros(x.shape[1])
    ridge = np.append(np.ones(x.shape[1] - 1), 1e-3)

    def loss(v: np.ndarray) -> float:
        return 0.5 * (ridge * v * v).sum() + c * (weight * np.maximum(0, 1 - y * (x @ v)) ** 2).sum()

    now = loss(w)
    for _ in range(steps):
        on = y * (x @ w) < 1
        xs, ws = x[on], weight[on]
        target = np.linalg.solve(((xs * (2 * c * ws)[:, None].astype(xs.dtype)).T @ xs).astype(float) + np.diag(ridge), xs.T @ (2 * c * ws * y[on]))
        size = 1.0
        while size > 1e-3 and (new := loss(w + size * (target - w))) > now:
            size /= 2
        if now - new < 1e-6 * now:
            break
        w, now = w + size * (target - w), new
    return w


class ToxicModel:
    """Trained on texts and 0/1 labels; a call scores texts."""

    def __init__(self, texts: list[str], toxic: list[int]):
        self.share = float(np.mean(toxic)) if toxic else 0.0
        self.kernel, self.cache = None, {}
        if not 0 < self.share < 1:
            return
        # a quarter of the documents is kept from the machine and only used for the mapping to probabilities
        apart = [i % 4 == 3 for i in range(len(texts))] if min(sum(toxic[3::4]), len(toxic[3::4]) - sum(toxic[3::4])) >= 25 else [False] * len(texts)
        same: dict[str, str] = {}  # one copy of each word
        bags = [sorted({same.setdefault(p, p) for w in words(t) for p in letters(w)}) for t, a in zip(texts, apart, strict=True) if not a]
        told = toxic
        toxic = [y for y, a in zip(told, apart, strict=True) if not a]
        good, bad = [b for b, y in zip(bags, toxic, strict=True) if not y], [b for b, y in zip(bags, toxic, strict=True) if y]
        clean = Counter(w for b in good for w in b)
        self.kernel = Kernel("".join(c for c, _ in Counter("".join(w for b in bags for w in b)).most_common()))
        grams = lambda w: {w, *(w[i : i + 4] for i in range(max(1, len(w) - 3)))}
        in_bad, in_good = (Counter(g for b in side for g in {g for w in b for g in grams(w)}) for side in (bad, good))
        least = max(2, 0.01 * len(bad))
        ratio = lambda n, m: (n + 0.5) / (len(bad) + 1) / ((m + 0.5) / (len(good) + 1))
        odds = {g: ratio(n, in_good[g]) for g, n in in_bad.items() if n >= least}
        telling = lambda w: max((odds.get(g, 0) for g in grams(w)), default=0)
        seen = Counter(w for b in bad for w in b)
        # a word counts as clean unless toxic documents hold it far more often
        innocent = {w for w, n in clean.items() if ratio(seen[w], n) < 4}
        doubtful = [w for w in sorted(seen) if w not in innocent and telling(w) >= 3]
        first = [w for w in doubtful if telling(w) >= 10]
        rng = np.random.default_rng(3)
        pool = sorted(innocent)
        pool = [pool[i] for i in rng.permutation(len(pool))]
        usual = sorted(innocent, key=lambda w: (-clean[w], w))[:30_000]
        negative = list(dict.fromkeys(usual[:2000] + pool[:2000]))
        pool = list(dict.fromkeys(usual + pool[:20_000] + [w for w in pool[20_000:] if telling(w) >= 3][:20_000]))
        if not first or not negative:
            self.kernel = None
            return
        some = sorted(first, key=lambda w: (-seen[w], w))[: LANDMARKS // 4]
        rest = [w for w in first if w not in set(some)]
        some += [rest[i] for i in rng.permutation(len(rest))[: LANDMARKS // 8]]
        near = [w for w in pool if telling(w) >= 3][: LANDMARKS // 4]
        positive = first
        for _ in range(ROUNDS):
            # landmarks: the words most seen in toxic documents, and clean ones that look like them most
            marks = list(dict.fromkeys(some + near + negative))[:LANDMARKS]
            tensors = None  # the last round's go before this round's come
            tensors = self.kernel.tensors(marks)
            value, vector = np.linalg.eigh(self.kernel.against(marks, tensors).astype(float))
            root = vector[:, value > 1e-5] / np.sqrt(value[value > 1e-5])
            x = self.kernel.against(positive + negative, tensors) @ root.astype(np.float32)
            y = np.append(np.ones(len(positive)), -np.ones(len(negative)))
            often = np.sqrt(np.array([1.0 + seen[w] for w in positive] + [1.0 + clean[w] for w in negative]))
            often[: len(positive)] *= max(1.0, often[len(positive) :].sum() / often[: len(positive)].sum() / 4)
            w = hinge(x, y, often)
            self.tensor, self.bias = tensors @ (root @ w[:-1]), w[-1]
            # the words that toxic documents are toxic for, and the clean words that look like them
            margin = self.kernel.folded(doubtful, self.tensor) + self.bias
            positive = sorted({d for d, v in zip(doubtful, margin, strict=True) if v > 0.5} | set(first))
            ranked = sorted(((v, p) for p, v in zip(pool, self.kernel.folded(pool, self.tensor) + self.bias, strict=True) if v > -0.9), reverse=True)
            near = [p for _, p in sorted(ranked[:2000], key=lambda r: (-clean[r[1]], r[1]))[: LANDMARKS // 2]]
            negative = list(dict.fromkeys(negative + [p for _, p in ranked[:3000]]))
        held = [i for i, a in enumerate(apart) if a] or list(range(len(texts)))
        self.curve = _logistic(self.margins([texts[i] for i in held]), np.array([told[i] for i in held], dtype=float))
        self.cache = {}

    def margins(self, texts: list[str | None]) -> np.ndarray:
        """The three largest margins of the words of each text, in falling order."""
        bags = [words(t) if t else () for t in texts]
        fresh = list({w for b in bags for w in b} - self.cache.keys())
        if len(self.cache) + len(fresh) > 400_000:
            self.cache, fresh = {}, list({w for b in bags for w in b})
        cut = [letters(w) for w in fresh]
        pieces = sorted({p for c in cut for p in c})
        value = dict(zip(pieces, (self.kernel.folded(pieces, self.tensor) + self.bias).tolist(), strict=True))
        for w, c in zip(fresh, cut, strict=True):
            self.cache[w] = max(value[p] for p in c) if c else NOTHING
        get = self.cache.__getitem__
        none = [NOTHING] * 3
        return np.array([(sorted(map(get, b), reverse=True)[:3] + none)[:3] for b in bags]).reshape(len(bags), 3)

    def __call__(self, texts: list[str | None]) -> np.ndarray:
        if self.kernel is None:
            return np.full(len(texts), self.share)
        return 1 / (1 + np.exp(-np.clip(self.margins(texts) @ self.curve[:-1] + self.curve[-1], -30, 30)))


def _logistic(x: np.ndarray, y: np.ndarray) -> np.ndarray:
    """Slopes and offset of a logistic curve, by damped Newton steps; a small penalty keeps the slopes finite."""
    x = np.hstack([x, np.ones((len(x), 1))])
    penalty = np.append(np.full(x.shape[1] - 1, 0.5), 0.0)
    out = np.append(np.full(x.shape[1] - 1, 1.0), 0.0)
    for _ in range(50):
        p = 1 / (1 + np.exp(-np.clip(x @ out, -30, 30)))
        slope = x.T @ (y - p) - penalty * out
        curve = (x * (p * (1 - p) + 1e-9)[:, None]).T @ x + np.diag(penalty + 1e-9)
        out = out + np.linalg.solve(curve, slope).clip(-2, 2)
    return out


def training_texts(docs: DataFrame, labels: DataFrame, learn: Column, sample: int = SAMPLE) -> tuple[list[str], list[int]]:
    """At most ``sample`` labelled texts of each class, from ids where ``learn`` (an expression over doc_id) holds."""
    told = labels.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("toxic").cast("int").alias("toxic")).where("doc_id is not null and toxic is not null").where(learn).groupBy("doc_id").agg(F.max("toxic").alias("toxic"))
    order = [F.xxhash64("doc_id", F.lit(13)), F.col("doc_id")]
    picked = told.where("toxic = 1").orderBy(*order).limit(sample).union(told.where("toxic = 0").orderBy(*order).limit(sample))
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")).join(F.broadcast(picked), "doc_id").select("doc_id", "toxic", "text").collect()  # 2 x sample rows
    rows.sort(key=lambda r: (r["doc_id"], r["text"] or ""))
    return [r["text"] or "" for r in rows], [r["toxic"] for r in rows]


def score(docs: DataFrame, model: ToxicModel, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """doc_id and score of every row."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for batch in slices(whole):
                yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(model(batch.column(1).to_pylist()))], names=["doc_id", "score"])

    return docs.select(F.col(doc_id).cast("long").alias("doc_id"), F.col(text).cast("string").alias("text")).mapInArrow(run, "doc_id long, score double")


def reject(docs: DataFrame, model: ToxicModel, text: str = "text", threshold: float = 0.5) -> DataFrame:
    """``docs`` without the rows that score ``threshold`` or more."""
    at = docs.columns.index(text)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for batch in slices(whole, at):
                yield batch.filter(pa.array(model(batch.column(at).to_pylist()) < threshold))

    return docs.mapInArrow(run, docs.schema)
