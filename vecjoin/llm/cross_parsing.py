"""Language identification by cross-parsing entropy.

Per language a suffix automaton of sample text is built. A text is parsed against it greedily: each phrase is
the longest match from where the last one ended, plus the character that broke it. The number of phrases by the
number of characters estimates the cross entropy; the language that needs fewest phrases wins, ties going to
the alphabetically first label.

Letters are lower-cased and everything else is one separator (a run of them counts once). Texts are parsed in
stretches of ``STRETCH`` characters side by side, every stretch of every text, so the work is one table look-up
per character and language however long a text is.

The model learns from a bounded sample: the texts of the smallest keyed hashes of doc_id, ``chars`` normalised
characters for each language.

Rows: null text or text without a letter is ``und`` with score 0; a null lang teaches nothing; with no labelled text all
is ``und``; repeated rows are judged alike; other columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .kernels import ranges
from .lines import slices

CHARS, STRETCH, UNKNOWN = 48_000, 512, "und"
#: Documents of each language that the sample is picked from, and characters of each that are used.
TEXTS, TEXT_CHARS = 200, 4_000


def normalise(text: str) -> str:
    """Lower-case letters; runs of anything else are one space. Combining marks that are no letters count as anything else, in learning and in prediction alike."""
    return " ".join("".join(c if c.isalpha() else " " for c in text.lower()).split())


class Automaton:
    """Suffix automaton of one text as a dense table: ``go[state, letter]`` is twice the next state, plus 1 where the match broke."""

    def __init__(self, text: str, alphabet: dict[str, int], width: int):
        link, length, step = [-1], [0], [{}]
        last = 0
        for c in (alphabet[c] for c in text):
            new = len(step)
            link.append(0), length.append(length[last] + 1), step.append({})
            p, last = last, new
            while p >= 0 and c not in step[p]:
                step[p][c] = new
                p = link[p]
            if p >= 0:
                q = step[p][c]
                if length[q] != length[p] + 1:
                    twin = len(step)
                    link.append(link[q]), length.append(length[p] + 1), step.append(dict(step[q]))
                    while p >= 0 and step[p].get(c) == q:
                        step[p][c] = twin
                        p = link[p]
                    link[q] = twin
                    q = twin
                link[new] = q
        root = np.zeros(width, np.int32)
        for c, s in step[0].items():
            root[c] = s
        self.go = np.broadcast_to(2 * root + 1, (len(step), width)).copy()
        rows = np.repeat(np.arange(len(step)), [len(s) for s in step])
        self.go[rows, np.fromiter((c for s in step for c in s), int, len(rows))] = 2 * np.fromiter((t for s in step for t in s.values()), np.int32, len(rows))
        self.go = self.go.reshape(-1)
        self.width = width

    def phrases(self, columns: np.ndarray) -> np.ndarray:
        """Breaks in each column of letters (-1: ended)."""
        n = columns.shape[1]
        state, count = np.zeros(n, np.int64), np.zeros(n, np.int64)
        for row in columns:
            code = self.go[state * self.width + row]
            count += code & 1
            state = (code >> 1).astype(np.int64)
        return count


class CrossParser:
    """Automata of all languages over one alphabet."""

    def __init__(self, texts: dict[str, str]):
        self.langs = sorted(k for k, v in texts.items() if v)
        letters = sorted({c for v in texts.values() for c in v} | {" "})
        alphabet = {c: i for i, c in enumerate(letters)}
        self.width = len(letters) + 2  # then: a letter of no sample, and the end
        self.automata = [Automaton(texts[k], alphabet, self.width) for k in self.langs]
        for a in self.automata:  # behind the end no phrase breaks and nothing moves on
            a.go.reshape(-1, self.width)[:, -1] = 0
        self.table = np.zeros(0x110000, np.int16) + np.int16(-1)
        for c, i in alphabet.items():
            self.table[ord(c)] = i

    def codes(self, texts: list[str]) -> tuple[np.ndarray, np.ndarray]:
        """Letter numbers of all texts, separators of a run once, and the length of each."""
        low = [t.lower() for t in texts]
        points = np.frombuffer("".join(low).encode("utf-32-le", "surrogatepass"), np.uint32)
        owner = np.repeat(np.arange(len(low)), [len(t) for t in low])
        code = self.table[points]
        other = np.flatnonzero(code < 0)
        if len(other):
            kinds, back = np.unique(points[other], return_inverse=True)
            letter = np.array([chr(k).isalpha() for k in kinds.tolist()])
            code[other] = np.where(letter[back], self.width - 2, self.table[32])
        space = code == self.table[32]
        drop = np.zeros(len(code), bool)
        drop[1:] = space[1:] & space[:-1] & (owner[1:] == owner[:-1])
        return code[~drop], np.bincount(owner[~drop], minlength=len(low))

    def __call__(self, texts: list[str | None]) -> tuple[list[str], np.ndarray]:
        """Label and score of each text; the score is by how much of its phrases the runner-up needs more."""
        code, size = self.codes([t or "" for t in texts])
        letter = code != self.table[32]
        owner = np.repeat(np.arange(len(texts)), size)
        some = np.bincount(owner[letter], minlength=len(texts)) > 0
        n = -(-size // STRETCH)
        text = np.repeat(np.arange(len(texts)), n)
        begin = (np.cumsum(size) - size)[text] + ranges(n) * STRETCH
        span = np.minimum(STRETCH, (np.cumsum(size))[text] - begin)
        total = np.zeros((len(self.langs), len(texts)))
        order = np.argsort(-span, kind="stable")
        code = code.astype(np.int64)
        for a in range(0, len(order), 8192):
            mine = order[a : a + 8192]
            depth = int(span[mine[0]])
            at = np.arange(depth)[:, None]
            columns = np.where(at < span[mine][None, :], code[np.minimum(begin[mine][None, :] + at, len(code) - 1)], self.width - 1)
            for k, automaton in enumerate(self.automata):
                total[k] += np.bincount(text[mine], weights=automaton.phrases(columns), minlength=len(texts))
        if not self.langs:
            return [UNKNOWN] * len(texts), np.zeros(len(texts))
        total = (total + 1) / np.maximum(size, 1)
        best = np.argmin(total, axis=0)
        ranked = np.sort(total, axis=0)
        score = 1 - ranked[0] / ranked[1] if len(self.langs) > 1 else np.ones(len(texts))
        return [self.langs[b] if s else UNKNOWN for b, s in zip(best, some, strict=True)], np.where(some, np.clip(score, 0, 1), 0.0)


def remainder(doc_id: str, by: int) -> Column:
    return F.pmod(F.crc32(F.coalesce(F.col(doc_id).cast("string"), F.lit(""))), F.lit(by))


def sample_texts(docs: DataFrame, learn: Column, chars: int = CHARS, doc_id: str = "doc_id", text: str = "text", lang: str = "lang") -> dict[str, str]:
    """For each language the sample text, from rows where ``learn`` holds: a bounded number of texts, chosen by hash."""
    source = docs.where(learn).select(F.col(doc_id).cast("long").alias("i"), F.col(text).cast("string").alias("t"), F.col(lang).cast("string").alias("k")).where("k is not null and t is not null")
    counts = {r[0]: r[1] for r in source.groupBy("k").count().collect()}
    if not counts:
        return {}
    key = F.pmod(F.xxhash64("i", F.lit(11)), F.lit(1 << 30))
    # a threshold for each language that leaves about twice the texts asked for; the smallest keys of those are used
    share = F.create_map(*(x for k, n in counts.items() for x in (F.lit(k), F.lit(int(min(1.0, 2 * TEXTS / n) * (1 << 30))))))
    rows = source.where(key < share[F.col("k")]).select("k", key.alias("key"), F.substring("t", 1, TEXT_CHARS).alias("t")).collect()
    out: dict[str, str] = {}
    for k in counts:
        mine = [normalise(r["t"]) for r in sorted((r for r in rows if r["k"] == k), key=lambda r: (r["key"], r["t"]))]
        out[k] = " ".join(m for m in mine if m)[:chars]
    return out


_MODELS: dict[int, CrossParser] = {}


def _model(texts: dict[str, str]) -> CrossParser:
    """One model per Python worker and sample."""
    key = hash(tuple(sorted(texts.items())))
    if key not in _MODELS:
        _MODELS.clear()
        _MODELS[key] = CrossParser(texts)
    return _MODELS[key]


def identify(docs: DataFrame, texts: dict[str, str], doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """doc_id, lang_pred, score for every row, by a model of the sample ``texts``."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        model = _model(texts)
        for whole in batches:
            for batch in slices(whole):
                label, score = model(batch.column(1).to_pylist())
                yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(label, pa.string()), pa.array(score)], names=["doc_id", "lang_pred", "score"])

    return docs.select(F.col(doc_id).cast("long").alias("doc_id"), F.col(text).cast("string").alias("text")).mapInArrow(run, "doc_id long, lang_pred string, score double")
