"""Near-duplicate documents by improved consistent weighted sampling over TF-IDF shingles.

1. A document is the weighted set of its five-word shingles; weight = count x idf, with
   idf(s) = 1 + ln((N + 1) / (df(s) + 1)). df is exact, over all documents and for every shingle: rows are packed in
   chunks, each chunk deals its distinct shingles to parts by their hash, a part adds up what all chunks have of its
   shingles, and the sums go back to the chunks in the order in which the shingles came. So neither a task nor the
   driver ever holds the shingles of the corpus, and a shingle of all documents comes once from each chunk.
   With a ``floor`` idf is level for shingles in a smaller share of the documents; the default has none.
2. Consistent weighted samples: for each of ``bands x rows`` seeds the shingle and quantised log-weight that
   minimise the sampling score; two documents agree in one sample with the probability of their weighted
   Jaccard similarity. The random variates are quantile tables read by bits of the shingle's keyed hash.
3. Texts of one band value are candidates. Equal texts are one node. In each bucket all nodes are compared
   with one hub, and then every pair that is still in different groups, in large buckets by blocks as matrix
   products; so most copies cost one comparison each, and no link that joins groups is lost.
4. Candidates are verified: sum of minima over sum of maxima of the weights, at least ``similarity``.

Rows: null and word-less texts match nothing and are groups of their own; a text of one to four words has
one shingle, all of it; equal texts are always one group; rows of a repeated doc_id are judged by their
texts; other columns pass through ``keep_first``.
"""

from __future__ import annotations

import uuid
from collections.abc import Iterator, Mapping
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .kernels import HASH_BITS, give_back, list_array, mix64, ranges, shingles, signed, string_buffer, weighted_sets
from .lines import slices
from .tables import components, cut, maybe_in

WORDS, SIMILARITY, BANDS, ROWS, FLOOR, SEED = 5, 0.8, 10, 3, 0.0, 20240101
#: Seeds of the hubs of each round.
HUBS = ((1,),)
_LEVELS = 1 << 13
_LOW = np.uint64(_LEVELS - 1)
#: Buckets of more nodes have their last comparisons made block by block, of about so many nodes each.
SMALL, BLOCK = 64, 512
#: Shingles of a chunk of rows, and of a part of all shingles, about; bytes of text that have one shingle.
CHUNK, PART, _BYTES = 1_000_000, 4_000_000, 6


@lru_cache(maxsize=1)
def _variates() -> tuple[np.ndarray, np.ndarray]:
    """Quantiles of the Gamma(2, 1) distribution at the midpoints of 8,192 levels, and their logarithms."""
    p = (np.arange(_LEVELS) + 0.5) / _LEVELS
    low, high = np.zeros(_LEVELS), np.full(_LEVELS, 40.0)
    for _ in range(60):
        mid = (low + high) / 2
        under = 1 - (1 + mid) * np.exp(-mid) < p
        low, high = np.where(under, mid, low), np.where(under, high, mid)
    return low, np.log(low)


class Idf:
    """idf of document frequencies, or of shingles by a table ``frequent`` of theirs; what it doesn't have is in one document."""

    def __init__(self, n_docs: int, frequent: Mapping[int, int], floor: float):
        self.n_docs, self.least = n_docs, floor * n_docs
        self.key = np.array(sorted(frequent), dtype=np.uint64)
        self.value = self.of(np.array([frequent[int(k)] for k in self.key], dtype=float))
        self.rare = self.of(np.ones(1))[0]

    def of(self, df: np.ndarray) -> np.ndarray:
        return 1 + np.log((self.n_docs + 1) / (np.maximum(df, self.least) + 1))

    def __call__(self, shingle: np.ndarray) -> np.ndarray:
        if not len(self.key):
            return np.full(len(shingle), self.rare)
        at = np.minimum(np.searchsorted(self.key, shingle), len(self.key) - 1)
        return np.where(self.key[at] == shingle, self.value[at], self.rare)


def to_bytes(x: np.ndarray) -> bytes:
    """Numbers from 0 on, as many bytes of each as the largest one has: first how many, then all lowest bytes, all second ones and so on, which compresses well."""
    width = max(1, (int(x.max(initial=0)).bit_length() + 7) // 8)
    return bytes([width]) + x.astype("<u8").view(np.uint8).reshape(-1, 8)[:, :width].T.tobytes()


def from_bytes(data: bytes) -> np.ndarray:
    raw = np.frombuffer(data, np.uint8)
    out = np.zeros(((len(raw) - 1) // int(raw[0]), 8), np.uint8)
    out[:, : raw[0]] = raw[1:].reshape(int(raw[0]), -1).T
    return out.view("<u8").reshape(-1)


def joined(parts: list[bytes]) -> np.ndarray:
    return np.concatenate([from_bytes(x) for x in parts]) if parts else np.zeros(0, np.uint64)


def packed(rows: DataFrame) -> DataFrame:
    """Rows (doc_id, node, check, text) in chunks of about CHUNK shingles: chunk (a number of its own), docs, size (bytes of text), rows (compressed)."""
    most = CHUNK * _BYTES

    def pack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        options = pa.ipc.IpcWriteOptions(compression="zstd")
        for whole in batches:
            for batch in slices(whole, 3, most):
                sink = pa.BufferOutputStream()
                with pa.ipc.new_stream(sink, batch.schema, options=options) as writer:
                    writer.write_batch(batch)
                size = int(np.diff(string_buffer(batch.column(3))[1]).sum())
                yield pa.RecordBatch.from_arrays([pa.array([uuid.uuid4().int >> 65]), pa.array([batch.num_rows]), pa.array([size]), pa.array([sink.getvalue().to_pybytes()], pa.binary())], names=["chunk", "docs", "size", "rows"])

    return rows.mapInArrow(pack, "chunk long, docs long, size long, rows binary")


def unpacked(data: bytes) -> pa.RecordBatch:
    with pa.ipc.open_stream(data) as reader:
        return reader.read_next_batch()


class Frequencies(Mapping):
    """Document frequency of every shingle, as tables: ``chunks`` (see ``packed``), ``dealt`` (chunk, part, key: its shingles' distances
    from one to the next, n) and ``told`` (chunk, part, df: in the same order). A look-up collects all of it: for tests and small tables."""

    def __init__(self, chunks: DataFrame, dealt: DataFrame, told: DataFrame, shift: int):
        self.chunks, self.dealt, self.told, self.shift, self._held = chunks, dealt, told, shift, None

    def _all(self) -> dict[int, int]:
        if self._held is None:
            rows = self.dealt.join(self.told, ["chunk", "part"]).select("part", "key", "df").collect()
            self._held = {k: n for r in rows for k, n in zip((np.cumsum(from_bytes(r["key"])) + (np.uint64(r["part"]) << np.uint64(self.shift))).tolist(), from_bytes(r["df"]).tolist(), strict=True)}
        return self._held

    def __getitem__(self, shingle: int) -> int:
        return self._all()[shingle]

    def __iter__(self) -> Iterator[int]:
        return iter(self._all())

    def __len__(self) -> int:
        return len(self._all())


def document_frequencies(docs: DataFrame, words: int = WORDS) -> tuple[int, Frequencies]:
    """Number of documents, and the exact document frequency of every shingle."""
    chunks = cut(packed(docs.select(F.col("doc_id").cast("long"), node_of("text").alias("node"), F.hash("text").alias("check"), F.col("text").cast("string"))))
    total, size = (int(x) for x in chunks.agg(F.coalesce(F.sum("docs"), F.lit(0)), F.coalesce(F.sum("size"), F.lit(0))).first())
    bits = max(0, int(np.ceil(np.log2(max(1, size / _BYTES / PART)))))
    shift = HASH_BITS - bits

    def deal(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for chunk, rows in zip(whole.column(0).to_pylist(), whole.column(1), strict=True):
                batch = unpacked(rows.as_buffer())
                key, n = np.unique(np.concatenate([weighted_sets(*shingles(part.column(3), words))[1] for part in slices(batch, 3)] or [np.zeros(0, np.uint64)]), return_counts=True)
                part = (key >> np.uint64(shift)).astype(np.int32)
                own, head = np.unique(part, return_index=True)
                key = key & np.uint64((1 << shift) - 1)
                runs = list(zip(head.tolist(), [*head.tolist()[1:], len(key)], strict=False))
                yield pa.RecordBatch.from_arrays([pa.array([chunk] * len(runs), pa.int64()), pa.array(own), pa.array([to_bytes(np.diff(key[a:z], prepend=np.uint64(0))) for a, z in runs], pa.binary()), pa.array([to_bytes(n[a:z]) for a, z in runs], pa.binary())], names=["chunk", "part", "key", "n"])

    def add_up(table: pa.Table) -> pa.Table:
        keys = [np.cumsum(from_bytes(x)) for x in table["key"].to_pylist()]
        ends = np.cumsum([len(k) for k in keys])
        _, same = np.unique(np.concatenate(keys), return_inverse=True)
        df = np.bincount(same, weights=joined(table["n"].to_pylist())).astype(np.int64)[same]
        out = pa.table({"chunk": table["chunk"], "part": table["part"], "df": pa.array([to_bytes(x) for x in np.split(df, ends[:-1])], pa.binary())})
        give_back()
        return out

    dealt = chunks.select("chunk", "rows").mapInArrow(deal, "chunk long, part int, key binary, n binary")
    told = cut(dealt.groupBy("part").applyInArrow(add_up, "chunk long, part int, df binary"))
    return total, Frequencies(chunks, dealt, told, shift)


def samples(doc: np.ndarray, shingle: np.ndarray, weight: np.ndarray, n: int, size: int, seed: int = SEED) -> np.ndarray:
    """``size`` consistent weighted samples (64-bit codes) of each of ``n`` weighted sets; the rows of empty sets are 0."""
    gamma, log_gamma = _variates()
    out = np.zeros((n, size), np.uint64)
    step = 1 << 15
    edges = np.flatnonzero(np.append(True, doc[1:] != doc[:-1])) if len(doc) else np.zeros(0, np.int64)
    ends = np.append(edges[1:], len(doc))
    a = 0
    while a < len(edges):
        z = max(a + 1, int(np.searchsorted(ends, edges[a] + step, "right")))
        lo, hi = int(edges[a]), int(ends[z - 1])
        head, owner = edges[a:z] - lo, doc[edges[a:z]]
        s, log_w = shingle[lo:hi], np.log(weight[lo:hi])
        count = np.diff(np.append(head, hi - lo))
        for k in range(size):
            bits = mix64(s ^ np.uint64((seed + k * 0x632BE59BD9B4E019) & 0xFFFFFFFFFFFFFFFF))
            r = gamma[(bits & _LOW).view(np.int64)]
            shift = (bits >> np.uint64(40)) * (1 / (1 << 24))
            t = np.floor(log_w / r + shift)
            score = log_gamma[((bits >> np.uint64(16)) & _LOW).view(np.int64)] - r * (t - shift + 1)
            best = np.minimum.reduceat(score, head)
            hit = np.flatnonzero(score == np.repeat(best, count))
            which = np.searchsorted(head, hit, "right") - 1
            first = hit[np.append(True, which[1:] != which[:-1])]
            out[owner, k] = mix64(s[first] + t[first].astype(np.int64).view(np.uint64) * np.uint64(0x9E3779B97F4A7C15))
        a = z
    return out


def signatures(frequencies: Frequencies, idf: Idf, bands: int = BANDS, rows: int = ROWS, words: int = WORDS) -> DataFrame:
    """node (hash of the text), check, weight (total), bands (array of longs; empty where there is no word) and df (of its shingles in order, as bytes) of every row, beside doc_id."""

    def sign(chunk: pa.Table, told: pa.Table) -> pa.Table:
        whole = unpacked(chunk["rows"][0].as_buffer())
        told = told.sort_by("part")
        df, done, here = joined(told["df"].to_pylist()), [], 0
        sets = [(batch, *weighted_sets(*shingles(batch.column(3), words))) for batch in slices(whole, 3)]
        _, at = np.unique(np.concatenate([s for _, _, s, _ in sets]), return_inverse=True)
        for batch, doc, shingle, count in sets:
            n, own = batch.num_rows, df[at[here : here + len(shingle)]]
            here += len(shingle)
            weight = count * idf.of(own.astype(float))
            code = samples(doc, shingle, weight, n, bands * rows).reshape(n, bands, rows)
            band = np.zeros((n, bands), np.uint64)
            for j in range(rows):
                band = mix64(band ^ code[:, :, j])
            band = mix64(band + np.arange(bands, dtype=np.uint64))
            size = np.bincount(doc, minlength=n)
            some = size > 0
            total = np.bincount(doc, weights=weight, minlength=n).astype(float)
            each = pa.array([to_bytes(x) for x in np.split(own, np.cumsum(size)[:-1])], pa.binary())
            done.append(pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), batch.column(2), pa.array(total), list_array(pa.array(signed(band[some].reshape(-1))), np.where(some, bands, 0)), each], names=["doc_id", "node", "check", "weight", "bands", "df"]))
        give_back()
        return pa.Table.from_batches(done)

    told = frequencies.told.groupBy("chunk")
    return frequencies.chunks.select("chunk", "rows").groupBy("chunk").cogroup(told).applyInArrow(sign, "doc_id long, node long, check int, weight double, bands array<long>, df binary")


def node_of(text: str) -> Column:
    return F.xxhash64(F.coalesce(F.col(text), F.lit("")))


def weighted_jaccard(a: pa.Array, b: pa.Array, idf: Idf, words: int = WORDS, df: tuple[np.ndarray, np.ndarray] | None = None) -> np.ndarray:
    """Sum of minima over sum of maxima of the weights, row by row; 0 where either has no word. ``df``: of the shingles of ``a`` and of ``b``, where ``idf`` has no table."""
    n = len(a)
    da, sa, ca = weighted_sets(*shingles(a, words))
    db, sb, cb = weighted_sets(*shingles(b, words))
    pair, value = np.concatenate([da, db]), np.concatenate([sa, sb])
    left, right = np.concatenate([ca, np.zeros(len(db), np.int64)]), np.concatenate([np.zeros(len(da), np.int64), cb])
    weight = np.concatenate([idf(sa), idf(sb)] if df is None else [idf.of(x.astype(float)) for x in df])
    order = np.lexsort((value, pair))
    pair, value, left, right = pair[order], value[order], left[order], right[order]
    new = np.flatnonzero(np.append(True, (value[1:] != value[:-1]) | (pair[1:] != pair[:-1]))) if len(pair) else np.zeros(0, np.int64)
    if not len(new):
        return np.zeros(n)
    left, right, weight = np.add.reduceat(left, new), np.add.reduceat(right, new), weight[order][new]
    small = np.bincount(pair[new], weights=np.minimum(left, right) * weight, minlength=n)
    large = np.bincount(pair[new], weights=np.maximum(left, right) * weight, minlength=n)
    return np.divide(small, large, out=np.zeros(n), where=large > 0)


def near_duplicates(docs: DataFrame, similarity: float = SIMILARITY, bands: int = BANDS, rows: int = ROWS, floor: float = FLOOR, words: int = WORDS, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """One row per input row: doc_id, node (the text), class_id (smallest doc_id of the group), class_size (rows), n_texts, first (whether the row is the one to keep)."""
    source = docs.select(F.col(doc_id).cast("long").alias("doc_id"), F.col(text).cast("string").alias("text"))
    n_docs, frequencies = document_frequencies(source, words)
    idf = Idf(n_docs, {}, floor)
    signed_rows = cut(signatures(frequencies, idf, bands, rows, words))
    every = signed_rows.drop("df")
    nodes = cut(every.groupBy("node", "check").agg(F.min("doc_id").alias("rep"), F.count(F.lit(1)).alias("n"), F.first("weight").alias("weight"), F.first("bands").alias("bands")))
    group = _groups(source, nodes, signed_rows, idf, similarity, words)
    # a text without words has no band: each such row is alone
    labelled = nodes.select("node", "check", "rep", "n", "weight").join(group.select(F.col("id").alias("node"), "group"), "node", "left").withColumn("group", F.coalesce("group", "node"))
    classes = labelled.groupBy("group").agg(F.min("rep").alias("class_id"), F.sum("n").alias("class_size"), F.count(F.lit(1)).alias("n_texts"))
    told = labelled.join(classes, "group").select("node", "check", "class_id", "class_size", "n_texts")
    out = every.select("doc_id", "node", "check", (F.col("weight") > 0).alias("_some")).join(told, ["node", "check"])
    return out.select("doc_id", "node", F.when(F.col("_some"), F.col("class_id")).otherwise(F.col("doc_id")).alias("class_id"), F.when(F.col("_some"), F.col("class_size")).otherwise(F.lit(1)).cast("long").alias("class_size"), F.when(F.col("_some"), F.col("n_texts")).otherwise(F.lit(1)).cast("long").alias("n_texts"), (~F.col("_some") | F.col("class_id").eqNullSafe(F.col("doc_id"))).alias("first"))


def _groups(source: DataFrame, nodes: DataFrame, every: DataFrame, idf: Idf, similarity: float, words: int) -> DataFrame:
    """(id, group) of the nodes that have a verified link."""
    keyed = nodes.where("weight > 0").select("node", "rep", "weight", F.explode("bands").alias("bucket"))
    shared = keyed.groupBy("bucket").agg(F.count(F.lit(1)).alias("n")).where("n > 1").select("bucket")
    member = cut(keyed.join(shared, "bucket").select("bucket", "node", "rep", "weight"))
    wanted = member.select("node", "rep").distinct()
    held = maybe_in(source.select(F.col("doc_id").alias("_id"), "text", node_of("text").alias("_node")), "_node", wanted.select("node"))
    held = held.join(wanted, F.col("_id").eqNullSafe(F.col("rep")) & (F.col("_node") == F.col("node")))
    known = maybe_in(every.select("node", "check", "df"), "node", wanted.select("node")).dropDuplicates(["node", "check"])
    texts = cut(held.select("node", "text", F.hash("text").alias("check")).dropDuplicates(["node"]).join(known, ["node", "check"]).select("node", F.struct("text", "df").alias("text")))

    def judge(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for batch in slices(whole, 2):
                ok = weighted_jaccard(batch.column(2), batch.column(3), idf, words, tuple(joined(batch.column(c).to_pylist()) for c in (4, 5))) >= similarity - 1e-9
                yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(ok)], names=["a", "b", "ok"])

    def verified(pairs: DataFrame) -> DataFrame:
        """Linked pairs of ``pairs`` (a, b, both weights)."""
        fits = F.least("wa", "wb") >= F.greatest("wa", "wb") * similarity - 1e-9
        one = pairs.where("a <> b").where(fits).select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).distinct()
        left, right = texts.select(F.col("node").alias("a"), F.col("text").alias("ta")), texts.select(F.col("node").alias("b"), F.col("text").alias("tb"))
        return one.join(left, "a").join(right, "b").select("a", "b", "ta.text", F.col("tb.text").alias("other"), "ta.df", F.col("tb.df").alias("other_df")).mapInArrow(judge, "a long, b long, ok boolean").where("ok").select("a", "b")

    links, label = None, None
    for seeds in (*HUBS, None):
        now = member.select("bucket", "node", "weight", F.col("node").alias("group")) if label is None else member.join(label, member["node"] == label["id"], "left").select("bucket", "node", "weight", F.coalesce("group", "node").alias("group"))
        if label is not None:  # only buckets that still hold several groups
            mixed = now.groupBy("bucket").agg(F.min("group").alias("lo"), F.max("group").alias("hi")).where("lo < hi").select("bucket")
            now = cut(now.join(mixed, "bucket"))
            if now.isEmpty():
                break
        if seeds:
            hubs = now.groupBy("bucket").agg(*(F.min(F.struct(F.xxhash64("node", F.lit(s)).alias("x"), "node", "weight", "group")).alias(f"h{s}") for s in seeds)).select("bucket", F.explode(F.array(*(f"h{s}" for s in seeds))).alias("h"))
            mine = hubs.select("bucket", F.col("h.node").alias("a"), F.col("h.weight").alias("wa"), F.col("h.group").alias("ga"))
            found = verified(mine.join(_right(now), "bucket").where(_fits(similarity)))
        else:
            size = now.groupBy("bucket").agg(F.count(F.lit(1)).alias("size"))
            small = now.join(size.where(F.col("size") <= SMALL).select("bucket"), "bucket")
            mine = small.select("bucket", F.col("node").alias("a"), F.col("weight").alias("wa"), F.col("group").alias("ga"))
            found = verified(mine.join(_right(small), "bucket").where(_fits(similarity) & (F.col("a") < F.col("b"))))
            large = now.join(size.where(F.col("size") > SMALL), "bucket").select("bucket", "size", "node", "group")
            found = found.union(_block_links(large, texts, idf, similarity, words))
        links = cut(found if links is None else links.union(found))
        label = cut(components(links))
    return label


def _right(now: DataFrame) -> DataFrame:
    return now.select("bucket", F.col("node").alias("b"), F.col("weight").alias("wb"), F.col("group").alias("gb"))


def _fits(similarity: float) -> Column:
    """Different groups, and totals near enough for the similarity."""
    return (F.col("ga") != F.col("gb")) & (F.least("wa", "wb") >= F.greatest("wa", "wb") * similarity - 1e-9)


def _block_links(large: DataFrame, texts: DataFrame, idf: Idf, similarity: float, words: int) -> DataFrame:
    """Links between different groups in ``large`` (bucket, size, node, group): each bucket's nodes are dealt to blocks by hash, each pair
    of blocks is one group of about 2 x BLOCK rows, compared as a matrix product; it tells links enough to join what they join."""
    dealt = large.join(texts.select("node", "text.text", "text.df"), "node").withColumn("n", F.ceil(F.col("size") / BLOCK).cast("int")).withColumn("own", F.pmod(F.xxhash64("node", F.lit(17)), F.col("n")).cast("int"))
    paired = dealt.select("bucket", "node", "group", "text", "df", "own", F.explode(F.expr("sequence(0, n - 1)")).alias("other")).select("bucket", F.least("own", "other").alias("i"), F.greatest("own", "other").alias("j"), "node", "group", "text", "df")

    def compare(table: pa.Table) -> pa.Table:
        node, group = table["node"].to_numpy(), table["group"].to_numpy()
        doc, value, count = weighted_sets(*shingles(table["text"], words))
        # a shingle that occurs k times is k features, so that minima of counts are common features
        doc, value, level = np.repeat(doc, count), np.repeat(value, count), ranges(count)
        _, feature = np.unique(value + level.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15), return_inverse=True)
        weight = np.zeros(feature.max(initial=-1) + 1)
        weight[feature] = np.repeat(idf.of(joined(table["df"].to_pylist()).astype(float)), count)
        total = np.bincount(doc, weights=weight[feature], minlength=len(node))
        shared = np.bincount(feature, minlength=len(weight)) > 1
        number = np.cumsum(shared) - 1
        keep = shared[feature]
        doc, feature, width = doc[keep], number[feature[keep]], int(shared.sum())
        weight = np.sqrt(weight[shared])
        common = np.zeros((len(node), len(node)))
        for a in range(0, width, 4096):
            here = (feature >= a) & (feature < a + 4096)
            part = np.zeros((len(node), min(4096, width - a)))
            part[doc[here], feature[here] - a] = weight[feature[here]]
            common += part @ part.T
        ok = common >= similarity * (total[:, None] + total[None, :] - common) - 1e-9
        parent = {int(g): int(g) for g in group}

        def find(x: int) -> int:
            while parent[x] != x:
                parent[x] = x = parent[parent[x]]
            return x

        links = []
        for x, y in zip(*np.nonzero(np.triu(ok & (group[:, None] != group[None, :]), 1)), strict=True):
            p, q = find(int(group[x])), find(int(group[y]))
            if p != q:
                parent[max(p, q)] = min(p, q)
                links.append((int(min(node[x], node[y])), int(max(node[x], node[y]))))
        return pa.table({"a": pa.array([r[0] for r in links], pa.int64()), "b": pa.array([r[1] for r in links], pa.int64())})

    return paired.groupBy("bucket", "i", "j").applyInArrow(compare, "a long, b long")


def keep_first(docs: DataFrame, doc_id: str = "doc_id", text: str = "text", **options) -> DataFrame:
    """``docs`` with one document of each near-duplicate group: the one of the smallest doc_id; of rows equal in id and text one stays, if it has words."""
    told = near_duplicates(docs, doc_id=doc_id, text=text, **options).where("first")
    out = told.groupBy(F.col("doc_id").alias("__kept_id"), F.col("node").alias("__kept_node")).agg((F.count(F.lit(1)) > 1).alias("__many"), (F.max("class_size") > 1).alias("__copied"))
    keyed = docs.withColumn("__own_node", node_of(text))
    same = keyed[doc_id].cast("long").eqNullSafe(out["__kept_id"]) & (keyed["__own_node"] == out["__kept_node"])
    repeated = F.col("__many") & F.col("__copied")
    once = keyed.join(out.where(~repeated), same, "left_semi")
    return once.union(keyed.join(out.where(repeated), same, "left_semi").dropDuplicates([doc_id, "__own_node"])).drop("__own_node")
