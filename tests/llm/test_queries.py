"""Every llm query on a small table, against SQL or a brute-force version, and on odd rows."""

import hashlib
import html
import itertools
import random
import re
import zlib

import duckdb
import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

from tests.oracle import compare
from vecjoin.llm import benchmark_winnowing, cross_parsing, fuzzy_lines, kernels, line_blocks, merge_dropout, mpeg_audio, registry, toxicity_kernel, unit_dedup, url_trees, weighted_minhash
from vecjoin.llm.tables import components

WORD = re.compile(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+")


def words(text):
    return WORD.findall((text or "").translate({i: i + 32 for i in range(65, 91)}))


@pytest.fixture(scope="module")
def docs():
    return dict(duckdb.sql("select doc_id, text from '/root/testdata/sf0.001/documents.parquet'").fetchall())


@pytest.fixture(scope="module")
def odd(spark):
    """Nulls in every column, empty and long texts, repeated rows and ids, and columns whose names operators use inside."""
    long = " ".join(f"word{i % 977}" for i in range(40_000))
    rows = [(1, "one two three four five six"), (1, "one two three four five six"), (2, None), (3, ""), (None, "one two three four five six"), (4, " \n\n \t"), (5, long), (5, "other text under a used id here"), (6, "ONE, two; three four five six!"), (7, "\U0001f642 ▁ \x00 é́ 日本語 テスト")]
    return spark.createDataFrame([(*r, None, f"x{i}", i, i, "clash", "u") for i, r in enumerate(rows)], "doc_id long, text string, lang string, node string, h1 int, `group` int, bucket string, unit_no string")


@pytest.fixture(scope="module")
def none(spark):
    return spark.createDataFrame([], "doc_id long, text string, lang string")


@pytest.mark.parametrize("name", list(registry.oracle_sql()))
def test_sql(spark, mid, name):
    assert compare(spark, mid, registry.queries()[name], registry.oracle_sql()[name]) == 1000


def test_components(spark):
    pairs = [(i, i + 1) for i in range(40)] + [(100, x) for x in range(200, 260)] + [(7, 7)]
    got = dict(components(spark.createDataFrame(pairs, "a long, b long")).collect())
    assert all(got[i] == 0 for i in range(41)) and all(got[x] == 100 for x in range(200, 260))
    assert components(spark.createDataFrame([], "a long, b long")).count() == 0


def test_media_round_trip(spark, small, docs):
    for r in registry.op2_media_columns(spark, small).collect():
        raw = (docs[r.doc_id] or "").encode()
        p = raw + b" " * (-len(raw) % 192 if raw else 192)
        assert (r.n_bytes, r.payload_bytes) == (len(raw), len(p)) and r.payload_sha256 == hashlib.sha256(p).hexdigest()
        assert r.tail_crc32 == zlib.crc32(p[-16:]) and r.duration_samples == 1152 * len(r.frame_offsets)


def test_media_resync_and_tags():
    payload = bytes(range(256)) * 20
    data = mpeg_audio.encode(payload)
    got, p = mpeg_audio.decode(data)
    assert got == payload and p["table"]["frames"] == len(p["offsets"]) == p["crc_good"] and p["skipped"] == 0
    assert all(mpeg_audio.header(data[o : o + 4]) for o in p["offsets"])
    begin = p["offsets"][2]
    hurt = data[:begin] + b"\xff\xfa junk" + data[begin:] + b"TAG" + b"title".ljust(125, b"\0")
    q = mpeg_audio.parse(hurt)
    assert q["ancillary"] == p["ancillary"] and q["skipped"] == 7 and q["tags"]["ID3v1"] == "title"
    flipped = bytearray(data)
    flipped[begin + 10] ^= 1
    assert mpeg_audio.parse(bytes(flipped))["crc_bad"] == 1
    with pytest.raises(ValueError):
        mpeg_audio.decode(bytes(flipped))
    assert mpeg_audio.parse(b"")["samples"] == 0 and mpeg_audio.parse(b"\xff" * 50)["offsets"] == []


def test_html(spark, small):
    pages = duckdb.sql("select page_id, html from '/root/testdata/sf0.001/pages.parquet'").fetchall()
    got = {r.page_id: r.text for r in registry.op3_html_extraction(spark, small).collect()}
    for i, page in pages:
        body = re.search(r"<article[^>]*>(.*?)(?:</article>|<footer|\Z)", page or "", re.S)
        parts = [html.unescape(re.sub(r"\s+", " ", re.sub(r"<[^>]+>", "", b.replace("<br>", " ")))).strip() for b in re.split(r"</?(?:p|h\d|div|li|ul)[^>]*>", body[1])] if body else []
        assert got[i] == "\n\n".join(p for p in parts if p)


def test_html_furniture():
    long = "Long enough sentences make a paragraph of this page and nothing else does. " * 3
    page = f"<html><head><title>t</title><script>var a='<p>x</p>'</script></head><body><nav><a href=x>Home</a></nav><div id='cookie-notice'>We use cookies</div><div><p>{long}</p><p>Short&nbsp;end &amp; more.</p></div><aside>side</aside><div class='comments'><p>{long}</p></div><form><p>Mail</p></form><footer>foot</footer>"
    assert line_blocks.main_text(page) == long.strip() + "\n\nShort end & more."
    assert line_blocks.main_text("<nav><li>menu<article><p>kept</p></article>") == "kept"
    assert line_blocks.main_text(None) == line_blocks.main_text("") == line_blocks.main_text("<script>x") == ""
    assert line_blocks.main_text("<article><p>a</p>" + "<div class=ad>x</div>" * 5 + "<p>b</p></article>") == "a\n\nb"


def test_url(spark, small):
    for r in registry.op10_url_filters(spark, small).collect():
        assert r.verdict in ("allow", "block")
    rows = spark.createDataFrame([(1, "HTTP://A.Example.ORG/es/x?y"), (2, "http://example.org/en/1#z"), (3, "http://x.com/fr/"), (4, "http://xcom/fr/"), (5, None), (6, "nothing"), (7, "http://org"), (8, "ftp://a.org?x=/"), (9, "http://notexample.org/en/1")], "page_id long, url string")
    got = {r.page_id: (r.host, r.path, r.rule) for r in url_trees.judge(rows).collect()}
    assert got == {1: ("a.example.org", "/es/x", "example.org/es/"), 2: ("example.org", "/en/1", "example.org/en/1"), 3: ("x.com", "/fr/", "com/fr/"), 4: ("xcom", "/fr/", None), 5: ("", "", None), 6: ("", "", None), 7: ("org", "", None), 8: ("a.org", "", None), 9: ("notexample.org", "/en/1", "org/")}
    x = np.random.default_rng(0).normal(size=(800, 4))
    y = ((x[:, 0] > 0) ^ (x[:, 1] > 0)).astype(float)
    assert (((url_trees.BoostedTrees(x, y)(x)) > 0.5) == y).mean() > 0.95


def brute_groups(texts, linked):
    parent = list(range(len(texts)))

    def find(i):
        while parent[i] != i:
            i = parent[i]
        return i

    for i, j in itertools.combinations(range(len(texts)), 2):
        if linked(i, j):
            a, b = find(i), find(j)
            parent[max(a, b)] = min(a, b)
    return [find(i) for i in range(len(texts))]


def test_near_duplicates_brute(spark):
    rng = random.Random(4)
    vocabulary = [f"w{i}" for i in range(400)]
    texts = []
    for _ in range(12):
        base = [rng.choice(vocabulary) for _ in range(rng.randint(60, 200))]
        texts.append(" ".join(base))
        for _ in range(rng.randint(0, 9)):
            copy = list(base)
            for _ in range(rng.randint(0, 6)):
                copy[rng.randrange(len(copy))] = rng.choice(vocabulary)
            texts.append(" ".join(copy))
    df = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    n, df_of = weighted_minhash.document_frequencies(df)
    value, ptr = kernels.shingles(pa.array(texts))
    sets = [set((value[a:z] >> np.uint64(20)).tolist()) for a, z in zip(ptr, ptr[1:], strict=False)]
    true = {}
    for s in sets:
        for x in s:
            true[x] = true.get(x, 0) + 1
    assert n == len(texts) and all(df_of.get(k) == v for k, v in true.items() if v >= 0.05 * n)
    idf = weighted_minhash.Idf(n, df_of, weighted_minhash.FLOOR)
    pairs = list(itertools.combinations(range(n), 2))
    j = dict(zip(pairs, weighted_minhash.weighted_jaccard(pa.array([texts[a] for a, _ in pairs]), pa.array([texts[b] for _, b in pairs]), idf), strict=True))
    want = brute_groups(texts, lambda a, b: j[a, b] >= 0.8)
    got = {r.doc_id: r.class_id for r in weighted_minhash.near_duplicates(df).collect()}
    assert [got[i] for i in range(n)] == want and len(set(want)) < n


def test_samples_estimate_similarity():
    rng = np.random.default_rng(1)
    s = np.sort(rng.integers(1, 1 << 62, 300).astype(np.uint64))
    wa, wb = rng.random(300) * 3 + 0.1, rng.random(300) * 3 + 0.1
    true = np.minimum(wa, wb).sum() / np.maximum(wa, wb).sum()
    code = weighted_minhash.samples(np.repeat([0, 1], 300), np.concatenate([s, s]), np.concatenate([wa, wb]), 2, 2000)
    assert abs((code[0] == code[1]).mean() - true) < 0.04


def edit(a, b):
    row = list(range(len(b) + 1))
    for i, x in enumerate(a, 1):
        last, row[0] = row[0], i
        for k, y in enumerate(b, 1):
            last, row[k] = row[k], min(row[k] + 1, row[k - 1] + 1, last + (x != y))
    return row[-1]


def test_edit_distance():
    rng = random.Random(1)
    for _ in range(400):
        a = "".join(rng.choice("abé ") for _ in range(rng.randint(0, 90)))
        b = "".join(c for c in a if rng.random() > 0.1) if rng.random() < 0.5 else "".join(rng.choice("abé ") for _ in range(rng.randint(0, 90)))
        true = edit(a, b)
        assert fuzzy_lines.edit_distance(a, b, 200) == true
        assert (fuzzy_lines.edit_distance(a, b, 12) <= 12) == (true <= 12)


def test_fuzzy_lines_brute(spark):
    rng = random.Random(9)
    vocabulary = [f"{a}{b}{c}" for a in "bdfgk" for b in "aeiou" for c in ("lm", "nt", "rs")]
    lines = []
    for _ in range(14):
        base = [rng.choice(vocabulary) for _ in range(rng.randint(30, 70))]
        lines.append(" ".join(base))
        for _ in range(rng.randint(0, 6)):
            copy = list(base)
            if rng.random() < 0.7:
                copy[rng.randrange(len(copy))] = rng.choice(vocabulary)
            else:
                copy.append(copy.pop(0))
            lines.append(" ".join(copy))
    lines += ["short line", "short line"]
    docs = [(i, "\n".join(lines[i * 4 : i * 4 + 4])) for i in range(-(-len(lines) // 4))]
    where = [(i, n) for i, t in docs for n, _ in enumerate(t.split("\n"))]
    flat = [line for _, t in docs for line in t.split("\n")]
    w, ptr = kernels.words_of(pa.array(flat))
    from vecjoin.llm.lines import simhashes

    code = simhashes(w, np.repeat(np.arange(len(flat)), np.diff(ptr)), len(flat))

    def linked(i, j):
        if len(words(flat[i])) < 5 or len(words(flat[j])) < 5:
            return False
        if flat[i] == flat[j]:
            return True
        return bin(int(code[i] ^ code[j])).count("1") <= 2 and edit(flat[i], flat[j]) <= 0.2 * max(len(flat[i]), len(flat[j])) + 1e-9

    want = brute_groups(flat, linked)
    gone = {where[i] for i, g in enumerate(want) if g != i}
    got = {(r.doc_id, r.unit_no) for r in fuzzy_lines.fuzzy_repeats(spark.createDataFrame(docs, "doc_id long, text string")).collect()}
    assert got == gone and gone


def test_language(spark, mid):
    truth = dict(duckdb.sql(f"select doc_id, lang from '{mid}/documents.parquet'").fetchall())
    rows = registry.op6_language_id(spark, mid).collect()
    held = [r for r in rows if r.held_out]
    assert len(rows) == 1000 and all(r.held_out == (zlib.crc32(str(r.doc_id).encode()) % 4 == 2) for r in rows)
    assert np.mean([truth[r.doc_id] == r.lang_pred for r in held]) > 0.97 and all(0 <= r.score <= 1 for r in rows)


def test_automaton_phrases():
    rng = random.Random(2)
    learned = "".join(rng.choice("abc ") for _ in range(300))
    parser = cross_parsing.CrossParser({"x": learned, "y": "zzz"})
    text = "".join(rng.choice("abcd ") for _ in range(400))
    code, _ = parser.codes([text])
    letters = "".join({i: c for c, i in ((c, int(parser.table[ord(c)])) for c in "abcz ")}.get(int(k), "d") for k in code)
    phrases, i = 0, 0
    while i < len(letters):
        n = 0
        while i + n < len(letters) and letters[i : i + n + 1] in learned:
            n += 1
        if i + n < len(letters):
            phrases += 1
        # the breaking letter opens the next match, unless nothing that was learned begins with it
        i += max(n, 1)
        if n and i < len(letters) and letters[i] not in learned:
            i += 1
    got = parser.automata[0].phrases(code.astype(np.int64)[:, None])[0]
    assert abs(int(got) - phrases) <= 1


def test_toxicity(spark, mid):
    toxic = dict(duckdb.sql(f"select doc_id, toxic from '{mid}/labels.parquet'").fetchall())
    rows = registry.op9_toxicity(spark, mid).collect()
    held = [r for r in rows if r.held_out and r.doc_id in toxic]
    accuracy = np.mean([r.predicted == toxic[r.doc_id] for r in held])
    assert len(rows) == 1000 and accuracy > 0.93, accuracy
    rng = random.Random(0)
    vocabulary = ["".join(rng.choice("abcdefghilmnoprstu") for _ in range(rng.randint(3, 8))) for _ in range(500)]
    clean = [" ".join(rng.choice(vocabulary) for _ in range(40)) for _ in range(200)]
    bad = [t + f" {rng.choice(['numbskull', 'blockhead'])} " + t for t in clean[:60]]
    model = toxicity_kernel.ToxicModel(clean + bad, [0] * 200 + [1] * 60)
    told = model(["you numbskull", "you numbxskull", "b l o c k h e a d here", "num.bsk.ull", "you " + vocabulary[3], None, ""])
    assert (told[:4] > 0.5).all() and (told[4:] < 0.5).all()


def test_kernel_norm():
    kernel = toxicity_kernel.Kernel("abcdefgh")
    for word in ("abc", "aabbc", "abcabcab", "hgfedcba"):
        raw = {}
        for i, j, k in itertools.combinations(range(len(word)), 3):
            t = word[i] + word[j] + word[k]
            raw[t] = raw.get(t, 0) + toxicity_kernel.DECAY ** (k - i + 1)
        code = np.array([[kernel.code[c] for c in word]])
        assert abs(float(kernel.norm(code)[0]) - sum(v * v for v in raw.values()) ** 0.5) < 1e-9


def test_pieces(spark, small, docs):
    sentencepiece = pytest.importorskip("sentencepiece")
    v = merge_dropout.pieces(merge_dropout.MODEL)
    texts = [t or "" for t in docs.values()] + [" a ", "a  b\n\n c", "① x", "", "日本語", "x" * 200]
    ids, count = merge_dropout.encode(texts, v, 0.0)
    library = sentencepiece.SentencePieceProcessor(model_file=merge_dropout.MODEL)
    at = np.cumsum(count) - count
    assert all(library.encode(t) == ids[a : a + n].tolist() for t, a, n in zip(texts, at, count, strict=True))
    a, n = merge_dropout.encode(texts, v, 0.3, seed=1)
    b, m = merge_dropout.encode(texts, v, 0.3, seed=2)
    assert merge_dropout.decode(a, n, v) == merge_dropout.decode(b, m, v) == texts and len(a) > len(ids) and not np.array_equal(n, m)
    rows = registry.op7_sentencepiece(spark, small).collect()
    assert len(rows) == len(docs) and all(r.lossless and len(r.ids) == r.n_pieces for r in rows)


def test_winnowing_blocks(spark):
    rng = random.Random(5)
    vocabulary = [f"v{i}" for i in range(30)]
    items = [(i, " ".join(rng.choice(vocabulary) for _ in range(rng.randint(0, 40)))) for i in range(30)] + [(7, "repeated id of an item"), (99, None)]
    docs = []
    for i in range(60):
        w = [rng.choice(vocabulary) for _ in range(rng.randint(0, 80))]
        if rng.random() < 0.5:
            part = words(rng.choice(items)[1])
            at = rng.randint(0, len(w))
            w[at:at] = part[rng.randint(0, 5) : rng.randint(5, 40)]
        docs.append((i, " ".join(w)))
    known = {}
    for i, t in items:
        w = words(t)
        n = min(10, len(w))
        for j in range(len(w) - n + 1 if n else 0):
            known.setdefault(tuple(w[j : j + n]), set()).add(str(i))
    df, bench = spark.createDataFrame(docs, "doc_id long, text string"), spark.createDataFrame(items, "item_id long, text string")
    for block in (1 << 20, 700):
        for r in benchmark_winnowing.decontaminate(df, bench, block_bytes=block).collect():
            w = words(docs[r.doc_id][1])
            hit, who = set(), set()
            for span, ids in known.items():
                for j in range(len(w) - len(span) + 1):
                    if tuple(w[j : j + len(span)]) == span:
                        hit.update(range(j, j + len(span)))
                        who |= ids
            assert (r.n_words, r.n_hit, r.n_items) == (len(w), len(hit), len(who)), (block, r)
            assert r.items_sha256 == hashlib.sha256(",".join(sorted(who)).encode()).hexdigest()
    kept = {r.doc_id for r in benchmark_winnowing.drop_contaminated(df, bench, block_bytes=700).collect()}
    assert kept == {r.doc_id for r in benchmark_winnowing.decontaminate(df, bench).where("not contaminated").collect()}


def test_odd_rows(spark, odd):
    n = odd.count()
    lines = unit_dedup.dedup_units(odd).collect()
    assert len(lines) == n and {r.node for r in lines} == {f"x{i}" for i in range(n)}
    fuzzy = fuzzy_lines.dedup_lines(odd).collect()
    assert len(fuzzy) == n and sum(r.n_removed for r in fuzzy) == sum(r.n_removed for r in lines) == 3  # the null id ranks first
    paragraphs = unit_dedup.dedup_units(odd, paragraphs=True).collect()
    assert len(paragraphs) == n
    near = weighted_minhash.near_duplicates(odd).collect()
    assert len(near) == n and [r.class_size for r in near if r.doc_id == 2] == [1]
    assert weighted_minhash.keep_first(odd).columns == odd.columns
    bench = spark.createDataFrame([(1, "three four five"), (None, "x"), (2, None)], "item_id long, text string")
    hits = benchmark_winnowing.decontaminate(odd, bench).collect()
    assert len(hits) == n and sorted(r.n_hit for r in hits)[-4:] == [3, 3, 3, 3]
    media = mpeg_audio.media_digests(mpeg_audio.encode_texts(odd)).collect()
    assert len(media) == n and min(r.payload_bytes for r in media) == 192
    told = cross_parsing.identify(odd, {"en": "one two three", "xx": "qqq zzz"}).collect()
    assert len(told) == n and {r.lang_pred for r in told if r.doc_id in (2, 3, 4)} == {"und"}
    assert {r.lang_pred for r in cross_parsing.identify(odd, cross_parsing.sample_texts(odd, F.lit(True))).collect()} == {"und"}
    encoded = merge_dropout.encode_docs(odd)
    assert all(r.lossless for r in encoded.collect())
    back = sorted((r.text for r in merge_dropout.decode_docs(encoded).collect()), key=str)
    assert back == sorted((r.text for r in odd.collect()), key=str)
    labels = spark.createDataFrame([(1, 1), (1, 0), (2, None), (None, 1), (3, 0)], "doc_id long, toxic int")
    model = toxicity_kernel.ToxicModel(*toxicity_kernel.training_texts(odd, labels, F.lit(True)))
    assert toxicity_kernel.score(odd, model).count() == n
    pages = odd.select(F.col("doc_id").alias("page_id"), F.lit(None).cast("string").alias("url"), F.col("text").alias("html"))
    assert line_blocks.page_texts(pages).count() == url_trees.judge(pages).count() == n
    assert line_blocks.extract(pages).columns == ["page_id", "url", "html", "text", "n_chars"]


def test_empty_tables(spark, none):
    bench = spark.createDataFrame([], "item_id long, text string")
    labels = spark.createDataFrame([], "doc_id long, toxic int")
    pages = spark.createDataFrame([], "page_id long, url string, html string")
    model = toxicity_kernel.ToxicModel(*toxicity_kernel.training_texts(none, labels, F.lit(True)))
    for df in (unit_dedup.dedup_units(none), fuzzy_lines.dedup_lines(none), weighted_minhash.near_duplicates(none), weighted_minhash.keep_first(none), benchmark_winnowing.decontaminate(none, bench), benchmark_winnowing.drop_contaminated(none, bench), mpeg_audio.media_digests(mpeg_audio.encode_texts(none)), cross_parsing.identify(none, cross_parsing.sample_texts(none, F.lit(True))), merge_dropout.encode_docs(none), toxicity_kernel.score(none, model), line_blocks.page_texts(pages), url_trees.judge(pages)):
        assert df.count() == 0


def test_pipeline(spark, small):
    import corpus_pipeline

    docs = spark.read.parquet(f"{small}/documents.parquet")
    before = docs.count()
    for name, stage in corpus_pipeline.STAGES[:-1]:
        out = stage(spark, docs, small)
        assert out.columns == corpus_pipeline.COLUMNS, name
        rows = out.collect()
        assert 0 < len(rows) <= before
        docs, before = spark.createDataFrame(rows, out.schema), len(rows)
    assert corpus_pipeline.run(spark, small).count() == before
