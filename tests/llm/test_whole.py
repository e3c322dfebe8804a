"""Cases in which an operator once did less than its whole job."""

import hashlib
import itertools
import random
import re
from collections import Counter

import duckdb
import numpy as np
import pyarrow as pa
from pyspark.sql import functions as F

from vecjoin.llm import benchmark_winnowing, fuzzy_lines, line_blocks, merge_dropout, mpeg_audio, unit_dedup, weighted_minhash


def test_lines_beyond_two_bits(spark):
    """Lines of edit similarity 0.8 or more go, however many bits their SimHashes differ in."""
    rng = random.Random(5)
    vocabulary = [f"{a}{b}{c}{d}" for a in "bdfgk" for b in "aeiou" for c in "lmnt" for d in ("ar", "es", "in")]
    texts, copies = [], 0
    for _ in range(60):
        base = [rng.choice(vocabulary) for _ in range(rng.randint(8, 40))]
        texts.append(" ".join(base))
        for k in (1, max(1, len(base) // 10)):
            other = list(base)
            for i in rng.sample(range(len(base)), k):
                other[i] = rng.choice(vocabulary)
            texts.append(" ".join(other))
            copies += 1
    out = fuzzy_lines.dedup_lines(spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")).collect()
    gone = [r.doc_id for r in out if r.n_removed]
    assert all(i % 3 for i in gone) and len(gone) >= 0.97 * copies


def test_every_occurrence_draws():
    """A chunk falls apart in as many ways as the dropout allows, within one text too, and as often as the rate says."""
    v = merge_dropout.pieces(merge_dropout.MODEL)
    texts = ["understanding " * 400, "understanding " * 399]
    ids, count = merge_dropout.encode(texts, v, 0.1)
    assert merge_dropout.decode(ids, count, v) == texts
    begins = [i for i, p in enumerate(ids.tolist()) if v.flat[v.begin[p]] == 32]
    forms = {tuple(ids[a:z].tolist()) for a, z in itertools.pairwise(begins)}
    plain, each = merge_dropout.encode(texts, v, 0.0)
    assert len(forms) > 8 and 1.05 < len(ids) / len(plain) < 3
    again = merge_dropout.encode(texts[::-1], v, 0.1)
    assert again[1].tolist() == count[::-1].tolist() and np.array_equal(again[0], np.concatenate([ids[count[0] :], ids[: count[0]]]))


def test_item_without_id(spark):
    """An item with a null id contaminates; only its id is missing from the list."""
    text = "alpha beta gamma delta epsilon zeta eta theta iota kappa lambda"
    docs = spark.createDataFrame([(1, f"so {text} ends"), (2, "nothing of it here at all")], "doc_id long, text string")
    bench = spark.createDataFrame([(None, text)], "item_id string, text string")
    got = {r.doc_id: (r.n_hit, r.n_items, r.contaminated) for r in benchmark_winnowing.decontaminate(docs, bench).collect()}
    assert got == {1: (11, 0, True), 2: (0, 0, False)}
    assert [r.doc_id for r in benchmark_winnowing.drop_contaminated(docs, bench).collect()] == [2]


def test_rows_across_blocks(spark):
    """Rows with equal or no doc_id stay apart when the benchmark goes in several blocks."""
    item = ["alpha beta gamma delta epsilon zeta eta theta iota kappa", "one two three four five six seven eight nine ten"]
    clean = "this text has ten words and none are known items"
    docs = spark.createDataFrame([(1, item[0]), (1, clean), (None, item[1]), (None, clean), (2, " ".join(item))], "doc_id long, text string")
    bench = spark.createDataFrame([(f"b{i}", t) for i, t in enumerate([*item, *(f"{clean} {i}x" * 3 for i in range(6))])], "item_id string, text string").where(F.col("item_id").isin("b0", "b1") | F.col("text").contains("5x"))
    want = sorted(map(tuple, benchmark_winnowing.decontaminate(docs, bench).select("doc_id", "n_words", "n_hit", "n_items").collect()), key=str)
    got = sorted(map(tuple, benchmark_winnowing.decontaminate(docs, bench, block_bytes=8).select("doc_id", "n_words", "n_hit", "n_items").collect()), key=str)
    assert got == want and len(got) == 5


def test_repeated_ids_keep_their_texts(spark):
    """Rows that share a doc_id are told apart by their texts: what is unique stays."""
    rng = random.Random(11)
    known, unique = (" ".join(f"{rng.choice('bdfgk')}{rng.choice('aeiou')}{rng.randrange(500)}" for _ in range(60)) for _ in range(2))
    docs = spark.createDataFrame([(1, known), (5, known), (5, unique), (5, known)], "doc_id long, text string")
    for dedup in (unit_dedup.dedup_units, unit_dedup.dedup_passages, fuzzy_lines.dedup_lines):
        got = sorted((r.doc_id, r.text, r.n_removed) for r in dedup(docs).collect())
        assert got == [(1, known, 0), (5, "", 1), (5, "", 1), (5, unique, 0)]


def test_passages_inside_lines(spark):
    """Passages of over 50 words go wherever in a line they begin; shared runs of under 39 words and short stock lines stay."""
    rng = random.Random(3)

    def some(n):
        return [f"{rng.choice('bdfgklmnprst')}{rng.choice('aeiou')}{rng.choice('bdfgklmnprst')}{rng.choice(['', 'er', 'ing'])}" for _ in range(n)]

    passages = [some(rng.randint(51, 140)) for _ in range(6)]
    short = [some(rng.randint(20, 38)) for _ in range(4)]
    stock = " ".join(some(9))
    texts, holds = [], []
    for i in range(90):
        w = some(rng.randint(0, 200))
        which = rng.randrange(6) if i % 3 == 0 else None
        part = passages[which] if which is not None else rng.choice(short)
        at = rng.randint(0, len(w))
        w[at:at] = [x if k else x.upper() for k, x in enumerate(part)]
        w += some(12)
        marks = [x + rng.choice([" ", " ", " ", ", ", ". ", "\n"]) for x in w]
        texts.append("".join(marks) + "\n" + stock)
        holds.append((which, at, len(part)))
    got = {r.doc_id: r for r in unit_dedup.dedup_passages(spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")).collect()}
    seen = set()
    for i, (which, at, n) in enumerate(holds):
        r = got[i]
        if which is None or which not in seen:
            assert r.n_removed == 0 and r.text == texts[i], i
        else:
            assert r.n_removed == 1, i
            gone = texts[i][r.removed[0].first : r.removed[0].last]
            assert texts[i][: r.removed[0].first] + texts[i][r.removed[0].last :] == r.text
            begins = [m.start() for m in unit_dedup._WORD.finditer(texts[i])]
            first, last = begins.index(r.removed[0].first), (begins + [len(texts[i])]).index(r.removed[0].last)
            assert at <= first < at + 12 and at + n - 12 < last <= at + n and len(gone.split()) >= 39
        seen.add(which)


def brute_stretches(texts, span, window):
    """What ``repeated_stretches`` finds, from its definition: (text, first word)."""
    size, first, out = span - window + 1, {}, set()
    for i, text in enumerate(texts):
        w = [m.group().lower() for m in re.finditer(r"[^\x00-\x2F\x3A-\x40\x5B-\x60\x7B-\x7F]+", text)]
        rank = [hashlib.md5(x.encode()).digest()[:8] for x in w]
        cuts = {min(range(s, s + window), key=lambda p: (rank[p], -p)) for s in range(len(w) - window + 1)} | {0, len(w) - size}
        for c in sorted(c for c in cuts if 0 <= c <= len(w) - size):
            j, b = first.setdefault(tuple(w[c : c + size]), (i, c))
            if j != i or c - b >= size:
                out.add((i, c))
    return out


def test_stretches_brute(spark):
    rng = random.Random(8)
    base = [rng.choice(["uno", "Dos", "tres", "日本", "é", "x1"]) for _ in range(400)]
    texts = [" ".join(base[(a := rng.randrange(300)) : a + rng.randrange(100)]) + rng.choice(["", " uno" * 60, "!"]) for _ in range(60)] + ["", "one", "the " * 300]
    df = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    for span, window in ((20, 6), (12, 1), (15, 15)):
        got = {(r.doc_id, r.at) for r in unit_dedup.repeated_stretches(df, span, window).collect()}
        assert got == brute_stretches(texts, span, window) and got


def test_recall_of_single_edits(spark):
    """Lines of sf0.01 with one character, word or number edited that stay at similarity 0.8: nine in ten go or more."""
    rng = random.Random(2)
    known = {line for (t,) in duckdb.sql("select text from '/root/testdata/sf0.01/documents.parquet' where text is not null").fetchall() for line in t.split("\n") if len(line.split()) >= 5 and len(line) < 400}
    lines = rng.sample(sorted(known), 400)
    vocabulary = [w for line in lines for w in line.split()]
    for kind in ("character", "word", "number"):
        edited = []
        for line in lines:
            w = line.split(" ")
            if kind == "number":
                w.append(str(rng.randrange(1000)))
            elif kind == "word":
                w[rng.randrange(len(w))] = rng.choice(vocabulary)
            else:
                k = rng.randrange(len(w))
                w[k] = w[k][:1] + rng.choice("abcdefgh") + w[k][2:]
            edited.append(" ".join(w))
        pairs = [(2 * i, a) for i, a in enumerate(lines)] + [(2 * i + 1, b) for i, b in enumerate(edited) if b != lines[i] and fuzzy_lines.similar(lines[i].lower(), b.lower(), 0.8)]
        gone = {r.doc_id for r in fuzzy_lines.dedup_lines(spark.createDataFrame(pairs, "doc_id long, text string")).where("n_removed > 0").collect()}
        asked = [i for i, _ in pairs if i % 2]
        assert sum(i in gone or i - 1 in gone for i in asked) >= 0.9 * len(asked), kind


def test_line_blocks_brute():
    """Stretches are runs of lines with text, with gaps shorter than the window, of which some window reaches the threshold."""
    rng = random.Random(4)
    for _ in range(300):
        sizes = [rng.choice([0, 0, 0, rng.randint(1, 120)]) for _ in range(rng.randint(0, 60))]
        window, threshold = rng.randint(1, 5), rng.choice([1, 86, 200])
        sums = [sum(sizes[i : i + window]) for i in range(len(sizes))]
        runs = []
        for i in (i for i, s in enumerate(sizes) if s):
            if runs and i - runs[-1][-1] <= window:
                runs[-1].append(i)
            else:
                runs.append([i])
        least = min(threshold, max(sums, default=0) / 2)
        want = [(r[0], r[-1] + 1) for r in runs if max(sums[r[0] : r[-1] + 1]) >= least]
        assert line_blocks.stretches(sizes, window, threshold) == want


def test_names_that_mention_furniture():
    long = "Long enough sentences make a paragraph of this page and nothing else does. " * 3
    page = f"<body class='has-sidebar'><div class='site-header'>top</div><div class='page has-sidebar'><p>{long}</p></div><div id=cookie_notice>We use cookies, as do others, and we say so in many words on every page.</div>"
    assert line_blocks.main_text(page) == long.strip()
    page = f"<article><header><h1>Head</h1></header><div class='entry-header'><h2>Title</h2></div><section class='related-work'><p>{long}</p></section><ul><li><a href=x>one</a><li><a>two</a><li><a>three</a></ul></article><p>{long}"
    assert line_blocks.main_text(page) == f"Head\n\nTitle\n\n{long.strip()}"


def naive_pieces(text, key, v, dropout):
    """Merges one by one on plain lists: best rank, leftmost, skipped candidates marked."""
    symbol = [(-1 if c in "▁\n" else v.char.get("▁" if c == " " else c, -1), i, i + 1) for i, c in enumerate(text)]
    skipped = set()
    while True:
        best = None
        for k, (a, b) in enumerate(itertools.pairwise(symbol)):
            hit = v.pairs.get(a[0] * v.base + b[0]) if a[0] >= 0 and b[0] >= 0 else None
            if hit and (a[1], b[1], b[2]) not in skipped and hit[0] < 2**31 - 1 and (best is None or hit[0] < best[0]):
                best = (hit[0], k, hit[1])
        if best is None:
            break
        a, b = symbol[best[1]], symbol[best[1] + 1]
        x = np.array([key], np.uint64)
        if merge_dropout._skipped(x, *(np.array([p]) for p in (a[1], b[1], b[2])), dropout)[0]:
            skipped.add((a[1], b[1], b[2]))
        else:
            symbol[best[1] : best[1] + 2] = [(best[2], a[1], b[2])]
    out = []
    for s, i, _ in symbol:
        out += [s] if 0 <= s < len(v.size) else [int(v.byte_id[x]) for x in text[i].encode()]
    return out


def test_dropout_brute(monkeypatch):
    """Rows of arrays, the agenda and plain lists give the same pieces at any dropout; a long run takes little time."""
    v = merge_dropout.pieces(merge_dropout.MODEL)
    rng = random.Random(6)
    texts = ["".join(rng.choice(["the", "ing", "é", "日", "un", " ", "stand", "x", "▁", "er"]) for _ in range(rng.randint(1, 30))) for _ in range(60)]
    for dropout in (0.0, 0.1, 0.5):
        monkeypatch.setattr(merge_dropout, "LONG", 10**9)
        rows = merge_dropout.encode(texts, v, dropout, 3)
        monkeypatch.setattr(merge_dropout, "LONG", 0)
        agenda = merge_dropout.encode(texts, v, dropout, 3)
        assert np.array_equal(rows[0], agenda[0]) and np.array_equal(rows[1], agenda[1])
        chunks = [c for t in texts for c in merge_dropout._CHUNK.findall(" " + t)]
        keys = np.arange(1, len(chunks) + 1, dtype=np.uint64) * np.uint64(0x9E3779B97F4A7C15)
        for c, k in zip(chunks, keys, strict=True):
            assert merge_dropout._merge_long(c, int(k), v, dropout).tolist() == naive_pieces(c, k, v, dropout)
    monkeypatch.setattr(merge_dropout, "LONG", 256)
    run = "".join(rng.choice("abcdefgh") for _ in range(100_000))
    ids, count = merge_dropout.encode([run], v, 0.1)
    assert merge_dropout.decode(ids, count, v) == [run]


def test_mark_in_short_frame():
    """A frame of under 62 bytes that holds the VBRI mark is a frame like others."""
    for size in range(40, 62):
        assert mpeg_audio._table(bytes(36) + b"VBRI" + bytes(size - 40), 32, 4) is None


def test_near_duplicates_in_blocks(spark, monkeypatch):
    """Buckets of more nodes than ``SMALL`` are compared in blocks, and the groups are those of all pairs."""
    monkeypatch.setattr(weighted_minhash, "SMALL", 3)
    monkeypatch.setattr(weighted_minhash, "BLOCK", 8)
    monkeypatch.setattr(weighted_minhash, "HUBS", weighted_minhash.HUBS[:1])
    asked = []
    blocks = weighted_minhash._block_links
    monkeypatch.setattr(weighted_minhash, "_block_links", lambda large, *rest: (asked.append(large.count()), blocks(large, *rest))[1])
    rng = random.Random(12)
    vocabulary = [f"w{i}" for i in range(400)]
    base = [rng.choice(vocabulary) for _ in range(120)]
    texts = [" ".join(base)]
    for _ in range(90):  # a chain of small edits: its ends are unlike
        base = list(base)
        for _ in range(rng.choice([1, 2, 4, 9])):
            base[rng.randrange(len(base))] = rng.choice(vocabulary)
        texts.append(" ".join(base))
    df = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    n, of = weighted_minhash.document_frequencies(df)
    idf = weighted_minhash.Idf(n, of, weighted_minhash.FLOOR)
    pairs = list(itertools.combinations(range(len(texts)), 2))
    alike = weighted_minhash.weighted_jaccard(pa.array([texts[a] for a, _ in pairs]), pa.array([texts[b] for _, b in pairs]), idf)
    group = list(range(len(texts)))
    for (a, b), j in zip(pairs, alike, strict=True):
        if j >= 0.8:
            low, high = sorted((group[a], group[b]))
            group = [low if g == high else g for g in group]
    got = {r.doc_id: r.class_id for r in weighted_minhash.near_duplicates(df).collect()}
    assert [got[i] for i in range(len(texts))] == group and sum(asked) > 0 and 1 < len(set(group)) < len(texts)


def test_keep_first_of_equal_rows(spark):
    text = " ".join(f"word{i}" for i in range(30))
    docs = spark.createDataFrame([(1, text, "a"), (1, text, "b"), (2, text, "c"), (3, "", "d"), (3, "", "e"), (4, None, "f"), (1, "other words of the same id are here", "g")], "doc_id long, text string, h1 string")
    kept = sorted(r.h1 for r in weighted_minhash.keep_first(docs).collect())
    assert kept[0] in "ab" and kept[1:] == ["d", "e", "f", "g"]


def _edited(rng: random.Random, line: str, edits: int) -> str:
    """``line`` with letters of ``edits`` different words replaced."""
    words = line.split(" ")
    for i in rng.sample(range(len(words)), edits):
        words[i] = rng.choice("qxz") + words[i][1:]
    return " ".join(words)


def test_every_pair_of_a_key_is_compared(spark, monkeypatch):
    """Lines of one key that are unlike its first line and near each other go, however far their SimHashes are; in blocks too."""
    rng = random.Random(9)
    lines = [" ".join(["common beginning here"] + ["".join(rng.choices("abcdefghij", k=5)) for _ in range(9)]) for _ in range(12)]
    texts = [t for line in lines for t in (line, _edited(rng, line, 9))]
    pairs = [(a, b) for a, b in itertools.combinations(range(len(texts)), 2) if fuzzy_lines.similar(texts[a], texts[b], 0.8)]
    assert pairs == [(2 * i, 2 * i + 1) for i in range(12)]
    forms = spark.createDataFrame([(i, len(t), [7] * 5) for i, t in enumerate(texts)], "h1 long, size int, bands array<int>")
    form = spark.createDataFrame(list(enumerate(texts)), "h1 long, form string")
    for block in (512, 5):
        monkeypatch.setattr(fuzzy_lines, "BLOCK", block)
        found = fuzzy_lines.key_links(fuzzy_lines.shared_keys(forms, 0.8), form, 0.8).distinct().collect()
        assert sorted((min(r), max(r)) for r in found) == pairs


def test_stage_drops_lines_unlike_the_first_of_their_key(spark, monkeypatch):
    """The pipeline's line stage removes a near line that shares its keys with an unlike first line."""
    import corpus_pipeline

    rng = random.Random(4)
    plain = fuzzy_lines.units
    monkeypatch.setattr(fuzzy_lines, "units", lambda *args, **options: plain(*args, **options).withColumn("bands", F.array(*[F.lit(7)] * 5)))
    lines = [" ".join("".join(rng.choices("abcdefghij", k=6)) for _ in range(10)) for _ in range(8)]
    texts = [t for line in lines for t in (line, _edited(rng, line, 9))]
    docs = spark.createDataFrame([(i, t, "en", "s", len(t)) for i, t in enumerate(texts)], "doc_id long, text string, lang string, source string, n_chars long")
    kept = {r.doc_id for r in corpus_pipeline.line_dedup(spark, docs, "").collect()}
    assert kept == set(range(0, 16, 2))


def test_frequencies_do_not_depend_on_the_chunk(spark, monkeypatch):
    """Small chunks of the first pass let more candidates through and lose none."""
    rng = random.Random(8)
    texts = [" ".join(["shared stock line of seven words here"] * (i % 3 == 0) + [rng.choice("abcdefg") for _ in range(30)]) for i in range(60)]
    df = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    want = weighted_minhash.document_frequencies(df)
    monkeypatch.setattr(weighted_minhash, "CHUNK", 50)
    assert want[0] == 60 and 20 in want[1].values() and weighted_minhash.document_frequencies(df) == want


def test_every_shingle_is_weighed_by_its_frequency(spark):
    """Frequencies of rare shingles are counted too: documents that share a long passage of 4 % of the documents and have text of their own stay apart."""
    rng = random.Random(21)
    some = lambda n: [f"w{rng.randrange(10**6)}" for _ in range(n)]
    passage = some(100)
    texts = [" ".join(passage + some(11)) for _ in range(16)] + [" ".join(some(60)) for _ in range(384)]
    df = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    n, of = weighted_minhash.document_frequencies(df)
    true = Counter(s for t in texts for s in {tuple(t.split()[i : i + 5]) for i in range(len(t.split()) - 4)})
    assert n == 400 and sorted(of.values()) == sorted(true.values())
    level = weighted_minhash.weighted_jaccard(pa.array(texts[:1]), pa.array(texts[1:2]), weighted_minhash.Idf(n, {}, 0.05))
    assert level[0] >= 0.8  # with one weight for all rare shingles they would go
    assert {r.class_size for r in weighted_minhash.near_duplicates(df).collect()} == {1}


def test_numbers_as_bytes():
    for x in ([], [0], [1, 255], [256, 0, 70_000], [2**44 - 1, 3]):
        assert weighted_minhash.from_bytes(weighted_minhash.to_bytes(np.array(x, np.uint64))).tolist() == x
