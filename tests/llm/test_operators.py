"""Dealt operators on hand-made tables, against brute force, and on awkward input."""

import hashlib
import random
import re
import zlib

import numpy as np
import pytest
from pyspark.sql import functions as F

from crowdrank.llm import ann, decontamination, html_text, jaccard_join, language_id, line_dedup, lm_scoring, packing, repair, substring_dedup, token_output
from crowdrank.llm.fm_index import FMIndex
from crowdrank.llm.tokens import PieceEncoder, default_path

rng = random.Random(5)
WORDS = [a + b for a in "ka lo mi nu re sa ti vo".split() for b in "ba de fi go hu ja".split()]
EXTRA = ["rank", "count", "w", "pos", "tok", "key", "lines", "m", "block", "places", "t", "shard", "items", "grp"]


def text(n, seed):
    r = random.Random(seed)
    return " ".join(r.choice(WORDS) + r.choice(["", "", "", ".", ",", ".\n"]) for _ in range(n))


def corpus():
    base = [text(120, i) for i in range(8)]
    shared = text(60, 99)
    near = base[0].split(" ")
    near[50] = "changed"
    docs = [*base, base[1], base[1], " ".join(near), shared + " " + base[2], base[3] + " " + shared, "", None, "   ", "word", "be " * 400, "\n\n", text(20_000, 7), "É. naïve—text 日本語。 a b\tc  d\n", "0 1 2 !!"]
    docs += ["one\ntwo\nthree", "zero\none\ntwo\nthree\nfour", "two\nthree"]
    return list(enumerate(docs))


def frame(spark, rows=None, extra=False):
    df = spark.createDataFrame(corpus() if rows is None else rows, "doc_id long, text string").withColumn("lang", F.when(F.col("doc_id") % 2 == 0, "xx").when(F.col("doc_id") % 3 == 0, None).otherwise("yy")).withColumn("source", F.lit(None).cast("string")).withColumn("n_chars", F.length("text").cast("long"))
    for name in EXTRA if extra else ():
        df = df.withColumn(name, F.lit(None).cast("int"))
    return df


def by_id(df, *cols):
    return {r["doc_id"]: tuple(r[c] for c in cols) for r in df.collect()}


# --- brute force


def brute_repeats(rows, width):
    words = {i: (t or "").encode().split() for i, t in rows}
    seen = {}
    for i, w in words.items():
        for s in range(len(w) - width + 1):
            seen.setdefault(tuple(w[s : s + width]), []).append((i, s))
    gone = {(i, s + k) for spots in seen.values() if len(spots) > 1 for i, s in spots for k in range(width)}
    out = {}
    for i, w in words.items():
        kept = b" ".join(x for p, x in enumerate(w) if (i, p) not in gone)
        out[i] = (len(w), len(w) - len(kept.split()), hashlib.sha256(kept).hexdigest())
    return out


@pytest.mark.parametrize("hot", [64, 0])
def test_substring_dedup(spark, hot):
    """``hot=0`` sends every minimiser with several segments the way of the hot ones."""
    got = by_id(substring_dedup.remove_repeats(frame(spark, extra=True), 35, hot_segments=hot, shard_texts=50), "n_words", "n_removed", "kept_sha256")
    assert got == brute_repeats(corpus(), 35)


def test_fm_index_counts_and_streams():
    r = np.random.default_rng(1)
    texts = [r.integers(1, 5, n).astype(np.uint64) for n in (30, 7, 1, 50, 12)]
    weights = np.array([1, 2, 1, 1, 3])
    index = FMIndex(texts, weights, 4)

    def count(p):
        return sum(int(w) * sum(np.array_equal(t[i : i + len(p)], p) for i in range(len(t) - len(p) + 1)) for t, w in zip(texts, weights, strict=True))

    for n in (1, 2, 3, 4):
        for _ in range(30):
            p = r.integers(1, 6, n).astype(np.uint64)
            assert index.occurrences(p) == count(p)
    stream = [*texts, r.integers(1, 6, 40).astype(np.uint64)]  # the last holds symbols and runs that are not indexed
    for t, got in zip(stream, index.statistics(stream), strict=True):
        assert got.tolist() == [count(t[i : i + 4]) for i in range(len(t) - 3)]


def brute_jaccard(rows, n=5, threshold=0.8):
    sets = {}
    for i, t in rows:
        w = (t or "").lower().encode().split()
        sets[i] = {tuple(w[s : s + min(n, len(w))]) for s in range(max(1, len(w) - n + 1))} if w else set()
    links = {i: [j for j in sets if j != i and sets[i] and sets[j] and len(sets[i] & sets[j]) >= threshold * len(sets[i] | sets[j])] for i in sets}
    root = {}
    for i in sorted(sets):
        todo = [i] if i not in root else []
        while todo:
            x = todo.pop()
            if x not in root:
                root[x] = i
                todo += links[x]
    return {i: (root[i], len(links[i])) for i in sets}


@pytest.mark.parametrize("block", [800, 2])
def test_jaccard_join(spark, block):
    """``block=2`` makes every group of three or more meet block by block."""
    rows = corpus() + [(100 + i, " ".join(w if k % 40 != i else "zz" for k, w in enumerate(text(300, 5).split()))) for i in range(9)]
    got = by_id(jaccard_join.jaccard_classes(frame(spark, rows, extra=True), block_docs=block), "class_id", "n_links")
    assert got == brute_jaccard(rows)


def test_jaccard_repeated_rows(spark):
    got = jaccard_join.jaccard_classes(frame(spark, [(1, "a b c d e f"), (1, "a b c d e f"), (2, "a b c d e f")])).collect()
    assert [(r["class_id"], r["n_links"]) for r in got] == [(1, 2)] * 3


def brute_lines(rows, g=2):
    lines = {i: t.split("\n") for i, t in rows if t is not None}
    first, gone = {}, set()
    for i in sorted(lines):
        for p in range(len(lines[i]) - g + 1):
            w = tuple(lines[i][p : p + g])
            if all(not x.strip(" ") for x in w):
                continue
            if first.setdefault(w, (i, p)) != (i, p):
                gone |= {(i, p + k) for k in range(g)}
    return {i: "\n".join(x for p, x in enumerate(ls) if (i, p) not in gone) for i, ls in lines.items()}


@pytest.mark.parametrize("guarantee", [2, 3])
def test_line_dedup(spark, guarantee):
    out = line_dedup.dedup_lines(frame(spark, extra=True), guarantee)
    assert out.columns[:-2] == frame(spark, extra=True).columns
    got = by_id(out, "text")
    assert {i: t for i, (t,) in got.items() if t is not None} == brute_lines(corpus(), guarantee)
    assert got[14] == (None,)


def test_decontamination(spark):
    items = [(1, "Alpha beta gamma delta epsilon zeta eta theta iota kappa la mu nu xi"), (2, "Short item"), (3, None), (4, "..."), (4, "short ITEM")]
    docs = [(0, "x. ALPHA beta gamma delta epsilon zeta eta theta iota kappa la mu nu! y"), (1, "a short item, here short"), (2, None), (3, ""), (4, "alpha beta gamma"), (5, "short item " * 30 + "pad " * 2000)]
    t = spark.createDataFrame(items, "item_id long, text string").withColumn("w", F.lit(1))
    for limit in (4_000_000, 0):
        hits = decontamination.find(frame(spark, docs, extra=True), t, broadcast_words=limit)
        assert {(r["doc_id"], r["start"], r["len"]) for r in hits.collect()} >= {(0, 1, 13), (1, 1, 2), (5, 0, 2)}
    got = by_id(decontamination.decontaminate(frame(spark, docs), t), "n_words", "n_hit", "contaminated")
    assert got == {0: (15, 13, True), 1: (5, 2, True), 2: (0, 0, False), 3: (0, 0, False), 4: (3, 0, False), 5: (2060, 60, False)}


def test_search(spark):
    r = np.random.default_rng(3)
    x = r.normal(size=(600, 16))
    x[300:420] = x[300] + r.normal(scale=0.01, size=(120, 16))  # near copies that codes cannot tell apart
    x[500:520] = x[500]
    rows = [(i, v.tolist()) for i, v in enumerate(x)] + [(1000, None), (1001, [0.0] * 16), (1020, [float("nan")] * 16), (1040, [None] + [1.0] * 15), (1060, [1.0])]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<double>").withColumn("rank", F.lit(1)).withColumn("v", F.lit(2))
    for measure in ("ip", "l2"):
        got = ann.search(df, F.col("vec_id") % 20 == 0, k=10, measure=measure, rerank=40).collect()
        found = {}
        for row in sorted(got, key=lambda q: (q["query_id"], q["rank"])):
            found.setdefault(row["query_id"], []).append(row["vec_id"])
        assert set(found) == set(range(0, 600, 20))
        hits = 0
        for q, ids in found.items():
            s = (x * x[q]).sum(1) if measure == "ip" else -((x - x[q]) ** 2).sum(1)
            s[q] = -np.inf
            hits += len(set(ids) & set(np.lexsort((np.arange(600), -s))[:10].tolist()))
        assert hits >= 0.9 * 10 * len(found)
    assert ann.search(df.limit(0), F.col("vec_id") % 20 == 0).count() == 0
    assert [r["vec_id"] for r in ann.search(df.filter("vec_id IN (0, 5, 1001)"), F.col("vec_id") % 20 == 0).collect()] == [5]


ODD = ["", None, "a  b   c", "\n\n x. y", "  lead", "trail  ", "it's can't. we'll,'d", "ÀB ć d", "x\t\ty z\n", "a\nb.\nCc d", "a \nb", "日本語。 テスト, 12 3.5 a1.b2 <|endoftext|> ok", "İI ß. ǅ. a\x1cd e", "à× b÷. é.— x—.", "a b c  d", "ë. öx u ̈ z", "' s 's. 'sam. x'S ID'LL", "A\x00b \x00. a.b,c!! --- ...x"]


@pytest.mark.parametrize("name,spaced", [("word_bpe_49k.json", False), ("byte_bpe_50k.json", True)])
def test_pieces_are_whole_text_ids(name, spaced):
    enc = PieceEncoder(default_path(name), spaced)
    texts = ODD + [t for _, t in corpus()]
    for t, got in zip(texts, enc.encode_all(texts, group=7), strict=True):
        assert np.frombuffer(got, "<u4").tolist() == enc.tokenizer.encode(t or "", add_special_tokens=False).ids


def test_packing(spark):
    tok = PieceEncoder(default_path("word_bpe_49k.json"), False).tokenizer
    rows = packing.pack_documents(frame(spark, extra=True), capacity=256, keep_ids=True).collect()
    ids = {}
    for r in sorted(rows, key=lambda r: (r["doc_id"], r["start"])):
        assert r["start"] == len(ids.setdefault(r["doc_id"], [])) and zlib.crc32(r["ids"]) == r["ids_crc32"]
        ids[r["doc_id"]] += np.frombuffer(r["ids"], "<u4").tolist()
    assert ids == {i: [*tok.encode(t or "", add_special_tokens=False).ids, 1] for i, t in corpus()}
    packs = {}
    for r in sorted(rows, key=lambda r: (r["sequence_id"], r["offset"])):
        assert r["offset"] == packs.get(r["sequence_id"], 0)
        packs[r["sequence_id"]] = r["offset"] + r["length"]
    assert set(packs) == set(range(len(packs))) and max(packs.values()) <= 256
    assert packing.pack_documents(frame(spark, [])).count() == 0


def test_shortest_pack_first():
    hist = {7: 2, 5: 3, 3: 4, 2: 1, 10: 1}
    out = packing.shortest_pack_first(hist, 10)
    assert all(sum(p) <= 10 for p, _ in out)
    assert {x: sum(n * p.count(x) for p, n in out) for x in hist} == hist


def test_token_output(spark):
    path = f"{spark.conf.get('spark.checkpoint.dir')}/ids-test"
    token_output.write_ids(frame(spark, extra=True), path, default_path("byte_bpe_50k.json"), shard_words=500)
    tok, start = PieceEncoder(default_path("byte_bpe_50k.json"), True).tokenizer, 0
    got = sorted(token_output.read_ids(spark, path, keep_ids=True).collect(), key=lambda r: r["doc_id"])
    for r, (i, t) in zip(got, corpus(), strict=True):
        want = [*tok.encode(t or "", add_special_tokens=False).ids, 0]
        assert (r["doc_id"], r["start"], np.frombuffer(r["ids"], "<u4").tolist()) == (i, start, want)
        start += len(want)


def test_repair_round_trip():
    r = np.random.default_rng(2)
    flat, sizes = r.integers(0, 6, 90).astype(np.uint32), np.array([1] + [4] * 10 + [49])
    flat[0] = 0
    seq = r.integers(1, 12, 4000)
    seq[499::500] = 0  # chunk 0 ends a document
    chunks = np.split(flat, np.cumsum(sizes)[:-1])
    rules, symbols, ends = repair.compress((flat, sizes), seq, 0, 6, least=2)
    docs = np.split(seq, np.flatnonzero(seq == 0)[:-1] + 1)
    want = [np.concatenate([chunks[c] for c in d]) for d in docs]
    shard = repair.Shard(repair.write_shard(list(range(len(docs))), np.array([len(w) for w in want]), rules, symbols, ends, 6))
    assert [np.frombuffer(shard.ids(i), "<u4").tolist() for i in reversed(range(len(docs)))] == [w.tolist() for w in reversed(want)]
    assert len(rules) and len(symbols) < sum(map(len, want)) / 2
    assert shard.lengths.tolist() == [len(shard.expand(x)) // 4 for x in range(6, 6 + len(rules))]
    for i, w in enumerate(want):
        for _ in range(20):
            lo, hi = sorted(r.integers(0, len(w) + 2, 2).tolist())
            assert np.frombuffer(shard.ids(i, lo, hi), "<u4").tolist() == w[lo:hi].tolist()


def test_repair_goes_on_until_nothing_is_frequent():
    """A passage of 4,096 different ids that is repeated whole, with its end, becomes one symbol."""
    flat, sizes = np.arange(4097, dtype=np.uint32), np.ones(4097, np.int64)
    seq = np.concatenate([np.append(np.arange(1, 4097), 0)] * 40)
    rules, symbols, ends = repair.compress((flat, sizes), seq, 0, 4097)
    assert len(symbols) == 40 and len(rules) == 4096
    shard = repair.Shard(repair.write_shard([None, *range(39)], np.full(40, 4097), rules, symbols, ends, 4097))
    assert shard.docs[0] is None and np.frombuffer(shard.ids(7, 4000, 4003), "<u4").tolist() == [4001, 4002, 4003]


def test_language_id(spark):
    words = {"aa": "kalo mire sati vonu kasa".split(), "bb": "xexo pippo dudda queque xilla".split()}
    rows = [(i, " ".join(rng.choice(words[lang]) for _ in range(30)), lang) for i in range(200) for lang in ("aa" if i % 2 else "bb",)]
    df = spark.createDataFrame(rows, "doc_id long, text string, lang string")
    model = language_id.fit(df.filter(~language_id.held_out()))
    probe = spark.createDataFrame([(0, "Kalo kalosati"), (1, "xexopippo"), (2, None), (3, "12 --"), (4, "")], "doc_id long, text string").withColumn("score", F.lit(1)).withColumn("lang_pred", F.lit("z"))
    got = by_id(language_id.predict(probe, model), "lang_pred")
    assert got == {0: ("aa",), 1: ("bb",), 2: ("und",), 3: ("und",), 4: ("und",)}
    assert by_id(language_id.predict(df, model), "lang_pred") == {i: (lang,) for i, _, lang in rows}
    empty = language_id.fit(df.limit(0))
    assert {r["lang_pred"] for r in language_id.predict(probe, empty).collect()} == {"und"}


def test_scores(spark):
    rows = corpus()
    words = {i: (t or "").encode().split() for i, t in rows}
    counts = {}
    for w in words.values():
        for k in (1, 2, 3):
            for s in range(len(w) - k + 1):
                g = tuple(w[s : s + k])
                counts[g] = counts.get(g, 0) + 1
    total = sum(map(len, words.values()))

    def one(w, i):
        for k in (3, 2):
            if i >= k - 1 and counts[tuple(w[i - k + 1 : i + 1])] >= 2:
                return np.log(counts[tuple(w[i - k + 1 : i + 1])] / counts[tuple(w[i - k + 1 : i])]) + np.log(0.4) * (min(3, i + 1) - k)
        return np.log(counts[(w[i],)] / total) + np.log(0.4) * (min(3, i + 1) - 1)

    got = by_id(lm_scoring.score(frame(spark, extra=True), block_bytes=5_000, slice_bytes=20_000), "n_words", "log_score")
    for i, w in words.items():
        assert got[i][0] == len(w) and np.isclose(got[i][1], sum(one(w, p) for p in range(len(w))))
    assert lm_scoring.score(frame(spark, [])).count() == 0


PAGE = "<html><head><title>T</title><style>p>a{}</style></head><body><header>H</header><nav><ul><li>m</ul></nav>{open}<article><h1>A &amp; B</h1><!-- <p>no</p> --><p>one\n two<b>x</b><br>three<script>var a='</p>';</script><div class='ad'>buy</div><div class=\"user-comments\"><p>me too</div><p>&eacute;&nbsp;end</article><footer>F</footer>"


def test_html(spark):
    pages = [(1, "http://h.org/a/1", PAGE.replace("{open}", "<p>Site line<p>only one")), (2, "https://h.org/a/2.html?x=1", PAGE.replace("{open}", "<p>Site line<p>only two")), (3, "http://g.org/a/1", PAGE.replace("{open}", "<p>Site line")), (4, None, None), (5, "http://h.org/z", ""), (6, "http://h.org/b", "plain &lt;text&gt;"), (7, "x", "<p>cut <b")]
    df = spark.createDataFrame(pages, "page_id long, url string, html string").withColumn("text", F.lit(1)).withColumn("shared", F.lit(2)).repartition(3)
    got = {r["page_id"]: (r["text"], r["n_chars"]) for r in html_text.extract(df).collect()}
    article = "A & B\none twox\nthree\né end"
    assert got[1][0] == "only one\n" + article and got[2][0] == "only two\n" + article and got[3][0] == "Site line\n" + article
    assert got[4] == ("", 0) and got[5] == ("", 0) and got[6] == ("plain <text>", 12) and got[7][0].startswith("cut")
    assert all(n == len(t) for t, n in got.values())
    assert html_text.extract(df.limit(0)).count() == 0


def test_common_lines_is_longest():
    def longest(a, b):
        t = [[0] * (len(b) + 1) for _ in range(len(a) + 1)]
        for i, x in enumerate(a):
            for j, y in enumerate(b):
                t[i + 1][j + 1] = t[i][j] + 1 if x == y else max(t[i][j + 1], t[i + 1][j])
        return t[-1][-1]

    for seed in range(60):
        r = random.Random(seed)
        a, b = ([r.randrange(6) for _ in range(r.randrange(14))] for _ in range(2))
        got = html_text.common_lines(a, b)
        assert len(got) == longest(a, b)


@pytest.mark.parametrize("f", [lambda d: substring_dedup.remove_repeats(d), lambda d: jaccard_join.jaccard_classes(d), lambda d: line_dedup.dedup_lines(d), lambda d: decontamination.decontaminate(d, d.withColumnRenamed("doc_id", "item_id"))])
def test_empty_tables_and_null_ids(spark, f):
    assert f(frame(spark, [])).count() == 0
    assert f(frame(spark, [(None, "a b c\nd e f"), (None, None), (3, "a b c\nd e f")])).count() >= 1


def test_words_contract():
    words = re.findall(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+", "a-b c_d É1".lower())
    assert words == ["a", "b", "c", "d", "é1"]
