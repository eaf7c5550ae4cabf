"""Nulls, repeated rows, ties, long texts, empty tables and clashing columns, against brute force."""

import hashlib
import random
from urllib.parse import urlsplit

import numpy as np
import pytest
from pyspark.sql import functions as F

from crowdrank.llm import ann, decontamination, html_text, jaccard_join, language_id, line_dedup, lm_scoring, packing, substring_dedup, token_output
from crowdrank.llm.tokens import default_path
from tests.llm.test_operators import WORDS, brute_jaccard, brute_repeats, corpus, frame, text

LONG = text(40, 1)
#: rows without an id, one id with two texts, a whole row twice
ROWS = [(None, LONG + " tail"), (None, LONG + " other end"), (1, text(50, 2)), (1, "x " + LONG), (2, text(50, 2)), (3, text(60, 3)), (3, text(60, 3)), (None, None), (4, "")]


def listed(df, *cols):
    return sorted((tuple(r[c] for c in cols) for r in df.collect()), key=str)


def test_substring_dedup_by_row(spark):
    want = brute_repeats(list(enumerate(t for _, t in ROWS)), 35)
    got = listed(substring_dedup.remove_repeats(frame(spark, ROWS, extra=True)), "doc_id", "n_words", "n_removed", "kept_sha256")
    assert got == sorted(((i, *want[k]) for k, (i, _) in enumerate(ROWS)), key=str)


def test_jaccard_by_row(spark):
    rows = [(None, LONG), (None, LONG.upper()), (7, LONG), (5, text(50, 2)), (5, text(80, 9)), (6, text(80, 9)), (None, "lonely words"), (8, None)]
    brute = brute_jaccard(list(enumerate(t for _, t in rows)))
    got = {}
    for r in jaccard_join.jaccard_classes(frame(spark, rows, extra=True)).collect():
        got.setdefault((r["doc_id"], r["n_grams"]), []).append((r["class_id"], r["n_links"], r["first"]))
    assert got[(7, 36)] == [(7, 2, True)] and got[(None, 36)] == [(7, 2, False)] * 2
    assert got[(5, 46)] == [(5, 0, True)] and got[(5, 76)] == [(5, 1, True)] and got[(6, 76)] == [(5, 1, False)]
    assert got[(None, 1)] == [(None, 0, True)] and got[(8, 0)] == [(8, 0, True)]
    assert sorted(n for rows in got.values() for _, n, _ in rows) == sorted(n for _, n in brute.values())


def test_jaccard_near_the_threshold(spark):
    """Links of many similarities, most of them near 0.8: none is lost, and prefixes are shortened for them."""
    r, rows = random.Random(4), []
    for g in range(40):
        base = text(200, 1000 + g).split()
        for k in range(6):
            words = base[:]
            for at in r.sample(range(200), r.choice([1, 3, 4, 5])):
                words[at] = f"z{r.random()}"
            rows.append((10 * g + k, " ".join(words)))
    got = {r["doc_id"]: (r["class_id"], r["n_links"]) for r in jaccard_join.jaccard_classes(frame(spark, rows), block_docs=5).collect()}
    assert got == brute_jaccard(rows)


def test_estimated_recall_decides():
    close, far = np.zeros(jaccard_join.STEPS), np.zeros(jaccard_join.STEPS)
    close[-1], far[0] = 10, 10
    assert jaccard_join.estimated_recall(close, 0.8, 8, 24) > 0.99999
    assert jaccard_join.estimated_recall(far, 0.8, 8, 24) < 0.99 < jaccard_join.estimated_recall(far, 0.8, 5, 24)
    assert jaccard_join.estimated_recall(far * 0, 0.8, 5, 24) == 0
    assert jaccard_join.shortest_needed(24, 8, 0.8, 0.99999) == 4


def test_sorted_labels_keep_what_matches(spark):
    """Against all pairs: a label stays if some other label of its tree shares a long enough prefix."""
    r = np.random.default_rng(3)
    sig = r.integers(0, 3, (60, 24, 8)).astype(">u2")
    reps = spark.createDataFrame([(i, bytearray(x.tobytes())) for i, x in enumerate(sig)], "rid long, sig binary")
    got = {(x["tree"], x["rid"]): x["deep"] for x in jaccard_join.sorted_labels(reps, 24, 4).collect()}
    for t in range(24):
        for i in range(60):
            best = max(int((sig[i, t] == sig[j, t]).cumprod().sum()) for j in range(60) if j != i)
            assert best < 4 or got.get((t, i), 0) >= best


def test_lines_null_and_repeated_ids(spark):
    rows = [(None, "a b c d e\nx"), (1, "a b c d e\ny"), (2, "p q r s\nt"), (2, "p q r s\nt"), (3, "p q r s\nu"), (4, None), (5, ""), (6, "k l m n"), (6, "\nk l m n\nz")]
    df = frame(spark, rows, extra=True).withColumn("n_lines", F.lit("mine"))
    got = line_dedup.dedup_lines(df, single_words=4)
    assert got.columns == [c for c in df.columns if c != "n_lines"] + ["n_lines", "n_removed"]
    want = [(None, "a b c d e\nx"), (1, "y"), (2, "p q r s\nt"), (2, "p q r s\nt"), (3, "u"), (4, None), (5, "")]
    assert listed(got.filter("doc_id IS NULL OR doc_id < 6"), "doc_id", "text") == sorted(want, key=str)


def test_lines_need_their_extension(spark):
    """Only selected lines are joined; those beside them go because matches are extended."""
    rows = [(1, "a\nb\nc\nd\ne\nf\ng"), (2, "x\na\nb\nc\nd\ne\nf\ng\ny"), (3, "a\nq\nc")]
    marks = line_dedup.fingerprints(frame(spark, rows), 3, None, "doc_id", "text")
    selected = {(r["doc"], r["pos"]) for r in marks.collect()}
    deleted = {(r["doc"], p) for r in line_dedup.repeats(frame(spark, rows), 3).collect() for p in range(r["start"], r["start"] + r["width"])}
    assert deleted == {(2, p) for p in range(2, 9)}
    assert deleted - selected and len(selected) < 7 + 9 + 3
    assert listed(line_dedup.dedup_lines(frame(spark, rows), 3), "doc_id", "text") == [(1, rows[0][1]), (2, "x\ny"), (3, rows[2][1])]


def test_long_runs_of_one_line(spark):
    rows = [(1, "\n".join(["same line of words"] * 3000)), (2, "same line of words"), (3, "\n" * 5000)]
    got = dict(listed(line_dedup.dedup_lines(frame(spark, rows), single_words=4), "doc_id", "text"))
    assert got == {1: "same line of words", 2: "", 3: "\n" * 5000}


def test_decontamination_by_row(spark):
    passage = " ".join(f"b{i}" for i in range(13))
    docs = [(None, f"x {passage}"), (None, "clean words"), (1, passage), (1, "also clean"), (2, passage), (2, passage), (3, " ".join(["b0"] * 30_000) + " " + passage)]
    items = spark.createDataFrame([(None, passage), (9, passage)], "item_id long, text string").withColumn("tok", F.lit(1))
    for limit in (4_000_000, 0):
        hits = decontamination.find(frame(spark, docs, extra=True), items, broadcast_words=limit)
        assert len({(r["doc_id"], r["th"], r["start"]) for r in hits.collect()}) == 4
    out = decontamination.decontaminate(frame(spark, docs, extra=True), items)
    assert listed(out, "doc_id", "n_words", "n_hit", "contaminated") == sorted([(None, 14, 13, True), (None, 2, 0, False), (1, 13, 13, True), (1, 2, 0, False), (2, 13, 13, True), (2, 13, 13, True), (3, 30_013, 13, False)], key=str)
    assert {tuple(r["items"]) for r in out.filter("n_hit > 0").collect()} == {("", "9")}
    assert decontamination.decontaminate(frame(spark, docs), items.limit(0)).filter("n_hit > 0").count() == 0
    assert decontamination.decontaminate(frame(spark, []), items).count() == 0


def test_token_output_and_packing_by_row(spark):
    path = f"{spark.conf.get('spark.checkpoint.dir')}/ids-edges"
    token_output.write_ids(frame(spark, ROWS, extra=True), path, default_path("byte_bpe_50k.json"), shard_words=30)
    rows = token_output.read_ids(spark, path).orderBy("start").collect()
    assert [r["doc_id"] for r in rows] == sorted((i for i, _ in ROWS), key=lambda i: (i is not None, i))
    assert [r["start"] for r in rows] == np.cumsum([0] + [r["n_tokens"] for r in rows])[:-1].tolist()
    assert listed(packing.pack_documents(frame(spark, ROWS)).groupBy("doc_id").count(), "doc_id", "count") == [(1, 2), (2, 1), (3, 2), (4, 1), (None, 3)]
    empty = f"{spark.conf.get('spark.checkpoint.dir')}/ids-none"
    token_output.write_ids(frame(spark, []), empty, default_path("byte_bpe_50k.json"))
    assert token_output.read_ids(spark, empty).count() == 0


def test_scores_by_row(spark):
    got = listed(lm_scoring.score(frame(spark, ROWS, extra=True), block_bytes=200, slice_bytes=500), "doc_id", "n_words", "log_score")
    again = listed(lm_scoring.score(frame(spark, ROWS[::-1])), "doc_id", "n_words", "log_score")
    assert [r[:2] for r in got] == [r[:2] for r in again] and np.allclose([r[2] for r in got], [r[2] for r in again])
    assert [r for r in got if r[0] == 3][0] == [r for r in got if r[0] == 3][1]


def test_language_of_odd_texts(spark):
    rows = [(i, "kalo mire" if i % 2 else "xexo pippo", "aa" if i % 2 else "bb") for i in range(40)]
    df = spark.createDataFrame([*rows, (None, "kalo", "bb"), (99, None, "aa")], "doc_id long, text string, lang string")
    model = language_id.fit(df)
    odd = ["\u00bd \u00b2 \u2460 \u2167", "12", "_", "", None, "\u00bdkalo\u00b2", "kalo xexo", "kalo " * 30_000]
    got = [lang for lang, _ in model.predict(odd)]
    assert got[:5] == ["und"] * 5 and got[5] == "aa" and got[7] == "aa"
    assert model.predict(["kalo xexo"])[0][0] == "aa" and abs(model.predict(["kalo xexo"])[0][1] - 0.5) < 0.01
    assert language_id.predict(df.limit(0), model).count() == 0


def brute_scores(words, counts, grams, langs, max_gram):
    """Word scores by plain dictionaries: own frequencies first, then the longest known n-grams."""
    out = []
    for w in words:
        if w in counts:
            out.append(counts[w])
            continue
        m = f"^{w}$"
        for n in range(min(max_gram, len(m)), 0, -1):
            hits = [grams[m[i : i + n]] for i in range(len(m) - n + 1) if m[i : i + n] in grams]
            if hits:
                out.append(np.mean(hits, axis=0))
                break
        else:
            out.append(np.zeros(langs))
    return np.array(out)


def test_language_scores_against_plain_dictionaries():
    r = random.Random(3)
    words = {w: np.random.default_rng(i).normal(size=3) for i, w in enumerate(WORDS[:20])}
    grams = {g: np.random.default_rng(100 + i).normal(size=3) for i, g in enumerate(["^k", "ka", "a$", "b", "lo$", "^mi", "e$", "ti", "^tib"])}
    model = language_id.WordFirstModel(["a", "b", "c"], language_id.Scores.of(words, 3), language_id.Scores.of(grams, 3), 4)
    probe = WORDS + ["".join(r.choice("kalobmtie") for _ in range(r.randrange(1, 7))) for _ in range(200)]
    assert np.allclose(model.word_scores(probe), brute_scores(probe, words, grams, 3, 4), atol=1e-5)


def test_search_edges(spark):
    rows = [(0, [1.0, 0.0]), (0, [1.0, 0.0]), (20, [0.5, 0.5]), (3, [1.0, 0.0]), (2, [1.0, 0.0]), (None, [1.0, 0.0]), (40, [1.0, 1.0, 1.0])]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<double>")
    got = listed(ann.search(df, F.col("vec_id") % 20 == 0, k=3), "query_id", "rank", "vec_id")
    # the row with id 0 stands twice, as a query and as a candidate; ties go to the smaller id
    assert [x for x in got if x[0] == 20] == [(20, 1, 0), (20, 2, 0), (20, 3, 2)]
    assert {x[2] for x in got if x[0] == 0} == {2, 3} or {x[2] for x in got if x[0] == 0} == {2, 3, 20}


def brute_extract(pages):
    """Decisions in plain Python, with a table of longest common subsequences."""

    def lcs(a, b):
        t = [[0] * (len(b) + 1) for _ in range(len(a) + 1)]
        for i in range(len(a) - 1, -1, -1):
            for j in range(len(b) - 1, -1, -1):
                t[i][j] = t[i + 1][j + 1] + 1 if a[i] == b[j] else max(t[i + 1][j], t[i][j + 1])
        i = j = 0
        found = set()
        while i < len(a) and j < len(b):
            if a[i] == b[j]:
                found.add(i)
                i, j = i + 1, j + 1
            elif t[i + 1][j] >= t[i][j + 1]:
                i += 1
            else:
                j += 1
        return found

    order = sorted(pages, key=lambda p: (urlsplit(p[1]).hostname, urlsplit(p[1]).path, p[0]))
    lines = [html_text.page_lines(h) for _, _, h in order]
    out = {}
    for i, (page, url, _) in enumerate(order):
        sides = []
        for j in (i - 1, i + 1):
            if 0 <= j < len(order) and urlsplit(order[j][1]).hostname == urlsplit(url).hostname:
                sides.append(lcs([t for t, _ in lines[i]], [t for t, _ in lines[j]]))
        gone = set()
        for kind in (html_text.ARTICLE, html_text.OPEN):
            own = [k for k, (_, x) in enumerate(lines[i]) if x == kind]
            size = lambda ks: sum(len(lines[i][k][0].split(" ")) for k in ks)
            judges = [s for s in sides if 2 * size([k for k in own if k in s]) <= size(own)]
            if kind == html_text.OPEN and judges:
                for k in own:
                    votes = [k in s for s in judges]
                    if all(votes) or any(votes) and size([k]) < html_text.LONG:
                        gone.add(k)
            elif len(judges) == 2:
                for seq in (own, own[::-1]):
                    for k in seq:
                        if size([k]) > html_text.SHORT or lines[i][k][0][-1] in html_text.ENDINGS or not all(k in s for s in judges):
                            break
                        gone.add(k)
        out[page] = "\n".join(t for k, (t, x) in enumerate(lines[i]) if x != html_text.BOILERPLATE and k not in gone)
    return out


@pytest.mark.parametrize("parts", [1, 7])
def test_extract_against_brute_force(spark, parts):
    r, pages = random.Random(8), []
    site = [f"Site part {i}" for i in range(4)] + [text(30, 77).replace("\n", " ")]
    for i in range(60):
        own = [f"own {i} {k} " + text(r.randrange(1, 30), 100 * i + k).replace("\n", " ") for k in range(r.randrange(1, 5))]
        # shared lines stand in one order, so the longest common subsequence is no matter of ties
        head, foot = r.sample(site[:2], r.randrange(3)), r.sample(site[2:], r.randrange(4))
        body = "".join(f"<p>{x}" for x in own)
        inner = "<p>Read on<p>Share it" if i % 3 else ""
        html = "".join(f"<div>{x}</div>" for x in sorted(head)) + (f"<article>{body}{inner}</article>" if i % 2 else body) + "".join(f"<div>{x}</div>" for x in sorted(foot))
        pages.append((i, f"http://h{i % 4}.org/{i // 8}/{r.randrange(40):02d}", html))
    df = spark.createDataFrame(pages, "page_id long, url string, html string").withColumn("gone", F.lit(1)).withColumn("lines", F.lit("x"))
    old = spark.conf.get("spark.sql.shuffle.partitions")
    spark.conf.set("spark.sql.shuffle.partitions", str(parts))
    try:
        got = {r["page_id"]: r["text"] for r in html_text.extract(df.repartition(5)).collect()}
    finally:
        spark.conf.set("spark.sql.shuffle.partitions", old)
    assert got == brute_extract(pages)
    assert any("Read on" not in got[i] for i in range(60) if i % 6 in (1, 5)) and any("Read on" in t for t in got.values())


def test_pages_by_row(spark):
    long = "<div>" + "<p>".join(f"line {i} " + "word " * 30 for i in range(3000)) + "</div>"
    pages = [(1, "http://a.b/1", "<p>one<p>site"), (1, "http://a.b/1", "<p>two<p>site"), (1, "http://a.b/1", "<p>two<p>site"), (None, None, "<p>no url"), (None, None, None), (2, "http://c.d/1", long)]
    got = listed(html_text.extract(spark.createDataFrame(pages, "page_id long, url string, html string")), "page_id", "url", "text")
    # the two equal rows are copies of each other and decide nothing about each other
    assert [t for i, _, t in got if i == 1] == ["one", "two", "two"] or [t for i, _, t in got if i == 1] == ["one", "two", "two\nsite"] or [t for i, _, t in got if i == 1] == ["one", "two\nsite", "two\nsite"]
    assert [t for i, u, t in got if u is None] == ["", "no url"]
    assert [len(t.split("\n")) for i, _, t in got if i == 2] == [3000]


def test_articles_that_say_the_same_stay_whole(spark):
    """A sentence that ends three neighbouring articles is text; a bare label there is not."""
    html = "<article><h1>Title {i}</h1><p>Paragraph {i} " + "word " * 20 + "<p>The same last words.<p>{label}</article>"
    pages = [(i, f"http://h.org/{i}", html.replace("{i}", str(i)).replace("{label}", "Share this")) for i in range(3)]
    got = {r["page_id"]: r["text"].split("\n") for r in html_text.extract(spark.createDataFrame(pages, "page_id long, url string, html string")).collect()}
    assert got[1][-1] == "The same last words." and len(got[1]) == 3
    assert got[0][-1] == got[2][-1] == "Share this"


MARKUP = [
    ("<article><p>a<p class='share'>x<p>Article</article>", "a\nArticle"),
    ("<ul><li class='promo'>ad<li>keep</ul><p>Body", "keep\nBody"),
    ("<article>price <span class='share-price'>12</span> now <span class='ad'>BUY</span> here</article>", "price 12 now here"),
    ("<div class='related-work'>kept</div><div class='related-posts'>gone</div><div class='SocialShare'>gone</div>", "kept"),
    ("<div><div class='ad'>x</div>y</div>z", "y\nz"),
    ("<div><div class='ad'>x<b>w</div>y</div>z", "y\nz"),
    ("<table><tr><td class='ad'>x<td>y<tr><td>z</table>", "y\nz"),
    ("<dl><dt class='comment'>x<dd>y<dt>z</dl>", "y\nz"),
    ("<section><p class='notice-box'>x</section>after", "after"),
    ("<p><b>bold<br><p>next</b> still", "bold\nnext still"),
    ("<b><p class='ad'>x</b>y</p>z", "z"),
    ("<select><option>a<option>b</select>t", "t"),
    ("a<script>if (x<y) '</p>'</script>b<style>p>a{}</style>c<!-- <p>d -->e", "abce"),
    ("<p>cut <b", "cut <b"),
    ("&amp;&nbsp;&eacute; &#x41;\t\n b", "& \u00e9 A b"),
]


@pytest.mark.parametrize("html,want", MARKUP)
def test_markup(html, want):
    assert "\n".join(t for t, k in html_text.page_lines(html) if k != html_text.BOILERPLATE) == want


def test_pipeline_on_awkward_tables(spark, tmp_path):
    import corpus_pipeline as p
    from crowdrank.llm.common import cut

    items = spark.createDataFrame([(1, text(13, 5))], "item_id long, text string")
    items.write.parquet(f"{tmp_path}/benchmark.parquet")
    rows = [(None, LONG + " more"), (1, LONG + " less"), (1, text(90, 4)), (2, text(90, 4)), (3, None), (4, text(13, 5) + " " + text(9, 6)), *((10 + i, t) for i, t in corpus())]
    for table in (frame(spark, rows, extra=True).withColumn("n_lines", F.lit("own")).withColumn("first", F.lit(2)), frame(spark, [])):
        docs = cut(table)
        for name, stage in p.STAGES:
            out = cut(stage(spark, docs, str(tmp_path)))
            if name != "packing":
                assert out.columns == docs.columns and out.dtypes == docs.dtypes
                assert "n_lines" not in out.columns or {r[0] for r in out.select("n_lines").distinct().collect()} == {"own"}
                docs = out
        assert {r[0] for r in out.select("doc_id").collect()} == {r[0] for r in docs.select("doc_id").collect()}
        if table.count():
            kept = {r["doc_id"]: r["text"] for r in docs.collect()}
            assert 4 not in kept and 3 not in kept and hashlib.sha256(kept[1].encode()).hexdigest()
