"""The pipeline against plain Python on a small table, stage by stage."""

import corpus_pipeline as p
from crowdrank.llm.common import cut
from tests.llm.test_operators import brute_jaccard, brute_lines, corpus, frame


def test_stages(spark, tmp_path):
    bench = "one of a kind passage that no other text holds at all in here today yes"
    rows = [*corpus(), (200, "kalo " + bench), (201, "kabe lode mifi nugo rehu saja")]
    spark.createDataFrame([(1, bench)], "item_id long, text string").write.parquet(f"{tmp_path}/benchmark.parquet")
    docs, kept = cut(frame(spark, rows)), dict(rows)
    columns = docs.columns
    for name, stage in p.STAGES:
        docs = cut(stage(spark, docs, str(tmp_path)))
        if name == "language_id":
            kept = {i: t for i, t in kept.items() if t and any(c.isalpha() for c in t)}
        elif name == "line_dedup":
            lines = brute_lines(sorted(kept.items()))
            kept = {i: t for i, t in lines.items() if t or kept[i] == t}
        elif name == "jaccard_join":
            roots = brute_jaccard(sorted(kept.items()))
            kept = {i: t for i, t in kept.items() if roots[i][0] == i}
        elif name == "decontamination":
            kept.pop(200)
        else:
            assert {r["doc_id"] for r in docs.collect()} == set(kept)
            break
        assert docs.columns == columns
        got = {r["doc_id"]: r["text"] for r in docs.collect()}
        assert got == kept, name
