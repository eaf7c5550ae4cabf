"""Cases that the operators once left out, against brute force."""

import math
from collections import Counter

import duckdb
import pytest

import corpus_pipeline
from crowdrank.llm import line_dedup, lm_scoring
from tests.llm.test_operators import by_id, corpus, frame

LONG = " ".join(f"w{i}" for i in range(60))
LINES = [(1, f"a\n{LONG}\nb"), (2, f"c\n{LONG}\nd\na"), (3, LONG), (4, "a b c d"), (5, "x\na b c d\ny\n\t\nz\n\t"), (6, None), (7, ""), (8, "b\n\nq\nb\n")]


def brute_singles(rows, least, g=2):
    lines = {i: t.split("\n") for i, t in rows if t is not None}
    first, gone = {}, set()
    for i in sorted(lines):
        for p in range(len(lines[i])):
            pair = tuple(lines[i][p : p + g])
            if len(pair) == g and any(x.strip(" ") for x in pair) and first.setdefault(pair, (i, p)) != (i, p):
                gone |= {(i, p + k) for k in range(g)}
            line = lines[i][p]
            if len(line.encode().split()) >= least and first.setdefault(line, (i, p)) != (i, p):
                gone.add((i, p))
    return {i: "\n".join(x for p, x in enumerate(ls) if (i, p) not in gone) for i, ls in lines.items()}


@pytest.mark.parametrize("least", [1, 4])
def test_single_lines(spark, least):
    rows = LINES + [(100 + i, t) for i, t in corpus()]
    got = by_id(line_dedup.dedup_lines(frame(spark, rows, extra=True), single_words=least), "text")
    assert {i: t for i, (t,) in got.items() if t is not None} == brute_singles(rows, least)
    assert got[6] == (None,) and LONG not in got[2][0] and got[3] == ("",)


def test_line_query_and_sql(spark, tmp_path):
    frame(spark, LINES + [(100 + i, t) for i, t in corpus()]).write.parquet(f"{tmp_path}/documents.parquet")
    got = sorted(map(tuple, line_dedup.op2_line_dedup(spark, str(tmp_path)).collect()))
    con = duckdb.connect()
    con.execute(f"CREATE VIEW documents AS SELECT * FROM '{tmp_path}/documents.parquet/*.parquet'")
    assert got == sorted(con.execute(line_dedup.SQL).fetchall())


def test_pipeline_single_lines(spark):
    got = by_id(corpus_pipeline.without_repeated_lines(spark, frame(spark, LINES), ""), "text")
    assert got[2] == ("c\nd\na",) and 3 not in got and got[5] == ("x\ny\n\t\nz\n\t",)


def test_score_query_and_sql(spark, tmp_path):
    frame(spark).write.parquet(f"{tmp_path}/documents.parquet")
    words = {i: (t or "").encode().split() for i, t in corpus()}
    count = Counter(tuple(w[s : s + k]) for w in words.values() for k in (1, 2, 3) for s in range(len(w) - k + 1))
    total = sum(map(len, words.values()))

    def log(gram):
        if len(gram) == 1:
            return math.log(count[gram] / total)
        return math.log(count[gram] / count[gram[:-1]]) if count[gram] >= 2 else math.log(0.4) + log(gram[1:])

    got = by_id(lm_scoring.op6_lm_scoring(spark, str(tmp_path)), "n_words", "log_score")
    con = duckdb.connect()
    con.execute(f"CREATE VIEW documents AS SELECT * FROM '{tmp_path}/documents.parquet/*.parquet'")
    sql = {i: r for i, *r in con.execute(lm_scoring.SQL).fetchall()}
    assert got.keys() == words.keys() == sql.keys()
    for i, w in words.items():
        want = sum(log(tuple(w[max(0, p - 2) : p + 1])) for p in range(len(w)))
        assert got[i][0] == sql[i][0] == len(w)
        assert abs(got[i][1] - want) < 1e-3 and abs(sql[i][1] - want) < 1e-3
