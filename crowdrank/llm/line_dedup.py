"""Line dedup by winnowing over line hashes [native: DataFrame functions only].

A document is a row of line hashes. Of every ``guarantee`` consecutive lines the smallest hash (the
leftmost, on ties) is selected, so any repeated run of that many lines shares a fingerprint, however
its surroundings differ. Only selected positions leave their document, each with the hashes of the
``guarantee - 1`` lines on either side. Equal fingerprints are joined; those seen once cannot stand in
a repeat and go. A match of two positions is extended to the left and to the right as far as the
windows that selected them reach; the first position in (id, line) order with the same extension is
the original, and the lines of all later ones are deleted. As every window of a longer run selects a
fingerprint of its own, the extensions cover the run, and overlapping ones merge.

With ``single_words`` a line of at least that many words is a window of its own too: all its
occurrences but the first in (id, line) order go, whatever stands around them.

Defined results: null text stays null with no lines; the empty text is one empty line; windows of
blank lines only are left alone; a null id is an id like others and comes first; rows that share an
id are one document, so a line that goes from one goes from all; documents shorter than ``guarantee``
lines lose only lines that count alone; an empty table gives no rows. Extra columns stay, but columns
named ``n_lines`` or ``n_removed`` are replaced.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from crowdrank.llm.common import cut, table

#: Lines of at least so many words count alone in production; shorter ones (headings, answers) in runs only.
SINGLE_WORDS = 4


def lines_of(text: Column) -> Column:
    return F.split(text, "\n")


def has_words(line: Column, least: int) -> Column:
    return line.rlike(rf"\A[\x20\x09-\x0D]*+(?:[^\x20\x09-\x0D]++[\x20\x09-\x0D]++){{{least - 1}}}[^\x20\x09-\x0D]")


def fingerprints(docs: DataFrame, guarantee: int, single_words: int | None, id_col: str, text_col: str) -> DataFrame:
    """Selected positions: ``doc, pos`` (lines from 1), ``picks``, and hashes ``h*``, ``c*`` of the lines around.

    Bit ``l`` of ``picks``: the window that begins ``l`` lines before selects this line; bit
    ``guarantee``: the line counts alone. ``h{guarantee - 1}`` is the line itself.
    """
    reach = guarantee - 1
    rows = docs.filter(F.col(text_col).isNotNull()).select(F.col(id_col).alias("doc"), lines_of(F.col(text_col)).alias("lines"))
    hashed = rows.select("doc", "lines", F.transform("lines", lambda x: F.xxhash64(x)).alias("hs"), F.transform("lines", lambda x: F.hash(x)).alias("cs"), F.transform("lines", lambda x: F.trim(x) != "").alias("solid"))
    one = hashed.withColumn("pos", F.explode(F.sequence(F.lit(1), F.size("lines"))))
    at = lambda name, k: F.get(name, F.col("pos") - 1 + k)
    picks = F.lit(0)
    for back in range(guarantee):
        inside = (F.col("pos") > back) & (F.col("pos") - back + reach <= F.size("lines"))
        least, some = F.lit(True), F.lit(False)
        for k in range(-back, guarantee - back):
            if k:
                least = least & (at("hs", 0) < at("hs", k) if k < 0 else at("hs", 0) <= at("hs", k))
            some = some | at("solid", k)
        picks = picks + F.when(inside & least & some, 1 << back).otherwise(0)
    if single_words is not None:
        picks = picks + F.when(has_words(at("lines", 0), single_words), 1 << guarantee).otherwise(0)
    around = range(-reach, guarantee)
    hashes = [at("hs", k).alias(f"h{k + reach}") for k in around] + [at("cs", k).alias(f"c{k + reach}") for k in around]
    return one.select("doc", F.col("pos").cast("int").alias("pos"), picks.alias("picks"), *hashes).filter("picks <> 0")


def extended(marks: DataFrame, guarantee: int) -> DataFrame:
    """Fingerprints extended both ways: ``doc, start, width, key, check``, a row a window that selects one."""
    reach, found = guarantee - 1, []
    for back in range(guarantee):
        own = range(reach - back, reach - back + guarantee)
        window = F.struct((F.col("pos") - back).alias("start"), F.lit(guarantee).alias("width"), F.xxhash64(*[f"h{k}" for k in own]).alias("key"), F.hash(*[f"c{k}" for k in own]).alias("check"))
        found.append(F.when(F.col("picks").bitwiseAND(1 << back) != 0, window))
    alone = F.struct(F.col("pos").alias("start"), F.lit(1).alias("width"), F.xxhash64(f"h{reach}").alias("key"), F.hash(f"c{reach}").alias("check"))
    found.append(F.when(F.col("picks").bitwiseAND(1 << guarantee) != 0, alone))
    return marks.select("doc", F.explode(F.array(*found)).alias("w")).filter("w IS NOT NULL").select("doc", "w.*")


def repeats(docs: DataFrame, guarantee: int = 2, single_words: int | None = None, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Later windows with the place they repeat: ``doc, start, width, first_doc, first_start`` (lines from 1)."""
    line = [f"h{guarantee - 1}", f"c{guarantee - 1}"]
    marks = cut(fingerprints(docs, guarantee, single_words, id_col, text_col))
    twice = cut(marks.groupBy(*line).count().filter("count > 1").select(*line))
    live = cut(extended(marks.join(twice, line, "left_semi"), guarantee))
    same = ["width", "key", "check"]
    first = live.groupBy(*same).agg(F.min(F.struct("doc", "start")).alias("f"), F.count("*").alias("n")).filter("n > 1")
    first = cut(first.select(*same, F.col("f.doc").alias("first_doc"), F.col("f.start").alias("first_start")))
    later = ~(F.col("doc").eqNullSafe(F.col("first_doc")) & (F.col("start") == F.col("first_start")))
    return live.join(first, same).filter(later).select("doc", "start", "width", "first_doc", "first_start")


def dedup_lines(docs: DataFrame, guarantee: int = 2, id_col: str = "doc_id", text_col: str = "text", single_words: int | None = None) -> DataFrame:
    """``docs`` with later repeated runs deleted from ``text_col``, plus ``n_lines`` and ``n_removed``."""
    hits = repeats(docs, guarantee, single_words, id_col, text_col)
    runs = hits.groupBy("doc").agg(F.collect_set(F.struct("start", "width")).alias("__runs"))
    # a line goes if one of the windows that hold it goes
    hit = F.array_distinct(F.flatten(F.transform("__runs", lambda s: F.sequence(s["start"], s["start"] + s["width"] - 1))))
    gone = runs.select(F.col("doc").alias("__doc"), hit.alias("__gone"))
    both = docs.join(gone, F.col(id_col).eqNullSafe(F.col("__doc")), "left").withColumn("__gone", F.coalesce("__gone", F.array().cast("array<int>")))
    lines = lines_of(F.col(text_col))
    size = F.size(lines)
    # rows that share an id may have fewer lines than the place says
    kept = F.array_except(F.sequence(F.lit(1), size), F.col("__gone"))
    text = F.when(F.size("__gone") == 0, F.col(text_col)).otherwise(F.array_join(F.transform(kept, lambda i: F.element_at(lines, i)), "\n"))
    real = F.col(text_col).isNotNull()
    new = {
        "n_lines": F.when(real, size.cast("long")).otherwise(F.lit(0).cast("long")),
        "n_removed": F.when(real, (size - F.size(kept)).cast("long")).otherwise(F.lit(0).cast("long")),
        text_col: F.when(real, text),
    }
    old = [new[text_col].alias(c) if c == text_col else F.col(f"`{c}`") for c in docs.columns if c not in ("n_lines", "n_removed")]
    return both.select(*old, *(new[c].alias(c) for c in ("n_lines", "n_removed")))


def op2_line_dedup(spark, sf_dir: str) -> DataFrame:
    """Runs of two lines or more, and single lines of four words or more."""
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    return dedup_lines(docs, single_words=SINGLE_WORDS).select("doc_id", "n_lines", "n_removed", "text")


SQL = r"""
WITH d AS (SELECT doc_id, text, string_split(text, chr(10)) AS l FROM documents),
p AS (SELECT doc_id, p, l[p] AS a, l[p + 1] AS b, p < len(l) AS two FROM (SELECT doc_id, l, unnest(range(1, len(l) + 1)) AS p FROM d WHERE text IS NOT NULL)),
pairs AS (SELECT doc_id, p, row_number() OVER (PARTITION BY a, b ORDER BY doc_id, p) AS k FROM p WHERE two AND NOT (trim(a, ' ') = '' AND trim(b, ' ') = '')),
singles AS (SELECT doc_id, p, row_number() OVER (PARTITION BY a ORDER BY doc_id, p) AS k FROM p
  WHERE regexp_matches(a, '^[\x20\x09-\x0D]*([^\x20\x09-\x0D]+[\x20\x09-\x0D]+){3}[^\x20\x09-\x0D]')),
gone AS (SELECT doc_id, unnest([p, p + 1]) AS p FROM pairs WHERE k > 1 UNION SELECT doc_id, p FROM singles WHERE k > 1),
kept AS (SELECT doc_id, string_agg(a, chr(10) ORDER BY p) AS t FROM p WHERE NOT EXISTS (SELECT 1 FROM gone g WHERE g.doc_id = p.doc_id AND g.p = p.p) GROUP BY doc_id),
n AS (SELECT doc_id, count(*) AS n FROM gone GROUP BY doc_id)
SELECT doc_id, coalesce(len(l), 0)::BIGINT AS n_lines, coalesce(n, 0)::BIGINT AS n_removed,
  CASE WHEN text IS NULL THEN NULL ELSE coalesce(t, '') END AS text
FROM d LEFT JOIN kept USING (doc_id) LEFT JOIN n USING (doc_id)
"""
