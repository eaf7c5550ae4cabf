"""Main text of web pages by nearest-URL page differencing.

A page is read into text lines (one a block) with what its markup says of each: inside the article,
inside a menu, advert, notice, form or the like, or neither. Within a host, pages are ordered by URL
path; each is aligned with its two nearest ones by the longest common subsequence of line hashes.
Lines in marked boilerplate always go. Of all others differencing decides:

* a line outside any article goes if a nearest page shares it; one of ``LONG`` words or more must be
  shared with both nearest pages, where there are two;
* inside an article boilerplate stands at the edges: lines of up to ``SHORT`` words that do not end like
  a sentence go from its beginning and its end as long as both nearest pages share them; sentences and
  paragraphs within stay, as two articles may really say the same;
* a page that shares more than half of the words in question is a copy and decides nothing.

Pages are parsed once for their line hashes and once, when the decisions are known, for their text.

Defined results: null or empty html gives the empty text; a page without neighbours in its host
keeps all undecided lines; null URLs form a host of their own; equal URLs are ordered by page id,
then by a hash of their html; repeated rows are extracted alike, and rows of one page id and URL with
different html each by their own; an empty table gives no rows; extra columns are ignored.
"""

from __future__ import annotations

import html as entities
import re
from math import isqrt

import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from crowdrank.llm.common import cut, lean, table

#: Elements that end a text line, and elements whose content is never main text.
BLOCKS = frozenset("address article aside blockquote body br caption center dd details dialog div dl dt fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 head header hr html legend li main menu nav ol optgroup option p pre section select summary table tbody td tfoot th thead title tr ul".split())
HIDDEN = frozenset("head nav footer aside form menu dialog button select textarea iframe svg canvas object noscript template".split())
RAW = "script|style|noscript|template|textarea|iframe|svg"
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
#: Elements whose begin ends an open paragraph, and what other begins end, up to which element.
ENDS_PARAGRAPH = frozenset("address article aside blockquote center details dialog div dl fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 header hr main menu nav ol p pre section table ul".split())
ENDS = {
    "li": ({"li"}, {"ul", "ol", "menu"}),
    "dt": ({"dt", "dd"}, {"dl"}),
    "dd": ({"dt", "dd"}, {"dl"}),
    "option": ({"option"}, {"select"}),
    "optgroup": ({"option", "optgroup"}, {"select"}),
    "tr": ({"tr"}, {"table"}),
    "td": ({"td", "th"}, {"tr", "table"}),
    "th": ({"td", "th"}, {"tr", "table"}),
    "tbody": ({"tbody", "thead", "tfoot"}, {"table"}),
    "thead": ({"tbody", "thead", "tfoot"}, {"table"}),
    "tfoot": ({"tbody", "thead", "tfoot"}, {"table"}),
}
SCOPES = frozenset("table td th caption button object template".split())
TABLE_PARTS = frozenset("table tbody thead tfoot tr td th caption body html".split())
#: Words in a class or id that mark boilerplate, alone or beside others; those that do
#: so only beside words of layout; and such words.
STRONG = frozenset("ad ads advert adverts advertisement advertisements banner breadcrumb breadcrumbs comment comments consent cookie cookies disclaimer footer gdpr masthead menu modal nav navbar navigation newsletter popup promo promoted sidebar sponsor sponsored subscribe subscription toolbar widget".split())
WEAK = frozenset("notice notices related replies respond share sharing social".split())
LAYOUT = frozenset("area article articles bar block body bottom box button buttons container content div footer header icon icons inner item items left link links list main outer page panel post posts right row section site stories story this top with wrap wrapper".split())
ROLES = frozenset("navigation banner contentinfo complementary search form alert dialog menu menubar".split())
_TOKEN = re.compile(rf"<!--.*?(?:-->|\Z)|<({RAW})\b[^>]*>.*?(?:</\1\s*>|\Z)|<(/?)([a-zA-Z][^\s/>]*)((?:[^>\"']|\"[^\"]*\"|'[^']*')*)>|<[!?][^>]*>", re.S | re.I)
_ATTRIBUTE = re.compile(r"""\b(class|id|role)\s*=\s*(?:"([^"]*)"|'([^']*)'|([^\s>]+))""", re.I)
_PART = re.compile(r"[A-Z]?[a-z]+|[A-Z]+(?![a-z])")
ARTICLE, OPEN, BOILERPLATE = 0, 1, 2
LONG, SHORT = 20, 12
#: How a sentence ends. Such a line has ``SENTENCE`` added to its kind.
SENTENCE, ENDINGS = 4, ".,:;!?\u2026\u3002\uff01\uff1f\"'\u00bb\u201d\u2019)"


def marked(value: str) -> bool:
    """Whether a class or id names boilerplate."""
    for name in value.split():
        parts = [x.lower() for x in _PART.findall(name)]
        if any(x in STRONG for x in parts) or any(x in WEAK for x in parts) and all(x in WEAK or x in LAYOUT for x in parts):
            return True
    return False


def boilerplate(name: str, attributes: str, in_article: bool) -> bool:
    if name in HIDDEN or name == "header" and not in_article:
        return True
    if attributes:
        for key, a, b, c in _ATTRIBUTE.findall(attributes):
            value = a or b or c
            if key.lower() == "role" and value.lower() in ROLES or key.lower() != "role" and name not in ("html", "body") and marked(value):
                return True
    return False


class Lines:
    """Reads a page into lines; keeps the open elements, and what of them skips or is an article."""

    def __init__(self) -> None:
        self.out: list[tuple[str, int]] = []
        self.now: list[str] = []
        #: open elements: name, 1 where it skips its content, 1 where it is an article
        self.open: list[tuple[str, int, int]] = []
        self.skips = self.articles = 0

    def close_line(self) -> None:
        if self.now:
            text = " ".join(entities.unescape("".join(self.now)).split())
            if text:
                self.out.append((text, BOILERPLATE if self.skips else ARTICLE if self.articles else OPEN))
            self.now.clear()

    def text(self, part: str) -> None:
        # what an inline element skips leaves the line around it whole
        if not self.skips or any(skip and name in BLOCKS for name, skip, _ in self.open):
            self.now.append(part)

    def drop(self, place: int, only: bool = False) -> None:
        """Close the element at ``place`` and, unless ``only``, all inside it."""
        for _, skip, article in self.open[place : place + 1 if only else None]:
            if skip or article:
                if any(name in BLOCKS for name, *_ in self.open[place:]):
                    self.close_line()
                self.skips -= skip
                self.articles -= article
        del self.open[place : place + 1 if only else None]

    def innermost(self, names: set[str] | frozenset[str], limits) -> int:
        """Place of the innermost open element of ``names`` inside any of ``limits``, or -1."""
        for i in range(len(self.open) - 1, -1, -1):
            if self.open[i][0] in names:
                return i
            if self.open[i][0] in limits:
                break
        return -1

    def begin(self, name: str, attributes: str) -> None:
        if name in ENDS_PARAGRAPH and (i := self.innermost({"p"}, SCOPES)) >= 0:
            self.drop(i)
        if name in ENDS and (i := self.innermost(*ENDS[name])) >= 0:
            self.drop(i)
        if name in VOID or attributes.endswith("/"):
            return
        skip = int(not self.skips and boilerplate(name, attributes, self.articles > 0))
        article = int(not self.skips and not skip and name in ("article", "main"))
        if (skip or article) and name in BLOCKS:
            self.close_line()
        self.open.append((name, skip, article))
        self.skips += skip
        self.articles += article

    def end(self, name: str) -> None:
        if name in BLOCKS:
            i = self.innermost({name}, () if name in TABLE_PARTS else SCOPES)
            if i >= 0:
                self.drop(i)
            return
        # an inline end does not close the blocks around it
        for i in range(len(self.open) - 1, -1, -1):
            if self.open[i][0] == name:
                self.drop(i, only=any(x in BLOCKS for x, *_ in self.open[i:]))
                return


def page_lines(html: str | None) -> list[tuple[str, int]]:
    """Text lines of a page, white space folded, with ``ARTICLE``, ``OPEN`` or ``BOILERPLATE``."""
    page, at = Lines(), 0
    if not html:
        return page.out
    for m in _TOKEN.finditer(html):
        if m.start() > at:
            page.text(html[at : m.start()])
        at = m.end()
        if not (name := m[3]):
            continue
        name = name.lower()
        if name in BLOCKS:
            page.close_line()
        if m[2]:
            page.end(name)
        else:
            page.begin(name, m[4])
    page.text(html[at:])
    page.close_line()
    return page.out


def common_lines(a: list[int], b: list[int]) -> set[int]:
    """Places of ``a`` in a longest common subsequence with ``b``.

    Rows of the length table are kept as bits, one where a row's length does not grow; every so many
    rows are kept and those between are computed again, so memory stays near the square root.
    """
    lo, end = 0, 0
    while lo < min(len(a), len(b)) and a[lo] == b[lo]:
        lo += 1
    while end < min(len(a), len(b)) - lo and a[-1 - end] == b[-1 - end]:
        end += 1
    out = {*range(lo), *range(len(a) - end, len(a))}
    both = set(a[lo : len(a) - end]) & set(b[lo : len(b) - end])
    rows = [i for i in range(lo, len(a) - end) if a[i] in both]
    other = [x for x in b[lo : len(b) - end] if x in both]
    if not rows:
        return out
    masks: dict[int, int] = {}
    for j, x in enumerate(other):
        masks[x] = masks.get(x, 0) | 1 << j
    full = (1 << len(other)) - 1

    def after(v: int, i: int) -> int:
        m = v & masks[a[rows[i]]]
        return ((v + m) | (v - m)) & full

    step = isqrt(len(rows)) + 1
    kept, v = [full], full
    for i in range(len(rows)):
        v = after(v, i)
        if (i + 1) % step == 0:
            kept.append(v)
    i, j, block, table_rows = len(rows), len(other), -1, []
    while i and j:
        if (i - 1) // step != block:
            block = (i - 1) // step
            table_rows = [kept[block]]
            for r in range(block * step, min(len(rows), (block + 1) * step)):
                table_rows.append(after(table_rows[-1], r))
        here, above = table_rows[i - block * step], table_rows[i - 1 - block * step]
        if here >> (j - 1) & 1:
            j -= 1
        elif not above >> (j - 1) & 1:
            i -= 1
        else:
            out.add(rows[i - 1])
            i, j = i - 1, j - 1
    return out


def deleted(kinds: bytes, words: list[int], sides: list[set[int]]) -> list[int]:
    """Places of unmarked lines that differencing deletes; ``sides``: what each nearest page shares."""
    gone = []
    for kind in (OPEN, ARTICLE):
        own = [i for i, k in enumerate(kinds) if k & 3 == kind]
        total = sum(words[i] for i in own)
        judges = [s for s in sides if 2 * sum(words[i] for i in own if i in s) <= total]
        if not own or not judges:
            continue
        if kind == OPEN:
            gone += [i for i in own if (all if words[i] >= LONG else any)(i in s for s in judges)]
        elif len(judges) == 2:
            for edge in (own, own[::-1]):
                for i in edge:
                    if words[i] > SHORT or kinds[i] & SENTENCE or not all(i in s for s in judges):
                        break
                    gone.append(i)
    return sorted(set(gone))


def _hash(line: str) -> int:
    return xxhash.xxh3_64_intdigest(line) - (1 << 63)


_KINDS = {"page_id": pa.int64(), "url": pa.string(), "hh": pa.int64(), "part": pa.int32(), "edge": pa.int32(), "host": pa.string(), "lines": pa.list_(pa.int64()), "kinds": pa.binary(), "words": pa.list_(pa.int32()), "before": pa.list_(pa.int32()), "after": pa.list_(pa.int32()), "gone": pa.list_(pa.int32()), "text": pa.string(), "n_chars": pa.int64()}
_SQL = {"page_id": "long", "url": "string", "hh": "long", "part": "int", "edge": "int", "host": "string", "lines": "array<long>", "kinds": "binary", "words": "array<int>", "before": "array<int>", "after": "array<int>", "gone": "array<int>", "text": "string", "n_chars": "long"}


def _rows(rows: list[tuple], names: list[str]) -> pa.RecordBatch:
    cols = list(zip(*rows, strict=True)) or [[] for _ in names]
    return pa.RecordBatch.from_arrays([pa.array(c, _KINDS[n]) for c, n in zip(cols, names, strict=True)], names)


def _schema(names: list[str]) -> str:
    return ", ".join(f"{n} {_SQL[n]}" for n in names)


def hashed_lines(pages: DataFrame) -> DataFrame:
    """``page_id, url, hh, host, path`` and, line by line, ``lines`` (hashes), ``kinds`` and ``words``."""
    url = F.regexp_replace(F.coalesce("url", F.lit("")), r"^[a-zA-Z][a-zA-Z0-9+.-]*:/*", "")
    host = F.lower(F.substring_index(F.substring_index(F.substring_index(url, "/", 1), "?", 1), "#", 1))
    path = F.regexp_replace(F.regexp_replace(F.expr("substring(_u, length(_h) + 1)"), r"[?#].*$", ""), r"(\.html?|/)$", "")
    keyed = pages.withColumn("_u", url).withColumn("_h", host).select("page_id", "url", "hh", F.col("_h").alias("host"), path.alias("path"), "html")

    def run(batches):
        for b in batches:
            for lo in range(0, b.num_rows, 256):
                own = b.slice(lo, 256)
                found = [page_lines(h.as_py()) for h in own.column(5)]
                cols = [pa.array([[_hash(t) for t, _ in lines] for lines in found], pa.list_(pa.int64())), pa.array([bytes(k + SENTENCE * (t[-1] in ENDINGS) for t, k in lines) for lines in found], pa.binary()), pa.array([[t.count(" ") + 1 for t, _ in lines] for lines in found], pa.list_(pa.int32()))]
                yield pa.RecordBatch.from_arrays([*(own.column(i) for i in range(5)), *cols], ["page_id", "url", "hh", "host", "path", "lines", "kinds", "words"])

    return keyed.mapInArrow(lean(run), "page_id long, url string, hh long, host string, path string, lines array<long>, kinds binary, words array<int>")


#: Rows of a partition: its first and last page carry their lines on, to meet the pages beyond the border.
ALIGNED = ["page_id", "url", "hh", "part", "edge", "host", "lines", "kinds", "words", "before", "after", "gone"]
FIRST, LAST = 1, 2


def align(batches):
    """Neighbours in the order of a partition; ``edge`` is 0, ``FIRST``, ``LAST`` or both added."""
    names = ["page_id", "url", "hh", "part", "host", "lines", "kinds", "words"]
    older, held, rows = None, None, []

    def emit(row, before, after, edge):
        near = [sorted(common_lines(row[5], other[5])) if other is not None and other[4] == row[4] else None for other in (before, after)]
        if edge:
            return (*row[:4], edge, *row[4:], *near, None)
        return (*row[:4], 0, None, None, None, None, None, None, deleted(row[6], row[7], [set(s) for s in near if s is not None]))

    for b in batches:
        cols = [b.column(b.schema.get_field_index(c)).to_pylist() for c in names]
        for row in zip(*cols, strict=True):
            if held is not None:
                rows.append(emit(held, older, row, 0 if older is not None else FIRST))
            older, held = held, row
        if rows:
            yield _rows(rows, ALIGNED)
            rows = []
    if held is not None:
        yield _rows([emit(held, older, None, LAST if older is not None else FIRST + LAST)], ALIGNED)


def mend(batches):
    """Border pages against the pages beyond: ``page_id, url, hh, gone``."""
    for b in batches:
        out = []
        for r in b.to_pylist():
            sides = []
            for known, beyond, mask in (("before", "tail", FIRST), ("after", "head", LAST)):
                other = r[beyond] if r["edge"] & mask else None
                if r[known] is not None:
                    sides.append(set(r[known]))
                elif other is not None and other["host"] == r["host"]:
                    sides.append(common_lines(r["lines"], other["lines"]))
            out.append((r["page_id"], r["url"], r["hh"], deleted(r["kinds"], r["words"], sides)))
        yield _rows(out, ["page_id", "url", "hh", "gone"])


def differences(pages: DataFrame) -> DataFrame:
    """``page_id, url, hh, gone``: places of the lines that go, for pages that lose any."""
    thin = cut(hashed_lines(pages))
    order = ["host", "path", "page_id", "url", "hh"]
    # even ranges of (host, path), so a large host is spread; neighbours over a border come from its edge rows
    ranged = thin.repartitionByRange(*order).sortWithinPartitions(*order).withColumn("part", F.spark_partition_id())
    done = cut(ranged.mapInArrow(lean(align), _schema(ALIGNED)))
    borders = done.filter("edge > 0").drop("gone")
    # partition numbers alone: some may hold no page
    by_part = Window.orderBy("part")
    parts = borders.select("part").distinct().select("part", F.lag("part").over(by_part).alias("prior"), F.lead("part").over(by_part).alias("next"))
    tails = borders.filter(F.col("edge").bitwiseAND(LAST) != 0).select(F.col("part").alias("prior"), F.struct("host", "lines").alias("tail"))
    heads = borders.filter(F.col("edge").bitwiseAND(FIRST) != 0).select(F.col("part").alias("next"), F.struct("host", "lines").alias("head"))
    met = borders.join(parts, "part").join(tails, "prior", "left").join(heads, "next", "left")
    mended = met.select("page_id", "url", "hh", "edge", "host", "lines", "kinds", "words", "before", "after", "tail", "head").mapInArrow(mend, _schema(["page_id", "url", "hh", "gone"]))
    return done.filter("edge = 0").select("page_id", "url", "hh", "gone").union(mended).filter(F.size("gone") > 0)


def extract(pages: DataFrame, id_col: str = "page_id", url_col: str = "url", html_col: str = "html") -> DataFrame:
    """``page_id, url, text, n_chars`` for every page."""
    pages = pages.select(F.col(id_col).cast("long").alias("page_id"), F.col(url_col).cast("string").alias("url"), F.xxhash64(html_col).alias("hh"), F.col(html_col).alias("html"))
    gone = cut(differences(pages).select(F.col("page_id").alias("p"), F.col("url").alias("u"), F.col("hh").alias("h"), "gone").dropDuplicates(["p", "u", "h"]))

    def run(batches):
        for b in batches:
            out = []
            for page, url, h, lost in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), b.column(2), b.column(3).to_pylist(), strict=True):
                lost = set(lost or ())
                kept = "\n".join(t for i, (t, kind) in enumerate(page_lines(h.as_py())) if kind != BOILERPLATE and i not in lost)
                out.append((page, url, kept, len(kept)))
                if len(out) == 256:
                    yield _rows(out, ["page_id", "url", "text", "n_chars"])
                    out = []
            yield _rows(out, ["page_id", "url", "text", "n_chars"])

    same = (F.col("hh") == F.col("h")) & F.col("page_id").eqNullSafe(F.col("p")) & F.col("url").eqNullSafe(F.col("u"))
    return pages.join(gone, same, "left").select("page_id", "url", "html", "gone").mapInArrow(lean(run), _schema(["page_id", "url", "text", "n_chars"]))


def op9_html_extraction(spark, sf_dir: str) -> DataFrame:
    return extract(table(spark, sf_dir, "pages").select("page_id", "url", "html"))
