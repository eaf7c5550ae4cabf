"""Language ID by word-first backoff.

Known words score by their log frequency in each language; a word that is not known falls back to
the longest length of character n-grams of which any is known. A word is known once the sample holds
it ``min_word`` times, an n-gram once ``min_gram`` distinct known words hold it, whatever the size of
the sample. The only bound is ``sample_docs``, the number of labelled rows that a model is fitted on
(about; picked by a hash of their key); prediction covers every whole text.

Defined results: a word is a run of letters; null text, or text without a letter, gives ``und`` with
score 0; with nothing to learn from, every text gives ``und``; of languages with equal scores the
first in order wins; labelled rows without a key are not learned from; repeated rows are predicted
one by one; an empty table gives no rows. Other columns of the input are not read by ``predict``
apart from ``id_col`` and ``text_col``.
"""

from __future__ import annotations

from collections import defaultdict
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
import regex
import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from crowdrank.llm.common import lean, table

UNKNOWN = "und"
_WORD = regex.compile(r"\p{L}+")

#: The model whose word scores this process keeps; an earlier one gives its memory back.
_ACTIVE: list = []


def _key(text: str) -> int:
    return xxhash.xxh3_64_intdigest(text)


@dataclass
class Scores:
    """Rows of scores by the hash of a word or n-gram, sorted by hash."""

    keys: np.ndarray
    rows: np.ndarray

    @classmethod
    def of(cls, rows: dict[str, np.ndarray], langs: int) -> Scores:
        keys = np.array([_key(x) for x in rows], np.uint64)
        order = np.argsort(keys)
        values = np.array(list(rows.values()), np.float32).reshape(len(rows), langs)
        return cls(keys[order], values[order])

    def find(self, texts: list[str]) -> tuple[np.ndarray, np.ndarray]:
        """Places in ``rows`` of all texts, and which of them are known."""
        if not len(self.keys):
            return np.zeros(len(texts), np.int64), np.zeros(len(texts), bool)
        keys = np.fromiter(map(_key, texts), np.uint64, len(texts))
        at = np.searchsorted(self.keys, keys)
        at[at == len(self.keys)] = 0
        return at, self.keys[at] == keys


@dataclass
class WordFirstModel:
    """Log frequencies by language of words and of character n-grams (by length)."""

    langs: list[str]
    words: Scores
    grams: Scores
    max_gram: int = 5
    _rows: dict[str, int] = field(default_factory=dict)
    _matrix: np.ndarray | None = None

    def word_scores(self, words: list[str]) -> np.ndarray:
        """A row of scores a word: its own, or the mean of its longest known n-grams, or zeros."""
        out = np.zeros((len(words), len(self.langs)), np.float32)
        at, known = self.words.find(words)
        out[known] = self.words.rows[at[known]]
        left = np.flatnonzero(~known)
        for n in range(self.max_gram, 0, -1):
            marked = [f"^{words[i]}$" for i in left.tolist()]
            grams = [m[j : j + n] for m in marked for j in range(len(m) - n + 1)]
            of = np.repeat(left, [max(0, len(m) - n + 1) for m in marked])
            at, known = self.grams.find(grams)
            of, at = of[known], at[known]
            times = np.bincount(of, minlength=len(words))
            np.add.at(out, of, self.grams.rows[at])
            hit = times > 0
            out[hit] /= times[hit, None]
            left = left[~hit[left]]
            if not len(left):
                break
        return out

    def _learn(self, words: list[str]) -> None:
        i, n = len(self._rows), len(words)
        if self._matrix is None or i + n > len(self._matrix):
            grown = np.zeros((max(4096, 2 * (i + n)), len(self.langs)), np.float32)
            grown[:i] = self._matrix[:i] if self._matrix is not None else 0
            self._matrix = grown
        self._matrix[i : i + n] = self.word_scores(words)
        self._rows.update(zip(words, range(i, i + n), strict=True))

    def predict(self, texts: list[str | None], cache: int = 100_000, group: int = 64) -> list[tuple[str, float]]:
        """Language and score of each text; about ``cache`` scored words are kept."""
        if not _ACTIVE or _ACTIVE[0] is not self:
            forget()
            _ACTIVE[:] = [self]
        out = []
        for lo in range(0, len(texts), group):
            found = [_WORD.findall(t.lower()) if t and self.langs else [] for t in texts[lo : lo + group]]
            if len(self._rows) > cache:
                self._rows, self._matrix = {}, None
            rows = self._rows
            self._learn(list(dict.fromkeys(w for words in found for w in words if w not in rows)))
            for words in found:
                if not words:
                    out.append((UNKNOWN, 0.0))
                    continue
                total = self._matrix[[rows[w] for w in words]].sum(axis=0, dtype=np.float64)
                best = int(total.argmax())
                out.append((self.langs[best], float(1.0 / np.exp(total - total[best]).sum())))
        return out


def forget() -> None:
    """Drop the word scores that this process keeps."""
    for m in _ACTIVE:
        m._rows, m._matrix = {}, None
    _ACTIVE.clear()


def fit(docs: DataFrame, text_col: str = "text", lang_col: str = "lang", key_col: str = "doc_id", sample_docs: int = 20_000, min_word: int = 2, min_gram: int = 2, max_gram: int = 5) -> WordFirstModel:
    """Fit on about ``sample_docs`` labelled rows, chosen by a hash of their key."""
    labelled = docs.select(F.col(key_col).alias("k"), F.col(text_col).alias("t"), F.col(lang_col).alias("l")).filter("l IS NOT NULL AND k IS NOT NULL")
    share = min(1.0, sample_docs / max(1, labelled.select("l").count()))
    below = min(int(share * 2**63), 2**63 - 1)
    sample = labelled.filter(F.shiftrightunsigned(F.xxhash64("k"), 1) <= F.lit(below)).filter("t IS NOT NULL")
    words = sample.select("l", F.explode(F.regexp_extract_all(F.lower("t"), F.lit(r"(\p{L}+)"))).alias("w"))
    counts = words.groupBy("l", "w").count()
    totals = {r["l"]: r["n"] for r in counts.groupBy("l").agg(F.sum("count").alias("n")).collect()}
    langs = sorted(totals)
    at = {x: i for i, x in enumerate(langs)}
    # a word as one row; the bounded sample bounds what comes to the driver
    by_lang = F.map_from_entries(F.collect_list(F.struct("l", "count"))).alias("c")
    kept = counts.groupBy("w").agg(F.sum("count").alias("n"), by_lang).filter(F.col("n") >= min_word).select("w", "c")
    by_word: dict[str, np.ndarray] = {}
    by_gram: dict[str, np.ndarray] = defaultdict(lambda: np.zeros(len(langs)))
    holders: dict[str, int] = defaultdict(int)
    for r in kept.toLocalIterator():
        own = np.zeros(len(langs))
        for lang, n in r["c"].items():
            own[at[lang]] = n
        by_word[r["w"]] = own
        marked, weight = f"^{r['w']}$", own**0.5
        for g in {marked[i : i + n] for n in range(1, max_gram + 1) for i in range(len(marked) - n + 1)}:
            by_gram[g] += weight
            holders[g] += 1
    by_gram = {g: c for g, c in by_gram.items() if len(g) == 1 or holders[g] >= min_gram}
    sums = np.zeros((max_gram + 1, len(langs)))
    for g, c in by_gram.items():
        sums[len(g)] += c
    size = np.array([totals[x] for x in langs], float)
    grams = {g: np.log((c + 0.1) / (sums[len(g)] + 1)) for g, c in by_gram.items()}
    logs = {w: np.log((c + 0.05) / (size + 1)) for w, c in by_word.items()}
    return WordFirstModel(langs, Scores.of(logs, len(langs)), Scores.of(grams, len(langs)), max_gram)


def predict(docs: DataFrame, model: WordFirstModel, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row a document: ``doc_id, lang_pred, score``. The model is bounded, so it is broadcast."""
    shared = docs.sparkSession.sparkContext.broadcast(model)

    def run(batches):
        m = shared.value
        try:
            for b in batches:
                out = m.predict(b.column(1).to_pylist())
                yield pa.RecordBatch.from_arrays([b.column(0), pa.array([x[0] for x in out], pa.string()), pa.array([x[1] for x in out], pa.float64())], ["doc_id", "lang_pred", "score"])
        finally:
            forget()

    kind = docs.schema[id_col].dataType.simpleString()
    return docs.select(F.col(id_col), F.col(text_col)).mapInArrow(lean(run), f"doc_id {kind}, lang_pred string, score double")


def keep_known(docs: DataFrame, model: WordFirstModel, min_score: float = 0.5, text_col: str = "text") -> DataFrame:
    """The rows, all columns whole, whose text has a language with at least ``min_score``."""
    shared = docs.sparkSession.sparkContext.broadcast(model)

    def run(batches):
        m = shared.value
        try:
            for b in batches:
                found = m.predict(b.column(b.schema.get_field_index(text_col)).to_pylist())
                yield b.filter(pa.array([lang != UNKNOWN and score >= min_score for lang, score in found], pa.bool_()))
        finally:
            forget()

    return docs.mapInArrow(lean(run), docs.schema)


def held_out(id_col: str = "doc_id") -> Column:
    """A fifth of the ids, by their checksum."""
    return F.crc32(F.col(id_col).cast("string")) % 5 == 0


def op5_language_id(spark, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text", "lang")
    model = fit(docs.filter(~held_out()))
    return predict(docs, model).select("doc_id", held_out().alias("held_out"), "lang_pred", "score")
