"""Language identification, words first, then ever shorter character n-grams.

The model holds, for each language, log frequencies of frequent words and of character n-grams
(1 to 4, with word borders). A known word is scored by its frequencies in each language. An unknown
word falls back to its 4-grams that are known, if none is to its 3-grams, and so on. A document's
language is the one with the largest sum over its words; equal sums go to the first name.

The model is fitted on a sample of labelled rows of bounded expected size (``SAMPLE_DOCS``), taken
by a hash of the id, and is itself bounded (``TOP_WORDS``, ``TOP_GRAMS``), so it may be broadcast.

Defined results: a null text, an empty one and one without any letter give ``und`` with score 0;
with no labelled row at all every document is ``und``. Null ids are allowed; rows that repeat are
each returned; columns beyond the named ones are ignored. Texts are read whole.
"""

from __future__ import annotations

import math
import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from unischema.llm.common import arrow_ready, cut, held_out, read_table

#: Expected number of labelled documents that the fit reads; rows beyond are left out by a hash.
SAMPLE_DOCS = 20_000
TOP_WORDS = 60_000
TOP_GRAMS = 40_000
LONGEST_GRAM = 4
#: Known to the model only from so many occurrences in the sample.
LEAST_COUNT = 3
UNKNOWN = "und"
#: Words of which vectors are kept at once in a worker.
CACHE_WORDS = 100_000
#: Words that count towards the confidence; more would only push it to one.
CONFIDENT_WORDS = 12

_WORD = re.compile(r"[^\W\d_]+")


def tokens(text: str) -> list[str]:
    return _WORD.findall(text.lower())


def grams(word: str, size: int) -> list[str]:
    """The n-grams of a word, with a border mark at both ends for n over 1."""
    if size == 1:
        return list(word)
    framed = f"_{word}_"
    return [framed[i : i + size] for i in range(len(framed) - size + 1)]


class Model:
    """Log frequencies by language, and scoring of texts."""

    def __init__(self, langs: list[str], words: dict[str, list[int]], by_size: list[dict[str, list[int]]]):
        self.langs = langs
        self.words = {w: v for w, v in zip(words, self._logs(words), strict=True)}
        self.by_size = [dict(zip(g, self._logs(g), strict=True)) for g in by_size]
        self._reset()

    def _logs(self, table: dict[str, list[int]]) -> np.ndarray:
        counts = np.array(list(table.values()), np.float64).reshape(len(table), len(self.langs)) + 0.5
        return np.log(counts / counts.sum(0)) if len(table) else counts

    def _reset(self) -> None:
        self.place: dict[str, int] = {}
        self.rows = np.zeros((CACHE_WORDS, len(self.langs)))

    def __getstate__(self):
        return (self.langs, self.words, self.by_size)

    def __setstate__(self, state):
        self.langs, self.words, self.by_size = state
        self._reset()

    def word(self, word: str) -> np.ndarray:
        """A known word's logs, else the mean of those of its longest known n-grams, else zeros."""
        known = self.words.get(word)
        if known is not None:
            return known
        for size in range(LONGEST_GRAM, 0, -1):
            table = self.by_size[size - 1]
            found = [table[g] for g in grams(word, size) if g in table]
            if found:
                return np.mean(found, axis=0)
        return np.zeros(len(self.langs))

    def predict(self, text: str | None) -> tuple[str, float]:
        found = tokens(text or "")
        if not self.langs or not found or not any(c.isalpha() for w in found for c in w):
            return UNKNOWN, 0.0
        total = np.zeros(len(self.langs))
        for at in range(0, len(found), CACHE_WORDS // 2):
            total += self._sum(found[at : at + CACHE_WORDS // 2])
        best = int(np.argmax(total))
        odds = np.exp((total - total[best]) * min(1.0, CONFIDENT_WORDS / len(found)))
        return self.langs[best], float(1 / odds.sum())

    def _sum(self, part: list[str]) -> np.ndarray:
        places = list(map(self.place.get, part))
        if None in places:
            fresh = {w for w, p in zip(part, places, strict=True) if p is None}
            if len(self.place) + len(fresh) > CACHE_WORDS:
                self._reset()
                fresh = set(part)
            for w in fresh:
                self.rows[len(self.place)] = self.word(w)
                self.place[w] = len(self.place)
            places = list(map(self.place.get, part))
        return self.rows[places].sum(0)


def _cells(framed: Column, size: int) -> Column:
    places = F.sequence(F.lit(1), F.greatest(F.length(framed) - (size - 1), F.lit(1)))
    return F.transform(places, lambda i: F.substring(framed, i, F.lit(size)))


def _pivot(counts: DataFrame, key: str, langs: list[str], top: int, least: int) -> dict[str, list[int]]:
    """The ``top`` most frequent keys with a count for each language."""
    by_lang = [F.sum(F.when(F.col("lang") == lang, F.col("n")).otherwise(0)).alias(f"c{i}") for i, lang in enumerate(langs)]
    rows = counts.groupBy(key).agg(F.sum("n").alias("total"), *by_lang).where(F.col("total") >= least)
    rows = rows.orderBy(F.col("total").desc(), key).limit(top)
    return {r[key]: [r[f"c{i}"] for i in range(len(langs))] for r in rows.collect()}


def fit(docs: DataFrame, sample_docs: int = SAMPLE_DOCS, top_words: int = TOP_WORDS, top_grams: int = TOP_GRAMS, least_count: int = LEAST_COUNT) -> Model:
    """Learn from text and non-null ``lang`` of rows that are not held out.

    The model has at most ``top_words`` words and ``top_grams`` n-grams of each size, those with the most
    occurrences and at least ``least_count``; a word beyond them is scored by its n-grams, so no text goes unscored.
    """
    usable = F.col("lang").isNotNull() & F.col("text").isNotNull() & ~held_out(F.col("doc_id"))
    by_lang = docs.where(usable).groupBy("lang").count().collect()
    langs = sorted(r["lang"] for r in by_lang)
    share = min(1.0, sample_docs / max(1, sum(r["count"] for r in by_lang)))
    bar = math.ceil(share * (1 << 53))
    chosen = F.shiftrightunsigned(F.xxhash64("doc_id", F.lit("sample")), 11) < F.lit(bar)
    found = F.regexp_extract_all(F.lower("text"), F.lit(r"\p{L}+"), F.lit(0))
    words = cut(docs.where(usable & chosen).select("lang", F.explode(found).alias("word")).groupBy("lang", "word").agg(F.count(F.lit(1)).alias("n")))
    table = _pivot(words, "word", langs, top_words, least_count)
    by_size = []
    for size in range(1, LONGEST_GRAM + 1):
        framed = F.col("word") if size == 1 else F.concat(F.lit("_"), "word", F.lit("_"))
        cells = words.where(F.length(framed) >= size).select("lang", "n", F.explode(_cells(framed, size)).alias("gram"))
        by_size.append(_pivot(cells.groupBy("lang", "gram").agg(F.sum("n").alias("n")), "gram", langs, top_grams, least_count))
    return Model(langs, table, by_size)


def identify(docs: DataFrame, model: Model) -> DataFrame:
    """``doc_id, held_out, lang_pred, score`` for each row."""
    arrow_ready(docs.sparkSession)
    shared = docs.sparkSession.sparkContext.broadcast(model)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own = shared.value
        for batch in batches:
            found = [own.predict(t.as_py()) for t in batch.column(2)]
            yield pa.RecordBatch.from_arrays(
                [batch.column(0), batch.column(1), pa.array([f[0] for f in found], pa.string()), pa.array([f[1] for f in found], pa.float64())],
                ["doc_id", "held_out", "lang_pred", "score"],
            )

    return docs.select(F.col("doc_id").cast("long"), held_out(F.col("doc_id")).alias("held_out"), "text").mapInArrow(run, "doc_id long, held_out boolean, lang_pred string, score double")


def op7_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = read_table(spark, sf_dir, "documents")
    return identify(docs, fit(docs))


def stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pipeline stage: documents of which no language can be told go; a null ``lang`` becomes the
    prediction, so that later stages know the language of every document. Rows are judged one by one,
    also where ids repeat; an empty table stays empty.
    """
    arrow_ready(spark)
    shared = spark.sparkContext.broadcast(fit(docs))
    text, lang = docs.columns.index("text"), docs.columns.index("lang")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own = shared.value
        for batch in batches:
            found = pa.array([own.predict(t.as_py())[0] for t in batch.column(text)], pa.string())
            told = batch.set_column(lang, batch.schema.field(lang), pc.coalesce(batch.column(lang), found))
            yield told.filter(pc.not_equal(found, UNKNOWN))

    return docs.mapInArrow(run, docs.schema)
