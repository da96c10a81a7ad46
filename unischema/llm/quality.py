"""Quality classification with a factorisation machine over hashed words, structure and metadata.

A document becomes a sparse vector: hashed words (damped counts, unit length) and standardised
structure features (case, punctuation, repetition, line and word lengths, size) and metadata (whether
there is a text, and the recorded number of characters against the real one). The machine adds to
a linear model all pairwise interactions through low-rank factors, in time linear in the number of
non-zeros: the interactions of a factor are half the square of the sum less the sum of squares.

The fit reads at most ``SAMPLE_DOCS`` labelled rows, those of the least hashes of their ids among rows that
are not held out, and runs on the driver; scoring is a map over all texts.

Defined results: null and empty texts are scored as texts without words; with no label of some class
every score is the share of ones (0.5 without labels). Rows that repeat are each returned; null ids
are allowed in scoring and never learnt from; of several labels of one id the largest counts; columns
beyond the named ones are ignored; without a column ``n_chars`` (or with nulls in it) that feature is 0;
empty tables give empty results; very long texts are scored whole. ``lang``,
``source``, ids and labels never enter a score.
"""

from __future__ import annotations

import math
import re
import zlib
from collections import Counter
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from unischema.llm.common import arrow_ready, held_out, read_table

SAMPLE_DOCS = 6_000
BUCKETS = 1 << 14
FACTORS = 8
EPOCHS = 12
RATE = 0.05
DECAY = 1e-5

_WORD = re.compile(r"\w+")
_MARKS = "!?.,;:|*#%$&@<>{}[]()=\"'/\\_-~^+"


def structure(text: str, words: list[str]) -> list[float]:
    """Shape of a text: shares of character kinds, repetition, lengths."""
    n, w = max(1, len(text)), max(1, len(words))
    counts = Counter(text)
    lines = text.split("\n")
    letters = sum(c for ch, c in counts.items() if ch.isalpha())
    upper = sum(c for ch, c in counts.items() if ch.isupper())
    digits = sum(c for ch, c in counts.items() if ch.isdigit())
    distinct = len(set(words))
    repeats = sum(a == b for a, b in zip(words, words[1:], strict=False))
    chars = sum(map(len, words))
    shares = [letters / n, upper / max(1, letters), digits / n, counts.get(" ", 0) / n, distinct / w, distinct / math.sqrt(w), repeats / w]
    shares += [chars / w / 10, math.log1p(len(text)) / 10, math.log1p(len(words)) / 10, len(lines) / w, len(set(lines)) / len(lines), float(not words)]
    return shares + [min(1.0, 10 * counts.get(mark, 0) / w) for mark in _MARKS]


def metadata(text: str | None, n_chars: int | None) -> list[float]:
    """Whether there is a text and a recorded length, and how far that is from the real one."""
    size = len(text or "")
    off = 0.0 if n_chars is None else max(-1.0, min(1.0, (n_chars - size) / max(1, size)))
    return [float(text is None), float(n_chars is None), off]


N_SHAPE = len(structure("", [])) + len(metadata("", 0))


class Featuriser:
    """Texts to ``(indices, values)``; hashed words first, then structure at ``BUCKETS + i``."""

    def __init__(self) -> None:
        self._known: dict[str, int] = {}

    def __call__(self, text: str | None, n_chars: int | None = None) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        known_of_it = metadata(text, n_chars)
        text = text or ""
        words = _WORD.findall(text)
        counts = Counter(words)
        if len(self._known) > 200_000:
            self._known.clear()
        known = self._known
        places = []
        for word in counts:
            place = known.get(word)
            if place is None:
                place = known[word] = zlib.crc32(word.lower().encode("utf-8", "surrogatepass")) % BUCKETS
            places.append(place)
        weights = np.bincount(np.array(places, np.int64), np.fromiter(counts.values(), float, len(counts)), BUCKETS) if places else np.zeros(BUCKETS)
        index = np.flatnonzero(weights)
        value = np.log1p(weights[index])
        return index, value / (np.linalg.norm(value) or 1.0), np.array(structure(text, words) + known_of_it)


class FactorisationMachine:
    """Second-order machine trained by Adagrad on the logistic loss."""

    def __init__(self, seed: int = 7) -> None:
        size = BUCKETS + N_SHAPE
        self.bias = 0.0
        self.linear = np.zeros(size)
        self.factors = np.random.default_rng(seed).normal(0, 0.02, (size, FACTORS))
        self.mean, self.spread = np.zeros(N_SHAPE), np.ones(N_SHAPE)
        self.constant: float | None = None

    def _join(self, parts: tuple[np.ndarray, np.ndarray, np.ndarray]) -> tuple[np.ndarray, np.ndarray]:
        index, value, shape = parts
        shape = np.clip((shape - self.mean) / self.spread, -4, 4) / math.sqrt(N_SHAPE)
        return np.append(index, BUCKETS + np.arange(N_SHAPE)), np.append(value, shape)

    def raw(self, parts: tuple[np.ndarray, np.ndarray, np.ndarray]) -> float:
        index, x = self._join(parts)
        own = self.factors[index]
        sums = x @ own
        squares = (x * x) @ (own * own)
        return float(self.bias + self.linear[index] @ x + 0.5 * (sums @ sums - squares.sum()))

    def score(self, parts: tuple[np.ndarray, np.ndarray, np.ndarray]) -> float:
        if self.constant is not None:
            return self.constant
        return 1.0 / (1.0 + math.exp(-max(-30.0, min(30.0, self.raw(parts)))))

    def fit(self, rows: list[tuple[np.ndarray, np.ndarray, np.ndarray]], labels: np.ndarray, seed: int = 11) -> FactorisationMachine:
        if len(set(labels.tolist())) < 2:
            self.constant = float(labels.mean()) if len(labels) else 0.5
            return self
        shapes = np.array([r[2] for r in rows])
        self.mean, self.spread = shapes.mean(0), shapes.std(0) + 1e-6
        joined = [self._join(r) for r in rows]
        order = np.random.default_rng(seed)
        seen_linear, seen_factors, seen_bias = np.full(len(self.linear), 1e-8), np.full(self.factors.shape, 1e-8), 1e-8
        for _ in range(EPOCHS):
            for i in order.permutation(len(joined)):
                index, x = joined[i]
                own = self.factors[index]
                sums = x @ own
                raw = self.bias + self.linear[index] @ x + 0.5 * (sums @ sums - ((x * x) @ (own * own)).sum())
                error = 1.0 / (1.0 + math.exp(-max(-30.0, min(30.0, raw)))) - labels[i]
                slope = error * x + DECAY * self.linear[index]
                seen_linear[index] += slope * slope
                self.linear[index] -= RATE * slope / np.sqrt(seen_linear[index])
                bend = error * (np.outer(x, sums) - own * (x * x)[:, None]) + DECAY * own
                seen_factors[index] += bend * bend
                self.factors[index] = own - RATE * bend / np.sqrt(seen_factors[index])
                seen_bias += error * error
                self.bias -= RATE * error / math.sqrt(seen_bias)
        return self


def _read(docs: DataFrame) -> DataFrame:
    """``doc_id, text, n_chars``; the last is null where there is no such column."""
    chars = F.col("n_chars").cast("long") if "n_chars" in docs.columns else F.lit(None).cast("long")
    return docs.select("doc_id", "text", chars.alias("n_chars"))


def training_rows(docs: DataFrame, labels: DataFrame, sample_docs: int = SAMPLE_DOCS) -> DataFrame:
    """``doc_id, text, n_chars, quality`` of at most ``sample_docs`` labelled ids that are not held out."""
    usable = labels.select("doc_id", "quality").where(F.col("quality").isNotNull() & F.col("doc_id").isNotNull() & ~held_out(F.col("doc_id")))
    chosen = usable.groupBy("doc_id").agg(F.max("quality").alias("quality")).orderBy(F.xxhash64("doc_id", F.lit("sample")), "doc_id").limit(sample_docs)
    return _read(docs).join(F.broadcast(chosen), "doc_id").dropDuplicates(["doc_id"])


def fit(docs: DataFrame, labels: DataFrame, sample_docs: int = SAMPLE_DOCS) -> FactorisationMachine:
    """Features are made where the texts lie; only they reach the driver."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        make = Featuriser()
        for batch in batches:
            made = [make(t.as_py(), n.as_py()) for t, n in zip(batch.column(1), batch.column(2), strict=True)]
            columns = [batch.column(0), batch.column(3).cast(pa.int32())]
            columns += [pa.array([m[i].tolist() for m in made], kind) for i, kind in enumerate((pa.list_(pa.int32()), pa.list_(pa.float64()), pa.list_(pa.float64())))]
            yield pa.RecordBatch.from_arrays(columns, ["doc_id", "quality", "index", "value", "shape"])

    rows = training_rows(docs, labels, sample_docs).mapInArrow(run, "doc_id long, quality int, index array<int>, value array<double>, shape array<double>")
    found = rows.toArrow().sort_by("doc_id")
    cells = [[cell.values.to_numpy() for cell in found.column(name)] for name in ("index", "value", "shape")]
    parts = [(index.astype(np.int64), value, shape) for index, value, shape in zip(*cells, strict=True)]
    return FactorisationMachine().fit(parts, (found.column("quality").to_numpy() == 1).astype(float))


def score_quality(docs: DataFrame, machine: FactorisationMachine) -> DataFrame:
    """``doc_id, held_out, score, predicted`` for each row."""
    arrow_ready(docs.sparkSession)
    shared = docs.sparkSession.sparkContext.broadcast(machine)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        make, own = Featuriser(), shared.value
        for batch in batches:
            scores = np.array([own.score(make(t.as_py(), n.as_py())) for t, n in zip(batch.column(2), batch.column(3), strict=True)], float)
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(scores), pa.array((scores >= 0.5).astype(np.int32))], ["doc_id", "held_out", "score", "predicted"])

    rows = _read(docs).select(F.col("doc_id").cast("long"), held_out(F.col("doc_id")).alias("held_out"), "text", "n_chars")
    return rows.mapInArrow(run, "doc_id long, held_out boolean, score double, predicted int")


def op4_quality_classifier(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = read_table(spark, sf_dir, "documents")
    return score_quality(docs, fit(docs, read_table(spark, sf_dir, "labels")))
