"""Benchmark decontamination by winnowed fingerprints, extended to exact windows.

Both sides hash every ``gram`` consecutive words and keep, of every ``width - gram + 1`` consecutive
hashes, the smallest. A span of ``width`` words present on both sides has the same hashes on both,
so the same one is kept on both: joining the kept hashes misses no shared span. Each hit is then
extended: every window of ``width`` words about it is compared as text with the items' windows.

Items of fewer than ``width`` words are one window each. For every such length present (at most
``width - 1``) a document's hash of each run of that many words is looked up instead.

Winnowing all documents would be wasted on most of them. So a first pass looks up every gram of a
document among the items' fingerprints and drops documents without any: a shared span holds a kept
gram of the item, so no document is lost. Winnowing and extension run on those that remain.

The fingerprints and windows of the items, and the ids of the remaining documents, are broadcast only
up to a checked number of rows; beyond it the same joins shuffle. Hits are keyed by document, so a
passage that many documents share meets in no single task.

Defined results: null texts have no words; an item without words has no window; item ids are
compared as text and a null id counts as the empty one; rows that repeat are each returned;
columns beyond the named ones are ignored; empty tables give an empty result or no hits. Very long
texts are read whole, in steps linear in their words. Of equal hashes in a winnow the place does not matter.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from unischema.llm.common import cut, drop_rows, let, read_table, words

WIDTH = 13
GRAM = 5
#: Rows of item fingerprints or windows up to which they are broadcast.
BROADCAST_ROWS = 400_000
#: Bits of a packed fingerprint that hold the place of its gram.
PLACE_BITS = 30
#: Each document sends one row through the join to a key of its own choice among so many.
MARKERS = 1024


def _run_hash(tokens: Column, at: Column, length: int) -> Column:
    return F.xxhash64(F.slice(tokens, at + 1, length))


def winnow(tokens: Column, width: int = WIDTH, gram: int = GRAM) -> Column:
    """Distinct packed fingerprints (hash above, place below) of a word array; none if it is short."""
    span = width - gram + 1
    n = F.size(tokens)
    packed = F.transform(
        F.sequence(F.lit(0), n - gram),
        lambda i: F.shiftleft(F.shiftright(_run_hash(tokens, i, gram), PLACE_BITS), PLACE_BITS).bitwiseOR(i.cast("long")),
    )
    minima = let(packed, lambda p: F.transform(F.sequence(F.lit(1), F.size(p) - (span - 1)), lambda s: F.array_min(F.slice(p, s, span))))
    return F.when(n >= width, F.array_distinct(minima)).otherwise(F.array().cast("array<bigint>"))


def _hash_of(packed: Column) -> Column:
    return F.shiftright(packed, PLACE_BITS)


def _place_of(packed: Column) -> Column:
    return packed.bitwiseAND(F.lit((1 << PLACE_BITS) - 1)).cast("int")


def _item_tables(items: DataFrame, width: int, gram: int) -> tuple[DataFrame, DataFrame]:
    """``(kind, fp)`` of the items, and ``(win, len, items)`` for each distinct window."""
    tokens = items.select(F.coalesce(F.col("item_id").cast("string"), F.lit("")).alias("item"), words(F.col("text")).alias("w")).where(F.size("w") > 0)
    tokens = cut(tokens)
    w, n = F.col("w"), F.size("w")
    length = F.least(n, F.lit(width))
    windows = (
        tokens.select("item", length.alias("len"), F.explode(F.transform(F.sequence(F.lit(1), n - length + 1), lambda s: F.concat_ws(" ", F.slice(w, s, length)))).alias("win"))
        .groupBy("win", "len")
        .agg(F.collect_set("item").alias("items"))
    )
    long = tokens.where(n >= width).select(F.lit(width).alias("kind"), F.explode(winnow(w, width, gram)).alias("p")).select("kind", _hash_of(F.col("p")).alias("fp"))
    short = [
        tokens.where(n == size).select(F.lit(size).alias("kind"), _hash_of(_run_hash(w, F.lit(0), size)).alias("fp")) for size in range(1, width)
    ]
    prints = long
    for part in short:
        prints = prints.unionByName(part)
    return cut(prints.distinct()), cut(windows)


def _entries(tokens: Column, short: list[int], width: int, gram: int) -> Column:
    """A document's fingerprints with the words about them."""
    back = width - gram
    kind = "array<struct<kind:int,fp:bigint,at:int,ctx:array<string>>>"
    entry = lambda k, fp, at, ctx: F.struct(k.alias("kind"), fp.alias("fp"), at.alias("at"), ctx.alias("ctx"))

    def about(packed: Column) -> Column:
        return let(
            F.greatest(_place_of(packed) - back, F.lit(0)),
            lambda start: entry(F.lit(width), _hash_of(packed), start, F.slice(tokens, start + 1, width + back)),
        )

    def runs(size: int) -> Column:
        every = F.sequence(F.lit(0), F.size(tokens) - size)
        return F.transform(every, lambda i: entry(F.lit(size), _hash_of(_run_hash(tokens, i, size)), i, F.slice(tokens, i + 1, size)))

    parts = [F.transform(winnow(tokens, width, gram), about).cast(kind)]
    for size in short:
        parts.append(F.when(F.size(tokens) >= size, runs(size).cast(kind)).otherwise(F.array().cast(kind)))
    return F.concat(*parts)


def _all_hashes(tokens: Column, size: int) -> Column:
    return F.transform(F.sequence(F.lit(0), F.size(tokens) - size), lambda i: _hash_of(_run_hash(tokens, i, size)))


def _sift(docs: DataFrame, prints: DataFrame, short: list[int], small: bool, gram: int) -> DataFrame:
    """``doc_id, mark, n_words, copies, met`` for each distinct row: whether some gram is an item's.

    Each row also sends one marker through the join, spread over ``MARKERS`` keys, so that rows
    without any gram in common come out too.
    """
    spark = docs.sparkSession
    keys = prints.select("fp").distinct()
    keys = keys.unionByName(spark.range(MARKERS).select((-F.col("id") - (1 << 40)).alias("fp")))

    def grams(tokens: Column) -> Column:
        marker = F.array((-F.pmod(F.xxhash64("doc_id", "mark"), F.lit(MARKERS)) - (1 << 40)).cast("long"))
        parts = [marker]
        for size in sorted({gram, *short}):
            parts.append(F.when(F.size(tokens) >= size, _all_hashes(tokens, size)).otherwise(F.array().cast("array<bigint>")))
        return F.struct(F.size(tokens).alias("n"), F.concat(*parts).alias("fps"))

    rows = docs.select("doc_id", F.xxhash64("text").alias("mark"), "text")
    rows = rows.select("doc_id", "mark", let(words(F.col("text")), grams).alias("g")).select("doc_id", "mark", F.col("g.n").alias("n"), F.explode("g.fps").alias("fp"))
    met = rows.join(F.broadcast(keys) if small else keys, "fp")
    marker = F.col("fp").between(-(1 << 40) - MARKERS, -(1 << 40))
    return cut(met.groupBy("doc_id", "mark").agg(F.max("n").cast("long").alias("n_words"), F.count_if(marker).alias("copies"), F.bool_or(~marker).alias("met")))


def decontaminate(docs: DataFrame, items: DataFrame, width: int = WIDTH, gram: int = GRAM, broadcast_rows: int = BROADCAST_ROWS) -> DataFrame:
    """``doc_id, n_words, n_hit, n_items, items_sha256, contaminated, item_ids`` for each row."""
    prints, windows = _item_tables(items, width, gram)
    short = sorted(r["kind"] for r in prints.where(F.col("kind") < width).select("kind").distinct().collect())
    small = prints.count() <= broadcast_rows and windows.count() <= broadcast_rows
    sifted = _sift(docs, prints, short, small, gram)

    chosen = sifted.where("met").select(F.col("doc_id").alias("k0"), F.col("mark").alias("k1"))
    if chosen.count() <= broadcast_rows:
        chosen = F.broadcast(chosen)
    rows = docs.select("doc_id", F.xxhash64("text").alias("mark"), "text")
    rows = rows.join(chosen, rows["doc_id"].eqNullSafe(chosen["k0"]) & (rows["mark"] == chosen["k1"]), "left_semi")
    rows = rows.select("doc_id", "mark", F.explode(let(words(F.col("text")), lambda w: _entries(w, short, width, gram))).alias("e")).select("doc_id", "mark", "e.*")
    met = rows.join(F.broadcast(prints) if small else prints, ["kind", "fp"])

    length = F.col("kind")
    tried = F.transform(
        F.sequence(F.lit(0), F.size("ctx") - length),
        lambda j: F.struct((F.col("at") + j).alias("start"), F.concat_ws(" ", F.slice("ctx", j + 1, length)).alias("win")),
    )
    spans = met.select("doc_id", "mark", F.explode(tried).alias("s")).select("doc_id", "mark", "s.*")
    hits = spans.join(F.broadcast(windows) if small else windows, "win")
    found = hits.groupBy("doc_id", "mark").agg(
        F.collect_set(F.struct("start", "len")).alias("spans"), F.array_distinct(F.flatten(F.collect_set("items"))).alias("found")
    )
    step = lambda acc, x: F.struct(
        F.greatest(acc["end"], x["start"] + x["len"]).alias("end"),
        (acc["covered"] + F.greatest(F.lit(0), x["start"] + x["len"] - F.greatest(acc["end"], x["start"]))).cast("long").alias("covered"),
    )
    covered = F.aggregate(F.sort_array("spans"), F.struct(F.lit(0).alias("end"), F.lit(0).cast("long").alias("covered")), step)["covered"]
    found = found.select(F.col("doc_id").alias("k0"), F.col("mark").alias("k1"), covered.alias("n_hit"), F.sort_array("found").alias("found"))

    both = sifted.join(found, sifted["doc_id"].eqNullSafe(found["k0"]) & (sifted["mark"] == found["k1"]), "left")
    ids = F.coalesce("found", F.array().cast("array<string>"))
    n_hit = F.coalesce("n_hit", F.lit(0).cast("long"))
    return both.select(
        "doc_id",
        "n_words",
        n_hit.alias("n_hit"),
        F.size(ids).cast("long").alias("n_items"),
        F.sha2(F.concat_ws(",", ids), 256).alias("items_sha256"),
        ((n_hit > 0) & (n_hit * 20 >= F.col("n_words"))).alias("contaminated"),
        ids.alias("item_ids"),
        F.explode(F.sequence(F.lit(1).cast("long"), F.col("copies"))).alias("copy"),
    ).drop("copy")


def stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pipeline stage: contaminated documents go."""
    found = decontaminate(docs, read_table(spark, sf_dir, "benchmark"))
    return drop_rows(docs, found.where("contaminated").select("doc_id"))


def op2_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    return decontaminate(read_table(spark, sf_dir, "documents"), read_table(spark, sf_dir, "benchmark")).drop("item_ids")


ORACLE = r"""
WITH dw AS (
  SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS w
  FROM documents
), bw AS (
  SELECT item_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS w
  FROM benchmark
), wins AS (
  SELECT DISTINCT item_id, least(len(w), 13) AS size, array_to_string(w[s : s + least(len(w), 13) - 1], ' ') AS win
  FROM (SELECT item_id, w, unnest(range(1, len(w) - least(len(w), 13) + 2)) AS s FROM bw WHERE len(w) > 0)
), sizes AS (
  SELECT DISTINCT size FROM wins
), runs AS (
  SELECT doc_id, size, s, array_to_string(w[s : s + size - 1], ' ') AS win
  FROM (SELECT doc_id, w, size, unnest(range(1, len(w) - size + 2)) AS s FROM dw, sizes WHERE len(w) >= size)
), hits AS (
  SELECT doc_id, s, runs.size, item_id FROM runs JOIN wins ON runs.win = wins.win AND runs.size = wins.size
), places AS (
  SELECT doc_id, count(DISTINCT p) AS n_hit
  FROM (SELECT doc_id, unnest(range(s, s + size)) AS p FROM (SELECT DISTINCT doc_id, s, size FROM hits)) GROUP BY doc_id
), named AS (
  SELECT doc_id, count(*) AS n_items, string_agg(item, ',' ORDER BY item) AS ids
  FROM (SELECT DISTINCT doc_id, item_id::VARCHAR AS item FROM hits) GROUP BY doc_id
)
SELECT doc_id, len(w)::BIGINT AS n_words, coalesce(n_hit, 0)::BIGINT AS n_hit, coalesce(n_items, 0)::BIGINT AS n_items,
       sha256(coalesce(ids, '')) AS items_sha256, coalesce(n_hit, 0) > 0 AND 20 * coalesce(n_hit, 0) >= len(w) AS contaminated
FROM dw LEFT JOIN places USING (doc_id) LEFT JOIN named USING (doc_id)
"""
