"""Line deduplication on a suffix array of line ids, built by distributed prefix doubling.

Every document is the sequence of its non-blank lines. A line that occurs once ends any repeated
run, so only *segments* of lines that occur more than once are indexed. Their suffixes are ranked by
prefix doubling: level 0 ranks the lines, level k+1 ranks the pairs (rank of 2^k lines here, rank of
the next 2^k lines). Ranks are order-preserving numbers of range-partitioned, sorted distinct pairs,
so no task sorts more than its share, however common one line is.

A run qualifies if it has at least ``min_words`` words, and a line is deleted if some qualifying run
around it also occurs earlier (by doc_id, then place). It is enough to look at two runs for each
line: the shortest qualifying one that begins there and the shortest that ends there. (Any line of a
qualifying repeated run lies in one of these that is inside the run: if the run up to the line
qualifies, the shortest that ends at the line; else the shortest from the run's begin passes it.)
The suffixes that share such a run are one interval of the suffix array whose common prefix is at
least the run; it is named by its length and the ranks of two overlapping power-of-two blocks. Of
each interval the earliest suffix stays, and the others' runs are deleted. So maximal repeated runs
go as unions of these, and no level beyond ``log2(min_words)`` is needed.

Defined results: null texts are empty; very long texts are one row only where lines are split and joined
again, in steps linear in their lines; equal runs in one document are ordered by place; blank lines are never deleted and do not break runs; rows that
repeat both id and text are one document; null ids come last in the order of copies; columns beyond
``doc_id`` and ``text`` are ignored; an empty table gives an empty result.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from unischema.llm.common import cut, let, read_table

MIN_WORDS = 50
BLANK = r"[\x20\x09\x0B-\x0D]+"
POSITION = ("doc_id", "mark", "at")


def lines_of(text: Column) -> Column:
    return F.split(F.coalesce(text, F.lit("")), "\n", -1)


def full(line: Column) -> Column:
    """Whether a line has anything but blanks."""
    return F.length(F.btrim(line, F.lit(" \t\x0b\x0c\r"))) > 0


def word_count(line: Column) -> Column:
    """Words of a line that isn't blank. Lines with single spaces alone are counted by their spaces."""

    def count(body: Column) -> Column:
        return F.length(body) - F.length(F.replace(body, F.lit(" "), F.lit(""))) + 1

    plain = F.trim(line)
    odd = plain.rlike(r"[\x09\x0B-\x0D]|  ")
    return F.when(odd, count(F.trim(F.regexp_replace(plain, BLANK, " ")))).otherwise(count(plain))


def _line_table(docs: DataFrame) -> DataFrame:
    """``doc_id, mark, at, a, b, words`` for each non-blank line; ``at`` counts non-blank lines.

    The mark is made before lines are taken apart: beside the generator it would be made for each line.
    """
    cells = F.transform(F.filter(lines_of(F.col("text")), full), lambda x: F.struct(F.xxhash64(x).alias("a"), F.xxhash64(F.lit(11), x).alias("b"), word_count(x).alias("words")))
    marked = docs.select("doc_id", F.xxhash64("text").alias("mark"), "text")
    return marked.select("doc_id", "mark", F.posexplode(cells).alias("at", "l")).select(*POSITION, "l.*")


def _ordered(distinct: DataFrame, *names: str) -> DataFrame:
    """Numbers in the order of ``names``: ranges of values go to ascending partitions, sorted inside."""
    return cut(distinct.repartitionByRange(*names).sortWithinPartitions(*names).withColumn("rank", F.monotonically_increasing_id()))


def _suffix_ranks(docs: DataFrame, min_words: int) -> tuple[DataFrame, int]:
    """Lines of repeated segments with ranks ``r0..rK`` of their suffixes; and K."""
    lines = cut(_line_table(docs))
    repeated = lines.groupBy("a", "b").agg(F.count(F.lit(1)).alias("many")).where("many > 1").select("a", "b")
    suffixes = lines.join(_ordered(repeated, "a", "b"), ["a", "b"]).select(*POSITION, "words", F.col("rank").alias("r0"))
    by_doc = Window.partitionBy("doc_id", "mark").orderBy("at")
    suffixes = cut(suffixes.dropDuplicates(list(POSITION)).withColumn("segment", F.col("at") - F.row_number().over(by_doc)))
    longest = suffixes.groupBy("doc_id", "mark", "segment").count().agg(F.max("count")).first()[0] or 0
    levels = int(math.log2(max(1, min(min_words, longest))))
    ahead = Window.partitionBy("doc_id", "mark", "segment").orderBy("at")
    for k in range(levels):
        pairs = suffixes.withColumn("next", F.lead(f"r{k}", 1 << k).over(ahead))
        known = pairs.where("next IS NOT NULL").groupBy(f"r{k}", "next").agg(F.count(F.lit(1)).alias("many")).where("many > 1").select(f"r{k}", "next")
        suffixes = cut(pairs.join(_ordered(known, f"r{k}", "next"), [f"r{k}", "next"], "left").drop("next").withColumnRenamed("rank", f"r{k + 1}"))
    return suffixes, levels


def _runs(suffixes: DataFrame, levels: int, min_words: int) -> DataFrame:
    """The shortest qualifying runs by begin and by end: ``doc_id, mark, at, m`` and the interval's name.

    Each line sees at most ``min_words`` lines ahead and behind, as every line has a word, so no row ever
    holds a whole segment, however long a text is.
    """
    ranks = [f"r{k}" for k in range(levels + 1)]
    by_segment = Window.partitionBy("doc_id", "mark", "segment").orderBy("at")
    cell = F.struct("words", *ranks)
    ahead = F.collect_list(cell).over(by_segment.rowsBetween(0, min_words - 1))
    behind = F.reverse(F.collect_list(cell).over(by_segment.rowsBetween(1 - min_words, 0)))

    def length(cells: Column) -> Column:
        """Lines of the shortest qualifying prefix of ``cells``; null if there is none."""
        start = F.struct(F.lit(0).cast("long").alias("words"), F.lit(0).alias("m"))
        step = lambda acc, x: F.when(acc["words"] >= min_words, acc).otherwise(F.struct((acc["words"] + x["words"]).cast("long").alias("words"), (acc["m"] + 1).alias("m")))
        return F.aggregate(cells, start, step, lambda acc: F.when(acc["words"] >= min_words, acc["m"]))

    def name(m: Column, first: Column, last) -> Column:
        """The interval of suffixes that begin with the run: ranks of the two power-of-two blocks that cover it."""
        pair = F.lit(None).cast("struct<x:bigint,y:bigint>")
        for k in range(levels + 1):
            pair = F.when(m >= (1 << k), F.struct(first[f"r{k}"].alias("x"), last(k)[f"r{k}"].alias("y"))).otherwise(pair)
        return pair

    seen = suffixes.withColumns({"ahead": ahead, "behind": behind}).withColumns({"m_ahead": length(F.col("ahead")), "m_behind": length(F.col("behind"))})
    begin = F.struct(F.col("at"), F.col("m_ahead").alias("m"), name(F.col("m_ahead"), F.get("ahead", F.lit(0)), lambda k: F.get("ahead", F.col("m_ahead") - (1 << k))).alias("pair"))
    end = F.struct((F.col("at") - F.col("m_behind") + 1).alias("at"), F.col("m_behind").alias("m"), name(F.col("m_behind"), F.get("behind", F.col("m_behind") - 1), lambda k: F.get("behind", F.lit((1 << k) - 1))).alias("pair"))
    both = seen.select("doc_id", "mark", F.explode(F.array(begin, end)).alias("r")).select("doc_id", "mark", "r.at", "r.m", "r.pair.x", "r.pair.y")
    return both.where("m IS NOT NULL AND x IS NOT NULL AND y IS NOT NULL").distinct()


def repeated_runs(docs: DataFrame, min_words: int = MIN_WORDS) -> DataFrame:
    """``doc_id, mark, at, m``: runs of ``m`` non-blank lines that also occur earlier.

    The intervals' first suffixes are a table of their own, so that AQE can split an interval that holds
    a large share of all runs.
    """
    suffixes, levels = _suffix_ranks(docs, min_words)
    runs = cut(_runs(suffixes, levels, min_words))
    place = F.struct(F.col("doc_id").isNull().alias("n"), "doc_id", "mark", "at")
    first = cut(runs.groupBy("m", "x", "y").agg(F.min(place).alias("first"), F.count(F.lit(1)).alias("many")).where("many > 1").drop("many"))
    return runs.join(first, ["m", "x", "y"]).where(place != F.col("first")).select(*POSITION, "m")


def _islands(runs: DataFrame) -> DataFrame:
    """``k0, k1, spans``: the removed lines of each document as disjoint intervals of places, in order."""
    before = Window.partitionBy("doc_id", "mark").orderBy("at", "m")
    reach = F.max(F.col("at") + F.col("m")).over(before.rowsBetween(Window.unboundedPreceding, -1))
    marked = runs.withColumn("fresh", (F.coalesce(reach, F.lit(-1)) < F.col("at")).cast("long"))
    numbered = marked.withColumn("island", F.sum("fresh").over(before.rowsBetween(Window.unboundedPreceding, 0)))
    spans = numbered.groupBy("doc_id", "mark", "island").agg(F.min("at").alias("from"), F.max(F.col("at") + F.col("m") - 1).alias("to"))
    return spans.groupBy(F.col("doc_id").alias("k0"), F.col("mark").alias("k1")).agg(F.array_sort(F.collect_list(F.struct("from", "to"))).alias("spans"))


def line_dedup(docs: DataFrame, min_words: int = MIN_WORDS) -> DataFrame:
    """``doc_id, n_lines, n_removed, text`` for each row: the text without later copies of runs."""
    spans = _islands(repeated_runs(docs, min_words))
    rows = docs.select("doc_id", F.xxhash64("text").alias("mark"), "text")
    met = rows.join(spans, rows["doc_id"].eqNullSafe(spans["k0"]) & (rows["mark"] == spans["k1"]), "left")

    def kept(lines: Column) -> Column:
        """The lines that stay. Places count lines that are not blank; all steps are linear in the lines."""
        every = F.sequence(F.lit(0), F.size(lines) - 1)

        def by_place(places: Column) -> Column:
            gone = F.flatten(F.transform("spans", lambda s: F.slice(places, s["from"].cast("int") + 1, (s["to"] - s["from"]).cast("int") + 1)))
            return F.transform(F.array_except(every, gone), lambda i: F.get(lines, i))

        return let(F.filter(every, lambda i: full(F.get(lines, i))), by_place)

    whole = F.coalesce(F.col("text"), F.lit(""))
    text = F.when(F.col("spans").isNull(), whole).otherwise(F.array_join(let(lines_of(F.col("text")), kept), "\n"))
    removed = F.aggregate("spans", F.lit(0).cast("long"), lambda n, s: n + (s["to"] - s["from"] + 1).cast("long"))
    return met.select(
        "doc_id",
        (F.length(whole) - F.length(F.replace(whole, F.lit("\n"), F.lit(""))) + 1).cast("long").alias("n_lines"),
        F.coalesce(removed, F.lit(0)).cast("long").alias("n_removed"),
        text.alias("text"),
    )


def op9_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = line_dedup(read_table(spark, sf_dir, "documents"))
    return found.select("doc_id", "n_lines", "n_removed", F.sha2("text", 256).alias("text_sha256"))


ORACLE = r"""
WITH l AS (
  SELECT doc_id, ord, line, len(regexp_extract_all(line, '[^\x20\x09\x0B-\x0D]+')) AS words
  FROM (SELECT doc_id, unnest(string_split(coalesce(text, ''), chr(10))) AS line, generate_subscripts(string_split(coalesce(text, ''), chr(10)), 1) AS ord FROM documents)
), s AS (
  SELECT doc_id, ord, line, words, row_number() OVER (PARTITION BY doc_id ORDER BY ord) AS pos FROM l WHERE words > 0
), d AS (
  SELECT doc_id, list(line ORDER BY pos) AS ls, list(words ORDER BY pos) AS ws FROM s GROUP BY doc_id
), i AS (
  SELECT doc_id, ls, ws, unnest(range(1, len(ls) + 1)) AS p FROM d
), m AS (
  SELECT doc_id, ls, p, list_filter(range(1, least(50, len(ls) - p + 1) + 1), lambda n : list_sum(ws[p : p + n - 1]) >= 50)[1] AS f,
         list_filter(range(1, least(50, p) + 1), lambda n : list_sum(ws[p - n + 1 : p]) >= 50)[1] AS b
  FROM i
), runs AS (
  SELECT doc_id, p AS pos, f AS m, array_to_string(ls[p : p + f - 1], chr(10)) AS body FROM m WHERE f IS NOT NULL
  UNION
  SELECT doc_id, p - b + 1, b, array_to_string(ls[p - b + 1 : p], chr(10)) FROM m WHERE b IS NOT NULL
), late AS (
  SELECT doc_id, pos, m, row_number() OVER (PARTITION BY body ORDER BY doc_id, pos) AS k FROM runs
), gone AS (
  SELECT DISTINCT doc_id, unnest(range(pos, pos + m)) AS pos FROM late WHERE k > 1
), kept AS (
  SELECT l.doc_id, count(*) AS n_lines, count(gone.pos) AS n_removed, coalesce(string_agg(l.line, chr(10) ORDER BY l.ord) FILTER (WHERE gone.pos IS NULL), '') AS text
  FROM l LEFT JOIN s ON l.doc_id = s.doc_id AND l.ord = s.ord LEFT JOIN gone ON s.doc_id = gone.doc_id AND s.pos = gone.pos GROUP BY l.doc_id
)
SELECT doc_id, n_lines::BIGINT AS n_lines, n_removed::BIGINT AS n_removed, sha256(text) AS text_sha256 FROM kept
"""
