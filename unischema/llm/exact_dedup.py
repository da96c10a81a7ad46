"""Exact deduplication: local combining, salted digest groups, then salt winners globally.

Every stage groups by the digest *and* the full normalised content, so a digest collision can
never merge two texts. Copies are combined inside each task before anything is shuffled, what is
left of a group is spread over ``salts`` tasks, and only one row per salt meets in the last stage.

Defined results for odd input: a null text counts as empty, and all empty texts are one group.
A null ``doc_id`` takes part in its group; it is chosen only if no row of the best length has an
id. Rows that repeat an id are one document: all of them carry ``kept`` of that id. Columns other
than ``doc_id`` and ``text`` are ignored, and an empty table gives an empty result. Very long texts are
normalised and compared whole, one row at a time.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from unischema.llm.common import cut, drop_rows, read_table

BLANKS = r"[\x20\x09-\x0D]+"
#: A group counts as hot beyond one in so many rows; so there are fewer hot groups than this.
HOT_SHARE = 1000


def sha256_of(body: Column) -> Column:
    return F.unhex(F.sha2(body, 256))


def exact_dedup(docs: DataFrame, salts: int = 32, digest=sha256_of) -> DataFrame:
    """One row per row of ``docs``: ``doc_id, keep_id, group_size, kept, text_sha256``.

    Of equal texts (blanks deleted) the row with the most code points stays, then the smallest id.
    """
    text = F.coalesce(F.col("text"), F.lit(""))
    body = F.regexp_replace(text, BLANKS, "")
    rows = docs.select("doc_id", F.length(text).alias("n"), body.alias("body")).withColumn("digest", digest(F.col("body")))

    salted = (
        rows.withColumn("salt", F.pmod(F.xxhash64("doc_id"), F.lit(salts)))
        .groupBy("digest", "body", "n", "salt")
        .agg(F.min("doc_id").alias("doc_id"), F.count(F.lit(1)).alias("size"))
    )
    winners = (
        salted.repartition("digest")
        .groupBy("digest", "body", "n")
        .agg(F.min("doc_id").alias("doc_id"), F.sum("size").alias("size"))
        .groupBy("digest", "body")
        .agg(F.max_by("doc_id", "n").alias("keep_id"), F.sum("size").alias("group_size"))
    )
    classes = cut(winners.select("digest", "keep_id", "group_size"))
    clashes = classes.groupBy("digest").count().where("count > 1").select("digest")
    keyed = rows.select("doc_id", "digest", F.sha2("body", 256).alias("text_sha256"))
    if clashes.isEmpty():
        return _assign(keyed, classes)
    clashes = cut(clashes)
    plain = _assign(keyed.join(clashes, "digest", "left_anti"), classes.join(clashes, "digest", "left_anti"))
    torn = rows.join(clashes, "digest", "left_semi")
    exact = torn.join(winners.join(clashes, "digest", "left_semi"), ["digest", "body"]).select(
        "doc_id", "keep_id", "group_size", F.col("doc_id").eqNullSafe(F.col("keep_id")).alias("kept"), F.sha2("body", 256).alias("text_sha256")
    )
    return plain.unionByName(exact)


def _assign(keyed: DataFrame, classes: DataFrame) -> DataFrame:
    """Give each row its class. The few hot classes are broadcast, so no task gathers a hot group."""
    total = classes.agg(F.sum("group_size")).first()[0] or 0
    hot = classes.where(F.col("group_size") * HOT_SHARE > F.lit(total)).select(
        "digest", F.col("keep_id").alias("hot_id"), F.col("group_size").alias("hot_size")
    )
    cold = classes.where(F.col("group_size") * HOT_SHARE <= F.lit(total)).select(F.col("digest").alias("key"), "keep_id", "group_size")
    spread = F.concat(F.lit("~"), F.coalesce(F.col("doc_id").cast("string"), F.lit(""))).cast("binary")
    routed = keyed.join(F.broadcast(hot), "digest", "left").withColumn("key", F.when(F.col("hot_size").isNull(), F.col("digest")).otherwise(spread))
    found = routed.join(cold, "key", "left")
    keep = F.when(F.col("hot_size").isNull(), F.col("keep_id")).otherwise(F.col("hot_id"))
    return found.select(
        "doc_id",
        keep.alias("keep_id"),
        F.coalesce("hot_size", "group_size").alias("group_size"),
        F.col("doc_id").eqNullSafe(keep).alias("kept"),
        "text_sha256",
    )


def op1_exact_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return exact_dedup(read_table(spark, sf_dir, "documents"))


def stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pipeline stage: only the row that stays of each group goes on."""
    found = exact_dedup(docs)
    return drop_rows(docs, found.where(~F.col("kept")).select("doc_id"))


ORACLE = r"""
WITH t AS (
  SELECT doc_id, length(coalesce(text, '')) AS n, regexp_replace(coalesce(text, ''), '[\x20\x09-\x0D]+', '', 'g') AS body
  FROM documents
), g AS (
  SELECT doc_id, body, first_value(doc_id) OVER (PARTITION BY body ORDER BY n DESC, doc_id) AS keep_id,
         count(*) OVER (PARTITION BY body) AS group_size
  FROM t
)
SELECT doc_id, keep_id, group_size, doc_id = keep_id AS kept, sha256(body) AS text_sha256 FROM g
"""
