"""What the methods are compared with: nested loops, index-free scans, unverified filters."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from unischema.functions.lineage import cut
from unischema.operators.knowledge import balls, compose, deal, every_end, unit_ball

#: Words of one task of the nested loop, and the most words that are sent to all tasks.
LOOP_WORDS, BROADCAST_WORDS = 1024, 2_000_000


def bruteforce_literal(attrs: DataFrame, eps: int) -> DataFrame:
    """All pairs compared: the nested loop.

    Lengths and sets of letters (64 bits) are compared before the words: an edit changes the length by one
    at most and the set by two letters at most.
    """
    letter = lambda c: F.call_function("shiftleft", F.lit(1).cast("long"), F.pmod(F.ascii(c), F.lit(64)))
    letters = F.aggregate(F.split("attr", ""), F.lit(0).cast("long"), lambda bits, c: bits.bitwiseOR(letter(c)))
    words = cut(attrs.select("attr").where("attr IS NOT NULL").distinct().select("attr", F.length("attr").alias("len"), letters.alias("letters")))
    n = words.count()
    x, y = words.repartition(max(int(words.sparkSession.conf.get("spark.sql.shuffle.partitions")), -(-n // LOOP_WORDS))).alias("x"), words.alias("y")
    x = x.withColumn("near", F.explode(F.sequence(F.col("len") - eps, F.col("len") + eps))).alias("x")
    near = (F.col("x.near") == F.col("y.len")) & (F.bit_count(F.col("x.letters").bitwiseXOR(F.col("y.letters"))) <= 2 * eps)
    within = near & (F.col("x.attr") < F.col("y.attr")) & (F.levenshtein("x.attr", "y.attr", eps) >= 0)
    pairs = x.join(F.broadcast(y) if n <= BROADCAST_WORDS else y, within)
    return pairs.select(F.col("x.attr").alias("a"), F.col("y.attr").alias("b"), F.levenshtein("x.attr", "y.attr").alias("d"))


def bruteforce_semantic(h1: DataFrame, gamma: int) -> DataFrame:
    """Least lengths between all concepts within ``gamma``, whatever the inputs are."""
    tasks = deal(h1, h1)
    if tasks is not None:
        return balls(every_end(h1, h1), h1, ["all"] * gamma, tasks).toDF("a", "b", "len")
    out = ball = cut(unit_ball(h1))
    for _ in range(gamma - 1):
        out = cut(compose(out, ball))
    return out if gamma else ball.where("len = 0")


def scan_semantic(seeds: DataFrame, edge_set: DataFrame, gamma: int) -> DataFrame:
    """Path expansion on the raw edge list, scanned and joined in both directions each round."""
    reached = cut(seeds.select(F.col("concept").alias("start"), F.col("concept").alias("end"), F.lit(0).alias("len")).distinct())
    for length in range(1, gamma + 1):
        up = reached.join(edge_set.hint("merge"), reached["end"] == edge_set["sub"]).select("start", F.col("sup").alias("end"))
        down = reached.join(edge_set.hint("merge"), reached["end"] == edge_set["sup"]).select("start", F.col("sub").alias("end"))
        both = up.unionByName(down).withColumn("len", F.lit(length))
        reached = cut(reached.unionByName(both).groupBy("start", "end").agg(F.min("len").alias("len")))
    return reached


def expand_by_single_hops(seeds: DataFrame, h1: DataFrame, gamma: int) -> DataFrame:
    """Expansion by the one-hop table alone, one min-plus join per step."""
    tasks = deal(seeds, h1)
    if tasks is not None:
        known = every_end(h1, h1) if gamma else seeds
        return balls(seeds.join(known.distinct(), "concept", "left_semi"), h1, ["all"] * gamma, tasks)
    ball = cut(unit_ball(h1))
    rows = seeds.select(F.col("concept").alias("a"), F.col("concept").alias("b"), F.lit(0).alias("len")).distinct()
    for _ in range(gamma):
        rows = cut(compose(rows, ball))
    return rows.select(F.col("a").alias("start"), F.col("b").alias("end"), "len")
