"""Accuracy and cost measures."""

from __future__ import annotations

import time
from collections.abc import Callable

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from unischema.functions.lineage import cut
from unischema.operators.knowledge import k_hop


def accuracy(found: DataFrame, gold: DataFrame) -> DataFrame:
    """Per target: sizes of ``found(target, attr)`` and ``gold(target, attr)``, common, recall, precision."""
    f = found.select("target", "attr", F.lit(1).alias("f")).distinct()
    g = gold.select("target", "attr", F.lit(1).alias("g")).distinct()
    both = f.join(g, ["target", "attr"], "full")
    counts = both.groupBy("target").agg(F.count("f").alias("found"), F.count("g").alias("gold"), F.count_if(F.col("f").isNotNull() & F.col("g").isNotNull()).alias("common"))
    ratio = lambda n, d: F.when(F.col(d) > 0, F.round(F.col(n) / F.col(d), 6))
    return counts.select("target", "found", "gold", "common", ratio("common", "gold").alias("recall"), ratio("common", "found").alias("precision"))


def macro_average(per_target: DataFrame) -> DataFrame:
    return per_target.agg(F.round(F.avg("recall"), 6).alias("recall"), F.round(F.avg("precision"), 6).alias("precision"))


def result_size(reached: DataFrame) -> DataFrame:
    """Concepts and inputs in a result set."""
    return reached.agg(F.count_distinct("start").alias("input_size"), F.count_distinct("end").alias("result_size"))


def second_degree(seeds: DataFrame, h1: DataFrame) -> DataFrame:
    """Concepts exactly two hops from each seed."""
    return k_hop(seeds, h1, 2).where("len = 2").groupBy(F.col("start").alias("concept")).agg(F.count(F.lit(1)).alias("degree2"))


def growth(sizes: DataFrame, group: str, over: str, value: str) -> DataFrame:
    """Ratio of each value to the one before it along ``over``."""
    order = Window.partitionBy(group).orderBy(over)
    return sizes.withColumn("ratio", F.round(F.col(value) / F.lag(value).over(order), 6))


def frontier_stats(reached: DataFrame) -> DataFrame:
    """Rows first reached in each round of an expansion."""
    return reached.groupBy("len").agg(F.count(F.lit(1)).alias("n_paths"), F.count_distinct("end").alias("n_ends"))


def judge_agreement(votes: DataFrame, gold: DataFrame) -> DataFrame:
    """Recall of each judge against a gold set of kept pairs, with mean and spread over judges."""
    kept = votes.where("verdict = 'keep'").select("judge", "a", "b").distinct()
    total = gold.agg(F.count(F.lit(1)).alias("total"))
    hits = kept.join(gold.select("a", "b").distinct(), ["a", "b"], "left_semi").groupBy("judge").agg(F.count(F.lit(1)).alias("hits"))
    every = votes.select("judge").distinct().join(hits, "judge", "left").crossJoin(F.broadcast(total))
    recall = every.select((F.coalesce("hits", F.lit(0)) / F.col("total")).alias("recall"))
    return recall.agg(F.round(F.avg("recall"), 6).alias("mean"), F.round(F.stddev_samp("recall"), 6).alias("deviation"))


def compression(n_in: DataFrame, n_out: DataFrame) -> DataFrame:
    """Attributes in, global attributes out, and their ratio."""
    x = n_in.agg(F.count_distinct("attr").alias("n_attrs"))
    y = n_out.agg(F.count_distinct("part_id").alias("n_global"))
    return x.crossJoin(y).withColumn("ratio", F.round(F.col("n_attrs") / F.col("n_global"), 6))


def filter_stats(attrs: DataFrame, eps: int = 1, q: int = 2) -> DataFrame:
    """``n_words, n_candidates, n_pairs, ratio``: what the filters of a literal self join let through, and what is right."""
    from unischema.operators.grams import deletion_candidates, gram_candidates, gram_index

    words = cut(attrs.select("attr").where("attr IS NOT NULL").distinct())
    postings = gram_index(words, q)
    found = gram_candidates(postings, postings, q, eps).select("a", "b").unionByName(deletion_candidates(words, words, q, eps)).distinct()
    right = F.levenshtein("a", "b", eps) >= 0
    counts = found.agg(F.count(F.lit(1)).alias("n_candidates"), F.count_if(right).alias("n_pairs"))
    return words.agg(F.count(F.lit(1)).alias("n_words")).crossJoin(counts).withColumn("ratio", F.round(F.try_divide("n_pairs", "n_candidates"), 6))


def slope(rows: DataFrame, value: str, over: str, *by: str) -> DataFrame:
    """The least-squares slope of one measure over another, and the number of points, in each group."""
    return rows.groupBy(*by).agg(F.round(F.regr_slope(F.col(value), F.col(over)), 4).alias("slope"), F.count(F.lit(1)).alias("n"))


def timed(build: Callable[[], DataFrame]) -> float:
    """Wall seconds of a run: what ``build`` does at once, and its result into the noop sink."""
    began = time.perf_counter()
    build().write.format("noop").mode("overwrite").save()
    return time.perf_counter() - began
