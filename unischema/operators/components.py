"""Connected components of pair lists, by alternating large-star and small-star steps."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from unischema.functions.lineage import cut


def components(pairs: DataFrame) -> DataFrame:
    """``node, label`` for every node of a pair; the label is the least node of its component.

    Each round joins on nodes and reduces by minima; no neighbourhood is ever gathered. The only
    thing the driver reads per round is a count and a checksum of the edges.
    """
    edges = cut(pairs.select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")).where("u <> v").distinct())
    mark = None
    while True:
        both = edges.unionByName(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
        least = both.groupBy("u").agg(F.least(F.min("v"), F.col("u")).alias("m"))
        large = both.join(least, "u").where("v > u").select(F.col("v").alias("u"), F.col("m").alias("v")).where("u <> v").distinct()
        floor = large.groupBy("u").agg(F.min("v").alias("m"))
        down = large.join(floor, "u").select(F.greatest("v", "m").alias("x"), "m").where("x <> m").select(F.col("x").alias("u"), F.col("m").alias("v"))
        edges = cut(down.unionByName(floor.select("u", F.col("m").alias("v"))).distinct())
        now = edges.agg(F.count(F.lit(1)), F.sum(F.pmod(F.xxhash64("u", "v"), F.lit(1 << 40)))).first()
        if now == mark:
            break
        mark = now
    leaves = edges.select(F.col("u").alias("node"), F.col("v").alias("label"))
    roots = edges.select(F.col("v").alias("node")).distinct().join(edges.select(F.col("u").alias("node")), "node", "left_anti")
    return leaves.unionByName(roots.select("node", F.col("node").alias("label")))


def label_nodes(nodes: DataFrame, pairs: DataFrame) -> DataFrame:
    """``node, label`` for all ``nodes``, those without pairs being their own label."""
    found = components(pairs)
    return nodes.join(found, "node", "left").select("node", F.coalesce("label", "node").alias("label"))


def components_by_propagation(pairs: DataFrame) -> DataFrame:
    """The same by spreading the least label over the pairs; a slow form to test against."""
    both = cut(pairs.select(F.col("a").alias("u"), F.col("b").alias("v")).unionByName(pairs.select(F.col("b").alias("u"), F.col("a").alias("v"))).distinct())
    labels = cut(both.select(F.col("u").alias("node")).distinct().select("node", F.col("node").alias("label")))
    while True:
        heard = both.join(labels, both["v"] == labels["node"]).groupBy("u").agg(F.min("label").alias("heard"))
        fresh = cut(labels.join(heard, labels["node"] == heard["u"], "left").select("node", F.least("label", F.coalesce("heard", "label")).alias("label"), (F.coalesce("heard", "label") < F.col("label")).alias("changed")))
        labels = fresh.select("node", "label")
        if fresh.where("changed").isEmpty():
            return labels
