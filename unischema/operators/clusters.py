"""Cluster families as two flat tables, and their merges.

``member(cluster_id, attr)`` and ``halo(cluster_id, concept, d_lit, d_sem)``. Ids are least member
names, so they do not depend on the plan.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from unischema.operators.components import label_nodes

HALO = "cluster_id string, concept string, d_lit int, d_sem int"


def singletons(attrs: DataFrame) -> dict[str, DataFrame]:
    """Each attribute a cluster of its own, with an empty halo."""
    member = attrs.select(F.col("attr").alias("cluster_id"), "attr").where("attr IS NOT NULL").distinct()
    return {"member": member, "halo": attrs.sparkSession.createDataFrame([], HALO)}


def locate(members: DataFrame, attrs: DataFrame) -> DataFrame:
    """``attr, cluster_id`` of the clusters that hold given attributes."""
    return attrs.join(members, "attr")


def least_halo(halo: DataFrame) -> DataFrame:
    """Of each concept in a cluster's halo, the least distances."""
    return halo.groupBy("cluster_id", "concept").agg(F.min("d_lit").alias("d_lit"), F.min("d_sem").alias("d_sem"))


def relabel(family: dict[str, DataFrame], labels: DataFrame) -> dict[str, DataFrame]:
    """Clusters renamed by ``node, label``; equal names unite, halos keep the least distances."""
    named = lambda df: df.join(labels, df["cluster_id"] == labels["node"], "left").withColumn("cluster_id", F.coalesce("label", "cluster_id")).drop("node", "label")
    member = named(family["member"]).distinct()
    least = member.groupBy("cluster_id").agg(F.min("attr").alias("name"))
    rename = lambda df: df.join(least, "cluster_id").withColumn("cluster_id", F.col("name")).drop("name")
    return {"member": rename(member), "halo": least_halo(rename(named(family["halo"])))}


def merge_all(pairs: DataFrame, family: dict[str, DataFrame]) -> dict[str, DataFrame]:
    """All joined clusters merged at once, transitively: components of the pairs of cluster ids."""
    nodes = family["member"].select(F.col("cluster_id").alias("node")).distinct()
    return relabel(family, label_nodes(nodes, pairs.select("a", "b")))


def merge_two(family: dict[str, DataFrame], one: str, other: str) -> dict[str, DataFrame]:
    """The merge of two clusters, members united, halo by least distance."""
    pair = family["member"].sparkSession.createDataFrame([(one, other)], "a string, b string")
    return merge_all(pair, family)


def refresh_halo(family: dict[str, DataFrame], anchors: DataFrame) -> dict[str, DataFrame]:
    """Members' anchors enter the halo at semantic distance 0, with their literal distance."""
    own = family["member"].join(anchors, "attr").select("cluster_id", "concept", F.col("d_lit").cast("int"), F.lit(0).alias("d_sem"))
    return {"member": family["member"], "halo": least_halo(family["halo"].unionByName(own))}


def cluster_stats(members: DataFrame) -> DataFrame:
    """``n_clusters, n_members, largest, n_overlapping`` of a member table."""
    sizes = members.groupBy("cluster_id").agg(F.count(F.lit(1)).alias("size"))
    shared = members.groupBy("attr").agg(F.count_distinct("cluster_id").alias("n")).where("n > 1")
    top = sizes.agg(F.count(F.lit(1)).alias("n_clusters"), F.sum("size").alias("n_members"), F.max("size").cast("long").alias("largest"))
    return top.crossJoin(shared.agg(F.count(F.lit(1)).alias("n_overlapping")))
