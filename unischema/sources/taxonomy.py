"""A knowledge base from the given tables: parts, names, brands, parties, nations, regions.

Concepts are triples (id, name, type); relations have six fields. The id of a concept is a number
made of its name's digest, so that the same name is one concept wherever it comes from.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from unischema.sources.tables import table


def concept_id(name: Column) -> Column:
    return F.conv(F.substring(F.md5(name), 1, 15), 16, 10).cast("long")


def trade_relations(spark: SparkSession, sf_dir: str, large: bool = False) -> DataFrame:
    """``sub_id, sub_name, sub_type, super_id, super_name, super_type``."""
    get = lambda name: table(spark, sf_dir, name)
    part, nation, region = get("part"), get("nation"), get("region")
    customer, supplier = get("customer"), get("supplier")
    instance = F.concat(F.lit("Part#"), "p_partkey")

    def rows(df: DataFrame, sub: Column | str, sub_type: str, sup: Column | str, sup_type: str) -> DataFrame:
        sub, sup = (F.col(c) if isinstance(c, str) else c for c in (sub, sup))
        return df.select(sub.alias("sub_name"), F.lit(sub_type).alias("sub_type"), sup.alias("super_name"), F.lit(sup_type).alias("super_type"))

    named_customer = customer.join(F.broadcast(nation), customer["c_nationkey"] == nation["n_nationkey"])
    named_supplier = supplier.join(F.broadcast(nation), supplier["s_nationkey"] == nation["n_nationkey"])
    parts = [
        rows(part, instance, "part", "p_name", "part name"),
        rows(part, instance, "part", "p_brand", "brand"),
        rows(part, instance, "part", "p_type", "part type"),
        rows(part, "p_name", "part name", F.element_at(F.split("p_name", " "), -1), "noun"),
        rows(part, "p_name", "part name", F.element_at(F.split("p_name", " "), 1), "modifier"),
        rows(named_customer, "c_name", "customer", "n_name", "nation"),
        rows(customer, "c_name", "customer", "c_mktsegment", "segment"),
        rows(named_supplier, "s_name", "supplier", "n_name", "nation"),
        rows(nation.join(F.broadcast(region), nation["n_regionkey"] == region["r_regionkey"]), "n_name", "nation", "r_name", "region"),
    ]
    if large:
        line = get("lineitem")
        name = F.concat(F.lit("Line#"), "l_orderkey", F.lit("."), "l_linenumber")
        order = F.concat(F.lit("Order#"), "l_orderkey")
        parts += [
            rows(line, name, "line", order, "order"),
            rows(line, name, "line", F.concat(F.lit("Part#"), "l_partkey"), "part"),
            rows(line.join(supplier, line["l_suppkey"] == supplier["s_suppkey"]), name, "line", "s_name", "supplier"),
            rows(get("orders").join(customer, F.col("o_custkey") == F.col("c_custkey")), F.concat(F.lit("Order#"), "o_orderkey"), "order", "c_name", "customer"),
        ]
    union = parts[0]
    for more in parts[1:]:
        union = union.unionByName(more)
    return union.distinct().select(concept_id(F.col("sub_name")).alias("sub_id"), "sub_name", "sub_type", concept_id(F.col("super_name")).alias("super_id"), "super_name", "super_type")


RELATIONS_SQL = """
  SELECT DISTINCT sub_name, sub_type, super_name, super_type FROM (
    SELECT 'Part#' || p_partkey AS sub_name, 'part' AS sub_type, p_name AS super_name, 'part name' AS super_type FROM part
    UNION ALL SELECT 'Part#' || p_partkey, 'part', p_brand, 'brand' FROM part
    UNION ALL SELECT 'Part#' || p_partkey, 'part', p_type, 'part type' FROM part
    UNION ALL SELECT p_name, 'part name', string_split(p_name, ' ')[-1], 'noun' FROM part
    UNION ALL SELECT p_name, 'part name', string_split(p_name, ' ')[1], 'modifier' FROM part
    UNION ALL SELECT c_name, 'customer', n_name, 'nation' FROM customer JOIN nation ON c_nationkey = n_nationkey
    UNION ALL SELECT c_name, 'customer', c_mktsegment, 'segment' FROM customer
    UNION ALL SELECT s_name, 'supplier', n_name, 'nation' FROM supplier JOIN nation ON s_nationkey = n_nationkey
    UNION ALL SELECT n_name, 'nation', r_name, 'region' FROM nation JOIN region ON n_regionkey = r_regionkey)
"""
EDGES_SQL = f"SELECT DISTINCT sub_name AS sub, super_name AS sup FROM ({RELATIONS_SQL}) WHERE sub_name <> super_name"
H1_SQL = f"SELECT sub AS concept, sup AS neighbour FROM ({EDGES_SQL}) UNION SELECT sup, sub FROM ({EDGES_SQL})"


def page_relations(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Pages below hosts, hosts below top domains: a knowledge base of another shape."""
    host = F.regexp_extract("url", r"^[a-z]+://([^/]+)", 1)
    rows = table(spark, sf_dir, "pages").select("url", host.alias("host"))
    return rows.select(F.col("url").alias("sub_name"), F.lit("page").alias("sub_type"), F.col("host").alias("super_name"), F.lit("host").alias("super_type")).unionByName(
        rows.select(F.col("host").alias("sub_name"), F.lit("host").alias("sub_type"), F.element_at(F.split("host", r"\."), -1).alias("super_name"), F.lit("domain").alias("super_type"))
    ).distinct()
