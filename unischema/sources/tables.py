"""Attribute sources: the catalog of the given tables, and schemas hidden in their rows."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from unischema.functions.lineage import cut

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def catalog(spark: SparkSession, sf_dir: str) -> DataFrame:
    """``schema_id, attr, ordinal, data_type, n_values``: every column of the tables, with the number of its values.

    One aggregate a table reads its rows; columns of tables without rows are there too, with 0 values.
    """
    parts = []
    for name in TABLES:
        own = table(spark, sf_dir, name)
        counts = own.agg(*[F.count(F.col(f"`{field.name}`")).alias(f"n{i}") for i, field in enumerate(own.schema.fields, 1)])
        cells = [
            F.struct(F.lit(field.name).alias("attr"), F.lit(i).alias("ordinal"), F.lit(field.dataType.simpleString()).alias("data_type"), F.col(f"n{i}").alias("n_values"))
            for i, field in enumerate(own.schema.fields, 1)
        ]
        parts.append(counts.select(F.lit(name).alias("schema_id"), F.inline(F.array(*cells))))
    return cut(reduce(DataFrame.unionByName, parts).coalesce(1))


def catalog_values() -> str:
    """The same pairs for an oracle, as SQL over DuckDB's own catalog of views."""
    names = ", ".join(f"'{t}'" for t in TABLES)
    return f"(SELECT table_name AS schema_id, column_name AS attr FROM information_schema.columns WHERE table_name IN ({names}))"


def token_schemas(spark: SparkSession, sf_dir: str, least: int = 4) -> DataFrame:
    """Each English document is a schema, its distinct words of ``least`` letters its attributes."""
    docs = table(spark, sf_dir, "documents").where("lang = 'en'")
    words = F.regexp_extract_all(F.lower("text"), F.lit("([a-z]+)"), F.lit(1))
    return docs.select(F.col("doc_id").alias("schema_id"), F.explode(F.array_distinct(F.filter(words, lambda w: F.length(w) >= least))).alias("attr"))


def token_sample(spark: SparkSession, sf_dir: str, least: int = 6, count: int = 5) -> DataFrame:
    """Words of at least ``least`` letters that occur ``count`` times or more in English documents."""
    docs = table(spark, sf_dir, "documents").where("lang = 'en'")
    words = docs.select(F.explode(F.regexp_extract_all(F.lower("text"), F.lit("([a-z]+)"), F.lit(1))).alias("attr"))
    return words.where(F.length("attr") >= least).groupBy("attr").count().where(F.col("count") >= count).select("attr")


TOKEN_SAMPLE_SQL = """
  SELECT attr FROM (SELECT unnest(regexp_extract_all(lower(text), '[a-z]+')) AS attr FROM documents WHERE lang = 'en')
  WHERE length(attr) >= 6 GROUP BY attr HAVING count(*) >= 5
"""


def word_schemas(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Each document of any language is a schema, all its distinct words its attributes."""
    words = F.regexp_extract_all(F.lower("text"), F.lit(r"(\p{L}+)"), F.lit(1))
    return table(spark, sf_dir, "documents").select(F.col("doc_id").alias("schema_id"), F.explode(F.array_distinct(words)).alias("attr"))


def all_tokens(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All distinct words of all documents, whatever their language, length and number."""
    return word_schemas(spark, sf_dir).select("attr").distinct()


ALL_TOKENS_SQL = r"SELECT DISTINCT unnest(regexp_extract_all(lower(text), '\p{L}+')) AS attr FROM documents"


def part_schemas(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Each brand is a schema, the names of its parts its attributes."""
    return table(spark, sf_dir, "part").select(F.col("p_brand").alias("schema_id"), F.col("p_name").alias("attr")).distinct()


def party_schemas(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Each nation is a schema, the names of its customers and suppliers its attributes."""
    nation = table(spark, sf_dir, "nation")
    customer = table(spark, sf_dir, "customer").select(F.col("c_nationkey").alias("n_nationkey"), F.col("c_name").alias("attr"))
    supplier = table(spark, sf_dir, "supplier").select(F.col("s_nationkey").alias("n_nationkey"), F.col("s_name").alias("attr"))
    return customer.unionByName(supplier).join(nation, "n_nationkey").select(F.col("n_name").alias("schema_id"), "attr").distinct()


def page_schemas(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Each web page is a schema, the words of its links its attributes."""
    links = F.regexp_extract_all("html", F.lit('href="/?([a-zA-Z]+)'), F.lit(1))
    return table(spark, sf_dir, "pages").select(F.col("page_id").alias("schema_id"), F.explode(F.array_distinct(links)).alias("attr"))


def turn_schemas(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Each turn is a schema, its distinct ASCII words its attributes."""
    words = F.regexp_extract_all(F.lower("text"), F.lit("([a-z]+)"), F.lit(1))
    rows = table(spark, sf_dir, "conversations")
    return rows.select(F.concat_ws(".", "conv_id", "turn").alias("schema_id"), F.explode(F.array_distinct(words)).alias("attr"))


def pool_attributes(schemas: DataFrame) -> DataFrame:
    """All distinct attributes with the number of schemas that hold them; null names are left out."""
    return schemas.where("attr IS NOT NULL").groupBy("attr").agg(F.count_distinct("schema_id").alias("n_schemas"))
