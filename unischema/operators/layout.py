"""Storage layout: bucket addresses, clustered files, pruned lookups and what a scan touches."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from unischema.functions.text import bucket_address


def addresses(attrs: DataFrame, seed: int = 13, length: int = 10_000, base: int = 1_000_000) -> DataFrame:
    """``attr, offset, address`` in one bucket."""
    total = bucket_address(F.col("attr"), seed, length, base)
    return attrs.select("attr", (total - base).alias("offset"), total.alias("address"))


def assign_buckets(members: DataFrame, seed: int = 13, length: int = 10_000, base: int = 1_000_000) -> DataFrame:
    """One bucket per cluster: ``cluster_id, attr, bucket, address``.

    Buckets are numbered by the order of cluster ids through range partitions, each with its own
    block of numbers, so no task sees all clusters.
    """
    ids = members.select("cluster_id").distinct().repartitionByRange("cluster_id").sortWithinPartitions("cluster_id").withColumn("bucket", F.monotonically_increasing_id())
    from unischema.functions.lineage import cut

    placed = members.join(cut(ids), "cluster_id")
    return placed.select("cluster_id", "attr", "bucket", bucket_address(F.col("attr"), seed, length, F.lit(base) + F.col("bucket") * length).alias("address"))


def write_clustered(df: DataFrame, cluster_col: str, path: str, files: int = 16) -> None:
    """Rows of a cluster together: same file, consecutive rows, so row-group statistics prune."""
    df.repartition(files, cluster_col).sortWithinPartitions(cluster_col).write.mode("overwrite").parquet(path)


def write_bucketed(df: DataFrame, cluster_col: str, table: str, path: str, buckets: int = 16) -> None:
    """The same as a bucketed table at ``path``, for joins without a shuffle on that side."""
    df.write.mode("overwrite").bucketBy(buckets, cluster_col).sortBy(cluster_col).option("path", path).saveAsTable(table)


def write_plain(df: DataFrame, path: str, files: int = 16) -> None:
    """The random layout to compare with: rows dealt out without regard to clusters."""
    df.repartition(files).write.mode("overwrite").parquet(path)


def lookup(df: DataFrame, column: str, keys: list) -> DataFrame:
    """Rows of a few keys; the filter reaches the scan."""
    return df.where(F.col(column).isin(keys))


def io_cost(df: DataFrame, cluster_col: str) -> DataFrame:
    """Per cluster, the files that hold its rows: ``cluster, files, rows``."""
    return df.withColumn("file", F.input_file_name()).groupBy(F.col(cluster_col).alias("cluster")).agg(F.count_distinct("file").alias("files"), F.count(F.lit(1)).alias("rows"))


def rank_in_cluster(members: DataFrame) -> DataFrame:
    """Offsets as plain ranks, the collision-free alternative to hashing inside a bucket."""
    return members.withColumn("place", F.row_number().over(Window.partitionBy("cluster_id").orderBy("attr")))
