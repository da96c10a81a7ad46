"""Cutting the lineage of iterative plans in storage that all executors share."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession


def shared_folder(spark: SparkSession) -> str:
    """The checkpoint folder of ``spark.checkpoint.dir``; where that is unset, a temporary one on a single
    machine (tests) and an error on a cluster, whose machines would not see each other's files."""
    sc = spark.sparkContext
    if sc._jsc.sc().getCheckpointDir().isEmpty():
        shared = spark.conf.get("spark.checkpoint.dir", None)
        if shared is None and not (sc.master == "local" or sc.master.startswith("local[")):
            raise RuntimeError("set spark.checkpoint.dir to a folder that all executors share")
        sc.setCheckpointDir(shared or tempfile.mkdtemp(prefix="unischema-checkpoint-"))
    return sc._jsc.sc().getCheckpointDir().get()


def scratch(spark: SparkSession) -> str:
    """A new folder in the shared checkpoint folder, for tables that are written to be read again."""
    return f"{shared_folder(spark)}/unischema-{uuid.uuid4().hex}"


def cut(df: DataFrame) -> DataFrame:
    """Checkpoint ``df`` in the shared folder."""
    shared_folder(df.sparkSession)
    return df.checkpoint()


def renamed(df: DataFrame, **names: str) -> DataFrame:
    """Columns chosen and renamed: ``renamed(df, new="old")``."""
    return df.selectExpr(*[f"`{old}` AS `{new}`" for new, old in names.items()])
