"""The flagship plan: the catalog of the given tables integrated into one global schema."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from unischema.config import DEFAULT, Config
from unischema.operators.verify import profile_values
from unischema.plans.batch import Integration, integrate_batch
from unischema.sources.tables import TABLES, catalog, table


def catalog_integration(spark: SparkSession, sf_dir: str, cfg: Config | None = None, with_values: bool = True) -> Integration:
    """Literal integration of the catalog, verified by the values of all tables."""
    schemas = catalog(spark, sf_dir).select("schema_id", "attr")
    profile = profile_values({name: table(spark, sf_dir, name) for name in TABLES}) if with_values else None
    return integrate_batch(schemas, None, cfg or DEFAULT.but(semantic=False), profile)


def integrate_catalog(spark: SparkSession, sf_dir: str) -> DataFrame:
    """``schema_id, attr, part_id, global_attr`` of every column."""
    return catalog_integration(spark, sf_dir).mapping
