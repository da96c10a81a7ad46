"""Arriving schemas as a stream: each micro-batch is integrated into a versioned state."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql.streaming import StreamingQuery

from unischema.config import DEFAULT, Config
from unischema.plans.incremental import StateStore

ARRIVAL = "schema_id string, attr string"


def read_arrivals(spark: SparkSession, path: str, files_per_batch: int = 1) -> DataFrame:
    """Parquet files of ``schema_id, attr`` as they arrive."""
    return spark.readStream.schema(ARRIVAL).option("maxFilesPerTrigger", files_per_batch).parquet(path)


def integrate_stream(source: DataFrame, state_path: str, checkpoint: str, h1: DataFrame | None = None, cfg: Config = DEFAULT, available_now: bool = True) -> StreamingQuery:
    """Start the query; the store skips micro-batches that it has already recorded."""
    store = StateStore(source.sparkSession, state_path)
    writer = source.writeStream.foreachBatch(lambda batch, number: store.apply(number, batch, h1, cfg)).option("checkpointLocation", checkpoint)
    return (writer.trigger(availableNow=True) if available_now else writer).start()
