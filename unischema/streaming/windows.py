"""Streaming forms of the operators: watermarked windows, deduplication, joins, keyed state."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.streaming import StatefulProcessor, StatefulProcessorHandle
from pyspark.sql.types import LongType, StringType, StructField, StructType


def windowed_counts(events: DataFrame, width: str = "1 hour", slide: str | None = None, late: str = "10 minutes") -> DataFrame:
    """Events per window and type; rows later than the watermark are dropped."""
    window = F.window("ts", width, slide) if slide else F.window("ts", width)
    return events.withWatermark("ts", late).groupBy(window.alias("w"), "event_type").agg(F.count(F.lit(1)).alias("n"))


def sessions(events: DataFrame, gap: str = "30 minutes", late: str = "10 minutes") -> DataFrame:
    return events.withWatermark("ts", late).groupBy("user_id", F.session_window("ts", gap).alias("w")).agg(F.count(F.lit(1)).alias("n"))


def first_arrivals(schemas: DataFrame, late: str = "1 day") -> DataFrame:
    """Schemas that arrive again within the watermark are dropped: ``schema_id, ts, ...``."""
    return schemas.withWatermark("ts", late).dropDuplicatesWithinWatermark(["schema_id"])


def arriving_concepts(names: DataFrame, h1: DataFrame) -> DataFrame:
    """Arriving names with their one-hop neighbours: a stream joined with a stored table."""
    return names.join(h1, names["attr"] == h1["concept"]).select("schema_id", "attr", "neighbour")


def paired_events(views: DataFrame, purchases: DataFrame, within: str = "1 hour", late: str = "10 minutes") -> DataFrame:
    """Views with purchases of the same user within an interval after them: a stream-stream join."""
    v = views.withWatermark("ts", late).select(F.col("event_id").alias("view_id"), F.col("user_id").alias("v_user"), F.col("ts").alias("v_ts"))
    p = purchases.withWatermark("ts", late).select(F.col("event_id").alias("purchase_id"), F.col("user_id").alias("p_user"), F.col("ts").alias("p_ts"))
    on = F.expr(f"v_user = p_user AND p_ts >= v_ts AND p_ts <= v_ts + INTERVAL {within}")
    return v.join(p, on).select("view_id", "purchase_id")


class AttributeCounter(StatefulProcessor):
    """Counts, for each schema, the attributes seen so far over all micro-batches."""

    def init(self, handle: StatefulProcessorHandle) -> None:
        self.seen = handle.getMapState("seen", StructType([StructField("attr", StringType())]), StructType([StructField("n", LongType())]))

    def handleInputRows(self, key, rows: Iterator[pd.DataFrame], timerValues) -> Iterator[pd.DataFrame]:
        for batch in rows:
            for attr in batch["attr"]:
                n = self.seen.getValue((attr,))[0] if self.seen.containsKey((attr,)) else 0
                self.seen.updateValue((attr,), (n + 1,))
        yield pd.DataFrame({"schema_id": [key[0]], "n_attrs": [sum(1 for _ in self.seen.keys())]})

    def close(self) -> None:
        pass


def attributes_seen(arrivals: DataFrame) -> DataFrame:
    """``schema_id, n_attrs`` after each micro-batch, by keyed state (needs the RocksDB state store)."""
    return arrivals.groupBy("schema_id").transformWithStateInPandas(AttributeCounter(), "schema_id string, n_attrs long", "Update", "None")
