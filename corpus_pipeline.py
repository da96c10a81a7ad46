"""The corpus pipeline: language, exact copies, near copies, contamination, then packing.

Each stage takes ``(spark, docs, sf_dir)`` and gives what it keeps, with the columns of ``docs``; the
last gives packed pieces. Nulls, empty tables, ties and extra columns are handled as each operator's
module states: extra columns pass through all filters and end at the packing.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from unischema.llm import decontamination, exact_dedup, language_id, near_dedup, packing
from unischema.llm.common import Workspace, cut, read_table

STAGES = [
    ("language_id", language_id.stage),
    ("exact_dedup", exact_dedup.stage),
    ("minhash_near_dedup", near_dedup.stage),
    ("benchmark_decontamination", decontamination.stage),
    ("best_fit_packing", packing.stage),
]

#: SQL can express neither the fitted language model nor the tokens; tests use brute force instead.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over the table of documents. Each result is written for the next stage and deleted as
    soon as the one after it is written, also when a stage fails."""
    docs, space = read_table(spark, sf_dir, "documents"), Workspace(spark)
    try:
        for number, (_, stage) in enumerate(STAGES[:-1], 1):
            docs = space.cut(stage(spark, docs, sf_dir))
            if number > 1:
                space.drop(number - 1)
        return cut(STAGES[-1][1](spark, docs, sf_dir))
    finally:
        space.clear()
