"""The few user functions beyond SQL: a table function of grams and a grouped aggregate."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import DoubleType, IntegerType, StringType, StructField, StructType


class GramTable:
    """``gram_table(text, q)``: one row per gram with its place."""

    def eval(self, text: str, q: int):
        for i in range(len(text or "") - q + 1):
            yield text[i : i + q], i + 1


def register_udtf(spark: SparkSession) -> None:
    spark.udtf.register("gram_table", F.udtf(GramTable, returnType=StructType([StructField("gram", StringType()), StructField("pos", IntegerType())])))


@F.pandas_udf(DoubleType())
def spread(values: pd.Series) -> float:
    """Population standard deviation of a group."""
    return float(values.std(ddof=0))
