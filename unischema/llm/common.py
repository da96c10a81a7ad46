"""Shared pieces of the corpus operators: lineage cuts, text folding, column-level ``let``."""

from __future__ import annotations

import string
import tempfile
import uuid

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: ASCII letters and digits plus everything beyond ASCII; all other ASCII separates words.
WORD = r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+"
#: The complement of WORD.
GAP = r"[\x00-\x2F\x3A-\x60\x7B-\x7F]+"
#: Labels may be learnt only from rows whose remainder is not this one.
HELD_OUT = 1


def read_table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_folder(spark: SparkSession) -> str:
    """The session's checkpoint folder, from ``spark.checkpoint.dir``.

    Only where that is unset and everything runs on one machine (tests) is a temporary folder made;
    on a cluster a local folder would be lost with its machine, so that is an error.
    """
    sc = spark.sparkContext
    if sc._jsc.sc().getCheckpointDir().isEmpty():
        shared = spark.conf.get("spark.checkpoint.dir", None)
        if shared is None and not (sc.master == "local" or sc.master.startswith("local[")):
            raise RuntimeError("set spark.checkpoint.dir to a folder that all executors share")
        sc.setCheckpointDir(shared or tempfile.mkdtemp(prefix="unischema-checkpoint-"))
    return sc._jsc.sc().getCheckpointDir().get()


def cut(df: DataFrame) -> DataFrame:
    """Materialise ``df`` in the shared checkpoint folder, so that a lost executor loses no work."""
    shared_folder(df.sparkSession)
    return df.checkpoint()


#: Rows of one Arrow batch; whole texts are long, and the default of ten thousand fills much memory.
ARROW_ROWS = 1000


def arrow_ready(spark: SparkSession) -> None:
    """Ask for smaller Arrow batches in this session, unless they are small already."""
    key = "spark.sql.execution.arrow.maxRecordsPerBatch"
    if not 0 < int(spark.conf.get(key)) <= ARROW_ROWS:
        spark.conf.set(key, str(ARROW_ROWS))


class Workspace:
    """Intermediate tables of one run, written as Parquet in the shared checkpoint folder.

    Compressed and pruned by column, unlike checkpoints; deleted one by one by ``drop`` or all by ``clear``.
    """

    def __init__(self, spark: SparkSession) -> None:
        self.spark = spark
        self.path = f"{shared_folder(spark)}/unischema-{uuid.uuid4().hex}"
        self.count = 0

    def cut(self, df: DataFrame) -> DataFrame:
        self.count += 1
        df.write.parquet(f"{self.path}/{self.count}")
        return self.spark.read.schema(df.schema).parquet(f"{self.path}/{self.count}")

    def drop(self, number: int) -> None:
        """Delete the table that was the ``number``-th to be cut."""
        self._delete(f"{self.path}/{number}")

    def clear(self) -> None:
        self._delete(self.path)

    def _delete(self, name: str) -> None:
        path = self.spark._jvm.org.apache.hadoop.fs.Path(name)
        path.getFileSystem(self.spark._jsc.hadoopConfiguration()).delete(path, True)


def let(value: Column, body) -> Column:
    """``body(value)`` with ``value`` evaluated once per row, also inside lambdas."""
    return F.get(F.transform(F.array(value), body), F.lit(0))


def fold_ascii(text: Column) -> Column:
    """Lower-case A-Z only; null counts as empty. ASCII texts take the fast path of ``lower``."""
    text = F.coalesce(text, F.lit(""))
    return F.when(F.length(text) == F.octet_length(text), F.lower(text)).otherwise(
        F.translate(text, string.ascii_uppercase, string.ascii_lowercase)
    )


def words(text: Column) -> Column:
    """The array of folded words of ``text``."""
    return F.regexp_extract_all(fold_ascii(text), F.lit(WORD), F.lit(0))


def held_out(doc_id: Column) -> Column:
    """Whether a document is kept away from every fit: crc32 of its id as text, modulo 3."""
    return F.coalesce(F.crc32(F.coalesce(doc_id.cast("string"), F.lit("")).cast("binary")) % 3 == HELD_OUT, F.lit(False))


#: Ids up to which a list of dropped documents is broadcast; a longer one is joined by a shuffle.
DROPPED_ROWS = 500_000


def drop_rows(docs: DataFrame, dropped: DataFrame) -> DataFrame:
    """``docs`` without the rows whose ``doc_id`` is in ``dropped`` (null-safe)."""
    gone = cut(dropped.select(F.col("doc_id").alias("gone_id")).distinct())
    if gone.count() <= DROPPED_ROWS:
        gone = F.broadcast(gone)
    return docs.join(gone, docs["doc_id"].eqNullSafe(gone["gone_id"]), "left_anti")
