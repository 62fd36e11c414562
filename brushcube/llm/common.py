"""Shared helpers of the training-data operators: input tables, word rules and hand-over tables."""

from __future__ import annotations

import tempfile
import uuid
from collections.abc import Iterator
from contextlib import contextmanager

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import StructType

#: Java patterns of the two word rules used by the operators.
SPACED_WORD = r"[^\x20\x09-\x0D]+"
LETTER_WORD = r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+"
_UPPER, _LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """A given table, read by Spark (so any store that Spark can open will do)."""
    return spark.read.parquet(f"{sf_dir.rstrip('/')}/{name}.parquet")


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share: spark.checkpoint.dir, else the one that the session's context has been given."""
    found = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not found and spark.sparkContext.master.split("[")[0] == "local":  # driver and executors are one process
        spark.sparkContext.setCheckpointDir(tempfile.mkdtemp(prefix="brushcube-"))
        found = spark.sparkContext.getCheckpointDir()
    if not found:
        raise ValueError("spark.checkpoint.dir names no shared folder")
    return found.rstrip("/")


def new_folder(spark: SparkSession, name: str) -> str:
    return f"{shared_dir(spark)}/{name}-{uuid.uuid4().hex}"


@contextmanager
def settings(spark: SparkSession, conf: dict[str, str]) -> Iterator[None]:
    """Run-time settings of the session while a table is written; former values come back."""
    former = {k: spark.conf.get(k) for k in conf}
    try:
        for k, v in conf.items():
            spark.conf.set(k, v)
        yield
    finally:
        for k, v in former.items():
            spark.conf.set(k, v)


def hand_over(df: DataFrame, name: str, by: str | None = None, batch: int | None = None) -> DataFrame:
    """Write ``df`` to the shared folder and read it back: lineage ends there, and lost executors cost nothing. The shuffle files of the
    write go when it ends; the table goes by ``release``. ``by``: a boolean column, a folder for each of its values (see ``part_of``).
    ``batch``: rows that go to a Python worker at once, where rows are large."""
    spark = df.sparkSession
    path = new_folder(spark, name)
    conf = {"spark.sql.classic.shuffleDependency.fileCleanup.enabled": "true"} | ({"spark.sql.execution.arrow.maxRecordsPerBatch": str(batch)} if batch else {})
    with settings(spark, conf):
        (df.write.partitionBy(by) if by else df.write).parquet(path)
    out = spark.read.schema(df.schema).parquet(path)
    out.handed_over = path
    return out


def part_of(table: DataFrame, by: str, value: bool) -> DataFrame:
    """The rows of a table handed over ``by`` that column, as a table that can be released on its own."""
    spark, schema = table.sparkSession, [f for f in table.schema if f.name != by]
    path = f"{table.handed_over}/{by}={str(value).lower()}"
    fs, p = _fs(spark, path)
    if not fs.exists(p):
        fs.mkdirs(p)
    out = spark.read.schema(StructType(schema)).parquet(path)
    out.handed_over = path
    return out


def release(*tables: DataFrame) -> None:
    """Delete tables that ``hand_over`` wrote, after their last reader."""
    for t in tables:
        if path := getattr(t, "handed_over", None):
            fs, p = _fs(t.sparkSession, path)
            fs.delete(p, True)


def _fs(spark: SparkSession, path: str):
    p = spark._jvm.org.apache.hadoop.fs.Path(path)
    return p.getFileSystem(spark._jsc.hadoopConfiguration()), p


def give_back() -> None:
    """At the end of a Python worker's task: memory that is free goes back to the system. Workers are kept for later tasks, whose peaks would come on top."""
    import ctypes

    import pyarrow as pa

    pa.default_memory_pool().release_unused()
    if trim := getattr(ctypes.CDLL(None), "malloc_trim", None):  # glibc has it
        trim(0)


def ascii_lower(col: Column) -> Column:
    """Lower-case A-Z and nothing else. Pure ASCII texts take the vectorised path."""
    return F.when(F.octet_length(col) == F.char_length(col), F.lower(col)).otherwise(F.translate(col, _UPPER, _LOWER))


def words_of(col: Column, pattern: str) -> Column:
    """All words of a text as an array; a null text has none."""
    return F.coalesce(F.regexp_extract_all(col, F.lit(pattern), F.lit(0)), F.array().cast("array<string>"))
