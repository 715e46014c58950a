"""Helpers that the text operators share: code shipping, shared folders, table access."""

from __future__ import annotations

import contextlib

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.shipping import ship  # noqa: F401 (the operators take it from here)
from ..functions.storage import shared_dir


def stored(df: DataFrame, name: str, codec: str = "zstd") -> DataFrame:
    """Write df to the shared folder and read it back: lineage ends there and lost executors lose nothing."""
    spark = df.sparkSession
    to = shared_dir(spark, name)
    df.write.option("compression", codec).parquet(to)
    return spark.read.schema(df.schema).parquet(to)


@contextlib.contextmanager
def small_batches(spark: SparkSession, records: int = 128):
    """Arrow batches of at most so many rows while a plan runs that carries texts beside each other or many times over."""
    key = "spark.sql.execution.arrow.maxRecordsPerBatch"
    old = spark.conf.get(key, None)
    spark.conf.set(key, str(records))
    try:
        yield
    finally:
        spark.conf.unset(key) if old is None else spark.conf.set(key, old)


@contextlib.contextmanager
def freed_shuffles(spark: SparkSession):
    """Shuffle files go when the write or action that needed them ends, not when the driver happens to collect garbage."""
    key = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"
    old = spark.conf.get(key, None)
    spark.conf.set(key, "true")
    try:
        yield
    finally:
        spark.conf.unset(key) if old is None else spark.conf.set(key, old)


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir.rstrip('/')}/{name}.parquet")


def id_text(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Only the two columns an operator reads; a null text counts as empty, other columns are not carried."""
    return docs.select(F.col(id_col).cast("long").alias("doc_id"), F.coalesce(F.col(text_col), F.lit("")).alias("text"))
