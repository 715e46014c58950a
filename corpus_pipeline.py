"""A corpus pipeline of five stages over `documents`: quality rules, exact dedup, near duplicates, secrets, packing.

Each stage takes (spark, docs, sf_dir), works on all that the stage before kept and returns the columns of documents; the
last returns the packed pieces. Rows with null ids or texts, empty tables and further columns pass as the operators define."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from shotgrid.llm import exact, jaccard, quality, secrets, tokens
from shotgrid.llm.common import shared_dir, table
from shotgrid.llm.queries import vocabulary


def quality_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the fixed limits or the learned rules reject go."""
    rules = quality.fit(docs, table(spark, sf_dir, "labels"))
    rows = docs.select(F.struct(*(F.col(f"`{c}`") for c in docs.columns)).alias("_row"), "doc_id", "text")
    kept = quality.quality_rules(rows, rules, keep=["_row"])
    # A filter pushed below the statistics would hold a copy of their expressions for each use; it isn't pushed past _at.
    return kept.select("_row", "kept", F.spark_partition_id().alias("_at")).where("kept and _at >= 0").select("_row.*")


def exact_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One row of each group of equal texts stays, that of the largest doc_id."""
    rows = exact.placed(docs, carry=True)
    kept = exact.marked(rows).where("kept").select("place")
    return rows.select("place", "row").join(kept, "place", "left_semi").select("row.*")


def near_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of each group of near duplicates the smallest doc_id stays."""
    groups = jaccard.jaccard_components(docs, k=4, num=85, den=100)
    return docs.join(groups.where("doc_id <> component_id").select("doc_id").distinct(), "doc_id", "left_anti").select(*docs.columns)


def secret_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Secrets are masked; all documents stay."""
    return secrets.redact(docs, secrets.fit(docs))


def packing_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return tokens.pack(docs, vocabulary("word_bpe_49k.json"), width=4096, end_id=2)


STAGES = [("quality rules", quality_stage), ("exact dedup", exact_stage), ("n-gram Jaccard join", near_stage), ("secret scans", secret_stage), ("packing", packing_stage)]
#: The learned and the tokenising stages have no SQL; tests/llm/test_pipeline.py holds every stage and run() against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for n, (_, stage) in enumerate(STAGES):
        to = shared_dir(spark, f"pipeline-{n}")
        stage(spark, docs, sf_dir).write.parquet(to)
        docs = spark.read.parquet(to)
    return docs
