"""Exact deduplication (operator 1): stateful streaming over digests, with a check of the bytes on hits."""

from __future__ import annotations

import hashlib

import pyarrow as pa
import pyarrow.compute as pc
from pyspark.errors import AnalysisException
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import shared_dir, ship, stored

STORE = "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider"


DIGESTS = "doc_id long, place string, sha string, digest string"


def folded(docs: DataFrame, digest_bytes: int = 32, text: bool = False) -> DataFrame:
    """doc_id, place (file and row), sha, digest (its first digest_bytes) and, if asked, the text with A-Z lower-cased."""
    ship(docs.sparkSession)

    def run(batches):
        for b in batches:
            low = pc.ascii_lower(b.column("text"))
            shas = [hashlib.sha256(t.as_buffer() if t.is_valid else b"").hexdigest() for t in low]
            cols = [b.column("doc_id"), b.column("place"), pa.array(shas, pa.string()), pa.array([s[: 2 * digest_bytes] for s in shas], pa.string())]
            yield pa.RecordBatch.from_arrays(cols + [low.cast(pa.string())] * text, ["doc_id", "place", "sha", "digest"] + ["norm"] * text)

    return docs.mapInArrow(run, "doc_id long, place string, sha string, digest string" + ", norm string" * text)


def keyed_state(spark: SparkSession, path: str, files_per_trigger: int) -> DataFrame:
    """Streams the digests under path through disk-backed keyed state that never expires; its last rows, one per digest:
    digest, keeper (doc_id and place of the row that stays), size."""
    out, check = shared_dir(spark, "exact-state"), shared_dir(spark, "exact-checkpoint")
    store = "spark.sql.streaming.stateStore"
    # Many small stores: none sets disk aside beforehand, all of an executor share one bound of memory, and those of an
    # ended query are soon unloaded.
    new = {f"{store}.providerClass": STORE, f"{store}.rocksdb.boundedMemoryUsage": "true", f"{store}.rocksdb.maxMemoryUsageMB": "96", f"{store}.rocksdb.allowFAllocate": "false", f"{store}.maintenanceInterval": "10s"}
    old = {k: spark.conf.get(k, None) for k in new}
    for k, v in new.items():
        spark.conf.set(k, v)
    try:
        digests = spark.readStream.schema(DIGESTS).option("maxFilesPerTrigger", files_per_trigger).parquet(path)
        state = digests.groupBy("digest").agg(F.max(F.struct("doc_id", "place")).alias("keeper"), F.count(F.lit(1)).alias("size"))
        query = (
            state.writeStream.outputMode("update")
            .foreachBatch(lambda df, n: df.write.mode("overwrite").parquet(f"{out}/batch={n}"))
            .option("checkpointLocation", check)
            .trigger(availableNow=True)
            .start()
        )
        query.awaitTermination()
    finally:
        for k, v in old.items():
            spark.conf.unset(k) if v is None else spark.conf.set(k, v)
    schema = "digest string, keeper struct<doc_id: long, place: string>, size long, batch int"
    spark.createDataFrame([], schema.rsplit(", ", 1)[0]).write.mode("append").parquet(f"{out}/batch=-1")
    # Sizes and keepers only grow from one trigger to the next, so the largest of each is the last.
    return spark.read.schema(schema).parquet(out).groupBy("digest").agg(F.max("keeper").alias("keeper"), F.max("size").alias("size"))


def placed(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", carry: bool = False) -> DataFrame:
    """doc_id, text and place of every row; carry adds the whole row as a struct named row.

    The place is the file and the row in it where docs is read from Parquet, even if it has a column named _metadata.
    Rows from elsewhere are written to the shared folder first and get their place there. A join of file rows with
    something that repeats them should be written out by the caller, since repeats have one place."""
    columns = [F.col(f"`{id_col}`").cast("long").alias("doc_id"), F.coalesce(F.col(f"`{text_col}`"), F.lit("")).alias("text")]
    columns += [F.struct(*(F.col(f"`{c}`") for c in docs.columns)).alias("row")] * carry
    try:
        at = docs.metadataColumn("_metadata")
        out = docs.select(*columns, F.concat_ws("#", at["file_path"], F.lpad(at["row_index"].cast("string"), 12, "0")).alias("place"))
        out.schema  # noqa: B018 (resolves the columns now)
        return out
    except AnalysisException:
        kept = stored(docs.select(*columns), "exact-rows")
        at = kept.metadataColumn("_metadata")
        return kept.select(*kept.columns, F.concat_ws("#", at["file_path"], F.lpad(at["row_index"].cast("string"), 12, "0")).alias("place"))


def exact_dedup(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", digest_bytes: int = 32, files_per_trigger: int = 10_000) -> DataFrame:
    """One row for each input row: doc_id, keep_id, group_size, kept, text_sha256, place.

    Texts are equal when they are after lower-casing A-Z only; null counts as empty. The row with the largest doc_id
    stays; a null doc_id comes before all others. Rows that repeat a doc_id and text differ in place (file and row), and
    the last place stays, so exactly one row of a group is kept. An empty table gives no rows.

    The state holds digest, stable id and place only. Groups with more than one row are hits: their smallest and largest
    folded text are compared, summed up before the shuffle, so one large group is a row per task. Should texts differ
    under one digest, those groups are grouped by their whole text instead. docs may be any DataFrame (see placed)."""
    return marked(placed(docs, id_col, text_col), digest_bytes, files_per_trigger)


def marked(base: DataFrame, digest_bytes: int = 32, files_per_trigger: int = 10_000) -> DataFrame:
    """exact_dedup of rows that have a place."""
    spark, base = base.sparkSession, base.select("doc_id", "text", "place")
    path = shared_dir(spark, "exact-digests")
    folded(base, digest_bytes).write.option("compression", "zstd").parquet(path)
    digests = spark.read.schema(DIGESTS).parquet(path)
    state = stored(keyed_state(spark, path, files_per_trigger), "exact-groups")
    hits = state.where("size > 1").select("digest")
    checked = stored(folded(base, digest_bytes, text=True).select("digest", "norm").join(hits, "digest").groupBy("digest").agg((F.min("norm") != F.max("norm")).alias("differ")), "exact-checked")
    mixed = checked.where("differ").select("digest")
    groups = digests.join(state, "digest")
    columns = ["doc_id", F.col("keeper.doc_id").alias("keep_id"), F.col("size").alias("group_size"), (F.col("doc_id").eqNullSafe(F.col("keeper.doc_id")) & (F.col("place") == F.col("keeper.place"))).alias("kept"), F.col("sha").alias("text_sha256"), "place"]
    if not mixed.take(1):
        return groups.select(*columns)
    apart = folded(base, digest_bytes, text=True).join(mixed, "digest")
    exact = apart.groupBy("norm").agg(F.max(F.struct("doc_id", "place")).alias("keeper"), F.count(F.lit(1)).alias("size"))
    return groups.join(mixed, "digest", "left_anti").select(*columns).unionByName(apart.join(exact, "norm").select(*columns))
