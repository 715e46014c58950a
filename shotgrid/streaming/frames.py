"""Structured Streaming over shots: frames as event-time windows, duplicates, sessions, residuals against the previous frame.

Each function takes a streaming (or static) DataFrame of shots and returns one; drain() runs a stream to its end and gives
its last result as a table, which is what a batch over the same shots gives."""

from __future__ import annotations

from collections.abc import Iterator

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from ..functions.storage import shared_dir
from ..operators.linear import encode
from ..sources.images import table

LATE = "1 hour"


def instant(ts: str = "ts") -> Column:
    """A time without zone as an instant of UTC: watermarks and windows take no zone-less times, and the session's zone must not matter."""
    inside = (F.hour(ts) * 3600 + F.minute(ts) * 60).cast("long") * 1_000_000 + (F.date_part(F.lit("SECONDS"), F.col(ts)) * 1_000_000).cast("long")
    return F.timestamp_micros(F.unix_date(F.to_date(ts)).cast("long") * 86_400_000_000 + inside)


def shots(df: DataFrame) -> DataFrame:
    """Event rows as shots: event_id, at (instant), row (beam), col (half hour of the day), sensor, range."""
    second = F.hour("ts") * 3600 + F.minute("ts") * 60 + F.floor(F.second("ts"))
    return df.select("event_id", instant("ts").alias("at"), (F.col("user_id") % 16).cast("int").alias("row"), F.floor(second / 1800).cast("int").alias("col"), (F.col("user_id") % 4).alias("sensor"), F.col("value").alias("range"), "event_type")


def source(spark: SparkSession, sf_dir: str, files: int = 4) -> DataFrame:
    """events as a file stream in order of time, one file a trigger; files are written one after the other, since a stream
    takes them by their time."""
    to = shared_dir(spark, "shots")
    e = table(spark, sf_dir, "events")
    cuts = e.select(instant().cast("double").alias("t")).approxQuantile("t", [i / files for i in range(1, files)], 0.01) if files > 1 else []
    at = instant().cast("double")
    for low, high in zip([None, *cuts], [*cuts, None]):
        part = e.where((at >= low) if low is not None else F.lit(True)).where((at < high) if high is not None else F.lit(True))
        part.coalesce(1).sortWithinPartitions("ts", "event_id").write.mode("append").parquet(to)
    return spark.readStream.schema(e.schema).option("maxFilesPerTrigger", 1).parquet(to)


def day(c: Column) -> Column:
    return F.floor(F.unix_seconds(c) / 86_400)


def frames(s: DataFrame, d: float = 0.1) -> DataFrame:
    """One frame a day: shots, sum of codes, first shot. The watermark closes a frame an hour after its end."""
    w = F.window("at", "1 day")
    got = s.withWatermark("at", LATE).where("range > 0 and range <= 75").withColumn("code", encode("range", d)).groupBy(w).agg(F.count(F.lit(1)).alias("n"), F.sum("code").alias("total"), F.min("event_id").alias("first"))
    return got.select(day(F.col("window.start")).alias("day"), "n", "total", "first")


def sliding(s: DataFrame) -> DataFrame:
    got = s.withWatermark("at", LATE).groupBy(F.window("at", "2 days", "1 day")).agg(F.count(F.lit(1)).alias("n"), F.round(F.avg("range"), 6).alias("mean"))
    return got.select(day(F.col("window.start")).alias("day"), "n", "mean")


def sessions(s: DataFrame, gap: str = "6 hours") -> DataFrame:
    """Bursts of a sensor that end after `gap` without a shot."""
    got = s.withWatermark("at", LATE).groupBy("sensor", F.session_window("at", gap)).agg(F.count(F.lit(1)).alias("n"))
    return got.select("sensor", F.unix_micros("session_window.start").alias("start"), F.unix_micros("session_window.end").alias("end"), "n")


def deduplicated(s: DataFrame) -> DataFrame:
    """Replayed shots of the same id within the watermark count once; then shots by type."""
    return s.withWatermark("at", LATE).dropDuplicatesWithinWatermark(["event_id"])


def calibrated(s: DataFrame, beams: DataFrame) -> DataFrame:
    """Stream-static join with the beam table (row, hs, dz), which is broadcast."""
    return s.join(F.broadcast(beams), "row").select("event_id", "row", (F.col("range") * F.col("dz")).alias("z"), (F.col("range") * F.col("hs")).alias("ground"))


def with_poses(s: DataFrame, poses: DataFrame, within: str = "30 minutes") -> DataFrame:
    """Stream-stream interval join: shots with the poses of their sensor (sensor, pose_at, heading) at most `within` before them."""
    a, p = s.withWatermark("at", LATE), poses.withWatermark("pose_at", LATE)
    return a.alias("s").join(p.alias("p"), F.expr(f"s.sensor = p.sensor and p.pose_at <= s.at and p.pose_at >= s.at - interval {within}")).select("s.event_id", "s.at", "p.pose_at", "p.heading")


def prev_deltas(s: DataFrame, d: float = 0.1) -> DataFrame:
    """Code of each shot minus the last one of the same pixel, kept in the state of the pixel, in order of time within a trigger."""

    def run(key: tuple, parts: Iterator, state: GroupState) -> Iterator:
        import pandas as pd

        x = pd.concat(list(parts)).sort_values(["at", "event_id"])
        last = state.get[0] if state.exists else 0
        before = [last, *x["code"].tolist()[:-1]]
        state.update((int(x["code"].iloc[-1]),))
        yield pd.DataFrame({"event_id": x["event_id"].to_numpy(), "delta": x["code"].to_numpy() - before})

    coded = s.where("range > 0 and range <= 75").select("event_id", "at", "row", "col", encode("range", d).alias("code"))
    return coded.groupBy("row", "col").applyInPandasWithState(run, "event_id long, delta long", "last long", "append", GroupStateTimeout.NoTimeout)


def drain(stream: DataFrame, mode: str = "complete") -> DataFrame:
    """Runs a stream over all that is there, trigger by trigger. complete, update: the last trigger's table; append: all of them.

    Batches are written under their number, so a batch that is run again after a failure replaces itself."""
    spark, out = stream.sparkSession, shared_dir(stream.sparkSession, "stream")
    last: list[int] = []

    def write(df: DataFrame, n: int) -> None:
        df.write.mode("overwrite").parquet(f"{out}/batch={n}")
        last.append(n)

    # One state store for each shuffle partition: a small stream needs few.
    stream.writeStream.outputMode(mode).option("checkpointLocation", shared_dir(spark, "stream-check")).trigger(availableNow=True).foreachBatch(write).start().awaitTermination()
    got = spark.read.schema(stream.schema)
    if not last:
        return spark.createDataFrame([], stream.schema)
    return got.parquet(f"{out}/batch={max(last)}") if mode == "complete" else got.parquet(*(f"{out}/batch={n}" for n in sorted(set(last))))
