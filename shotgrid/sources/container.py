"""The compressed container as a sink and as a data source that decodes while it reads.

    sink(codec.encode(...), path)
    register(spark)
    spark.read.format("shotgrid").option("path", path).load().where("frame_id = 7 and row between 0 and 15")

Filters on frame_id, row and col become predicates on block keys and on file statistics, so other blocks are not decoded."""

from __future__ import annotations

from collections.abc import Iterator

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, EqualTo, Filter, GreaterThan, GreaterThanOrEqual, In, InputPartition, LessThan, LessThanOrEqual

from ..functions.shipping import ship
from ..operators import codec

READ = ["frame_id", "block_row", "block_col", "predictor", "model_id", "coder", "precision", "h", "w", "crc", "mask_bytes", "payload"]


def sink(container: DataFrame, path: str, frames_a_file: int = 64) -> None:
    """Container rows as Parquet folders of `frames_a_file` frames each, sorted by frame and block, so statistics of files and row groups can skip."""
    rows = container.withColumn("frames", F.floor(F.col("frame_id") / frames_a_file))
    rows.repartition("frames").sortWithinPartitions("frame_id", "block_row", "block_col").write.partitionBy("frames").option("compression", "none").mode("overwrite").parquet(path)


def register(spark) -> None:
    """Makes format("shotgrid") known. Filters only reach Python sources with this session setting."""
    ship(spark)
    spark.conf.set("spark.sql.python.filterPushdown.enabled", "true")
    spark.dataSource.register(ContainerSource)


def load(spark, path: str) -> DataFrame:
    return spark.read.parquet(path).select(*codec.NAMES)


class Box:
    """Least and largest frame, row and column that filters leave."""

    def __init__(self):
        self.low, self.high = {}, {}

    def take(self, f: Filter) -> bool:
        """Notes a filter; whether it could be used. All are checked again on the pixels."""
        if f.attribute[0] not in ("frame_id", "row", "col") if hasattr(f, "attribute") else True:
            return False
        c = f.attribute[0]
        if isinstance(f, (EqualTo, GreaterThan, GreaterThanOrEqual)):
            self.low[c] = max(self.low.get(c, f.value), f.value)
        if isinstance(f, (EqualTo, LessThan, LessThanOrEqual)):
            self.high[c] = min(self.high.get(c, f.value), f.value)
        if isinstance(f, In) and f.value:
            self.low[c], self.high[c] = max(self.low.get(c, min(f.value)), min(f.value)), min(self.high.get(c, max(f.value)), max(f.value))
        return isinstance(f, (EqualTo, GreaterThan, GreaterThanOrEqual, LessThan, LessThanOrEqual, In))


class Part(InputPartition):
    def __init__(self, file: str):
        self.value = file


class ContainerReader(DataSourceReader):
    def __init__(self, options):
        self.path, self.box = options["path"], Box()

    def pushFilters(self, filters: list[Filter]) -> Iterator[Filter]:
        for f in filters:
            self.box.take(f)
            yield f  # Spark checks every filter again on the decoded pixels

    def partitions(self):
        import pyarrow.dataset as ds

        return [Part(f) for f in sorted(ds.dataset(self.path.removeprefix("file:"), format="parquet", partitioning="hive").files)]

    def read(self, part: Part):
        import pyarrow.compute as pc
        import pyarrow.dataset as ds

        low, high = self.box.low, self.box.high
        keep = pc.field("predictor") != "frame"
        if "frame_id" in low:
            keep &= pc.field("frame_id") >= low["frame_id"]
        if "frame_id" in high:
            keep &= pc.field("frame_id") <= high["frame_id"]
        for c, key, size in (("row", "block_row", "h"), ("col", "block_col", "w")):
            if c in low:
                keep &= (pc.field(key) + 1) * pc.field(size) > low[c]
            if c in high:
                keep &= pc.field(key) * pc.field(size) <= high[c]
        for b in ds.dataset(part.value, format="parquet").to_batches(columns=READ, filter=keep, batch_size=256):
            if b.num_rows:
                yield codec.decode_rows(b.to_pylist())


class ContainerSource(DataSource):
    """Pixels of a container written by sink() with a linear predictor."""

    @classmethod
    def name(cls) -> str:
        return "shotgrid"

    def schema(self) -> str:
        return codec.PIXELS

    def reader(self, schema) -> ContainerReader:
        return ContainerReader(self.options)
