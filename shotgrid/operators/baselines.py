"""Baselines re-created from public descriptions: octree occupancy, 16-bit image filters, field-wise differences."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .measures import entropy_h0


def raw(px: DataFrame) -> DataFrame:
    """Uncompressed cost: 32 bits for every range."""
    return px.agg(F.lit("raw").alias("method"), F.count(F.lit(1)).alias("n_valid"), (F.count("range") * 32).alias("bits"), (F.count("range") * 32 / F.count(F.lit(1))).alias("bpp"))


def voxels(points: DataFrame, depth: int, side: float) -> DataFrame:
    """Occupied leaf cells (frame_id, key) of a cube of the given side around the origin; key interleaves the bits of x, y, z."""
    unit = side / (1 << depth)
    q = {c: F.greatest(F.lit(0), F.least(F.lit((1 << depth) - 1), F.floor((F.col(c) + F.lit(side / 2)) / F.lit(unit)))).cast("long") for c in "xyz"}
    p = points.select("frame_id", *(q[c].alias(c) for c in "xyz"))
    bit = lambda c, i: F.shiftleft(F.shiftright(F.col(c), i).bitwiseAND(F.lit(1)), 3 * i + "xyz".index(c))
    key = reduce(lambda a, b: a.bitwiseOR(b), [bit(c, i) for c in "xyz" for i in range(depth)])
    return p.select("frame_id", key.alias("key")).distinct()


def octree_occupancy(cells: DataFrame, depth: int) -> DataFrame:
    """(frame_id, level, key, byte) of every inner node: bits of its occupied children, level by level from the leaves."""
    out, at = None, cells
    for level in range(depth - 1, -1, -1):
        at = at.select("frame_id", F.shiftright("key", 3).alias("parent"), F.expr("shiftleft(1, cast(key & 7 as int))").alias("bit")).groupBy("frame_id", F.col("parent").alias("key")).agg(F.bit_or("bit").cast("long").alias("byte"))
        rows = at.select("frame_id", F.lit(level).alias("level"), "key", "byte")
        out = rows if out is None else out.unionByName(rows)
    return out


def octree_entropy_ctx(nodes: DataFrame) -> DataFrame:
    """Entropy of the occupancy bytes given the number of children of the parent: an equi-join of each level with the one above."""
    above = nodes.select("frame_id", (F.col("level") + 1).alias("level"), F.col("key").alias("_up"), F.bit_count("byte").alias("ctx"))
    n = nodes.withColumn("_up", F.shiftright("key", 3)).join(above, ["frame_id", "level", "_up"], "left").withColumn("ctx", F.coalesce("ctx", F.lit(0)))
    per = entropy_h0(n, ["ctx"], "byte")
    return per.agg(F.round(F.sum(F.col("h0") * F.col("n_valid")) / F.sum("n_valid"), 5).alias("h_ctx"), F.sum("n_valid").alias("nodes"))


def octree_prev_ctx(nodes: DataFrame) -> DataFrame:
    """Entropy of the occupancy bytes given whether the frame before has the same node, and its byte's number of children."""
    before = nodes.select((F.col("frame_id") + 1).alias("frame_id"), "level", "key", F.bit_count("byte").alias("ctx"))
    n = nodes.join(before, ["frame_id", "level", "key"], "left").withColumn("ctx", F.coalesce("ctx", F.lit(0)))
    per = entropy_h0(n, ["ctx"], "byte")
    return per.agg(F.round(F.sum(F.col("h0") * F.col("n_valid")) / F.sum("n_valid"), 5).alias("h_ctx"), F.sum("n_valid").alias("nodes"))


def octree_entropy(nodes: DataFrame, points: int) -> DataFrame:
    """Order-0 rate of the occupancy bytes in bits for each original point."""
    return entropy_h0(nodes, column="byte").select(F.round(F.col("h0") * F.col("n_valid") / points, 5).alias("bpp"), F.col("n_valid").alias("nodes"))


def png_filters(px: DataFrame, scale: float) -> DataFrame:
    """Sum of absolute 16-bit filter residuals for each row of pixels and filter (none, left, up); the smallest is chosen by the coder."""
    v = px.select("frame_id", "row", "col", F.least(F.lit(65535), F.floor(F.col("range") * F.lit(float(scale)) + F.lit(0.5))).cast("long").alias("v"))
    row, col = Window.partitionBy("frame_id", "row").orderBy("col"), Window.partitionBy("frame_id", "col").orderBy("row")
    v = v.withColumn("l", F.coalesce(F.lag("v").over(row), F.lit(0))).withColumn("u", F.coalesce(F.lag("v").over(col), F.lit(0)))
    return v.groupBy("frame_id", "row").agg(F.sum("v").alias("none"), F.sum(F.abs(F.col("v") - F.col("l"))).alias("left"), F.sum(F.abs(F.col("v") - F.col("u"))).alias("up"))


def fieldwise_delta(points: DataFrame, scale: float, order: list[str]) -> DataFrame:
    """Per-axis differences to the previous point in scan order, on integers."""
    q = points.select("frame_id", *order, *(F.floor(F.col(c) / F.lit(scale) + F.lit(0.5)).cast("long").alias(c) for c in "xyz"))
    w = Window.partitionBy("frame_id").orderBy(*order)
    return q.select("frame_id", *order, *((F.col(c) - F.coalesce(F.lag(c).over(w), F.lit(0))).alias(f"d{c}") for c in "xyz"))
