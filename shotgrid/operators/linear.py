"""Quantisation, the linear predictors and their closed-form inverses, all as window expressions over codes.

Decoding needs no recursion: with the left predictor codes are running sums of deltas along a row; with the
three-neighbour one, row differences are running sums of deltas down a column (restarted after a void pixel). A void pixel
filled from the left differs by 0 from its left neighbour, so the three-neighbour predictor reads valid pixels only."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

ROW = ["frame_id", "row"]
COL = ["frame_id", "col"]


def encode(value: Column | str, d: float) -> Column:
    return F.floor((F.col(value) if isinstance(value, str) else value) / F.lit(float(d)) + F.lit(0.5)).cast("long")


def decode(code: Column | str, d: float) -> Column:
    return (F.col(code) if isinstance(code, str) else code).cast("double") * F.lit(float(d))


def codes(px: DataFrame, d: float, *keep: str) -> DataFrame:
    return px.select("frame_id", "row", "col", *keep, encode("range", d).alias("code"))


def blocked(df: DataFrame, block: tuple[int, int] | None) -> tuple[DataFrame, list[str], list[str]]:
    """Partition keys of rows and columns; with block=(h, w) every block starts anew."""
    if block is None:
        return df, ROW, COL
    df = df.withColumn("block_row", F.floor(F.col("row") / block[0]).cast("int")).withColumn("block_col", F.floor(F.col("col") / block[1]).cast("int"))
    return df, [*ROW, "block_col"], [*COL, "block_row"]


def delta_none(px: DataFrame) -> DataFrame:
    return px.withColumn("delta", F.col("code"))


def delta_left(px: DataFrame, row_wrap: bool = False, block: tuple[int, int] | None = None) -> DataFrame:
    """Code minus the last valid code to the left; 0 at the start of a row, or the previous row's last with row_wrap."""
    px, rows, _ = blocked(px, block)
    w = Window.partitionBy("frame_id").orderBy("row", "col") if row_wrap else Window.partitionBy(*rows).orderBy("col")
    return px.withColumn("delta", F.col("code") - F.coalesce(F.lag("code").over(w), F.lit(0)))


def undo_left(deltas: DataFrame) -> DataFrame:
    w = Window.partitionBy(*ROW).orderBy("col").rowsBetween(Window.unboundedPreceding, 0)
    return deltas.withColumn("code", F.sum("delta").over(w))


def grid(px: DataFrame) -> DataFrame:
    """All pixels of the used rows and columns of each frame, void ones with null code; never wider than the frames themselves."""
    box = px.groupBy("frame_id").agg(F.min("row").alias("r0"), F.max("row").alias("r1"), F.min("col").alias("c0"), F.max("col").alias("c1"))
    full = box.select("frame_id", F.explode(F.sequence("r0", "r1")).alias("row"), "c0", "c1").select("frame_id", "row", F.explode(F.sequence("c0", "c1")).alias("col"))
    return full.join(px, ["frame_id", "row", "col"], "left")


def filled(px: DataFrame, fill: str = "left", block: tuple[int, int] | None = None) -> DataFrame:
    """Adds plane: the code, at void pixels the last valid code to the left (or 0), 0 at the start of a row."""
    full, rows, _ = blocked(grid(px), block)
    w = Window.partitionBy(*rows).orderBy("col").rowsBetween(Window.unboundedPreceding, 0)
    return full.withColumn("plane", F.coalesce(F.last("code", True).over(w) if fill == "left" else F.col("code"), F.lit(0)))


def placed(px: DataFrame, value: str) -> DataFrame:
    """Pixels with a place and a value; others take part in no prediction."""
    return px.where(" and ".join(f"{c} is not null" for c in ("frame_id", "row", "col", value)))


def delta_three(px: DataFrame, fill: str = "left", block: tuple[int, int] | None = None) -> DataFrame:
    """Code minus (left + up - up-left) on the filled plane; only fill='zero' lays out the void pixels for it."""
    p, rows, cols = blocked(placed(px, "code"), block) if fill == "left" else blocked(filled(px, fill, block), block)
    value = "code" if fill == "left" else "plane"
    row, col = Window.partitionBy(*rows).orderBy("col"), Window.partitionBy(*cols).orderBy("row")
    p = p.withColumn("_left", F.coalesce(F.lag(value).over(row), F.lit(0))).withColumn("_step", F.col(value) - F.col("_left"))
    above = F.when(F.lag("row").over(col) == F.col("row") - 1, F.lag("_step").over(col))
    p = p.withColumn("delta", F.col("code") - F.col("_left") - F.coalesce(above, F.lit(0)))
    return p.where("code is not null").select(*px.columns, "delta")


def undo_three(deltas: DataFrame) -> DataFrame:
    """Inverse of delta_three(fill='left') in two running sums; pixels of a column without a void one between them are one run."""
    p = placed(deltas.select("frame_id", "row", "col", "delta"), "delta")
    p = p.withColumn("_run", F.col("row") - F.row_number().over(Window.partitionBy(*COL).orderBy("row")))
    run = Window.partitionBy(*COL, "_run").orderBy("row").rowsBetween(Window.unboundedPreceding, 0)
    p = p.withColumn("_step", F.sum("delta").over(run))
    row = Window.partitionBy(*ROW).orderBy("col").rowsBetween(Window.unboundedPreceding, 0)
    return p.withColumn("code", F.sum("_step").over(row)).select("frame_id", "row", "col", "code")


def neighbour(px: DataFrame, kind: str) -> DataFrame:
    """Other fixed filters on the filled plane: up, mean (floor of half of left + up), gradient (of left, up, up-left the one nearest to left + up - up-left)."""
    p = filled(px)
    row, col = Window.partitionBy(*ROW).orderBy("col"), Window.partitionBy(*COL).orderBy("row")
    p = p.withColumn("_l", F.coalesce(F.lag("plane").over(row), F.lit(0))).withColumn("_u", F.coalesce(F.lag("plane").over(col), F.lit(0))).withColumn("_ul", F.coalesce(F.lag("_l").over(col), F.lit(0)))
    left, up, corner = F.col("_l"), F.col("_u"), F.col("_ul")
    base = left + up - corner
    pick = F.when((F.abs(base - left) <= F.abs(base - up)) & (F.abs(base - left) <= F.abs(base - corner)), left).when(F.abs(base - up) <= F.abs(base - corner), up).otherwise(corner)
    pred = {"up": up, "mean": F.floor((left + up) / 2).cast("long"), "gradient": pick}[kind]
    return p.where("code is not null").select(*px.columns, (F.col("code") - pred).alias("delta"))


def weighted(px: DataFrame, weights: tuple[float, float, float]) -> DataFrame:
    """Delta against floor(0.5 + a left + b up + c up-left) on the filled plane."""
    p = filled(px)
    row, col = Window.partitionBy(*ROW).orderBy("col"), Window.partitionBy(*COL).orderBy("row")
    p = p.withColumn("_l", F.coalesce(F.lag("plane").over(row), F.lit(0))).withColumn("_u", F.coalesce(F.lag("plane").over(col), F.lit(0))).withColumn("_ul", F.coalesce(F.lag("_l").over(col), F.lit(0)))
    a, b, c = (F.lit(float(x)) for x in weights)
    pred = F.floor(a * F.col("_l") + b * F.col("_u") + c * F.col("_ul") + F.lit(0.5)).cast("long")
    return p.where("code is not null").select(*px.columns, (F.col("code") - pred).alias("delta"))


def fitted(px: DataFrame) -> tuple[float, float, float]:
    """Weights that fit_weights' moments give: the 3 x 3 normal equations are solved on the driver, rounded to thousandths."""
    import numpy as np

    m = fit_weights(px).first()
    if m is None or not m.n:
        return 1.0, 0.0, 0.0
    a = np.array([[m.aa, m.ab, m.ac], [m.ab, m.bb, m.bc], [m.ac, m.bc, m.cc]], float)
    return tuple(np.round(np.linalg.lstsq(a, np.array([m.ay, m.by, m.cy], float), rcond=None)[0], 3).tolist())


def fit_weights(px: DataFrame) -> DataFrame:
    """Moments for least-squares weights of left, up and up-left: one row of sums of products (fitted() solves for the weights)."""
    p = filled(px)
    row, col = Window.partitionBy(*ROW).orderBy("col"), Window.partitionBy(*COL).orderBy("row")
    p = p.withColumn("a", F.coalesce(F.lag("plane").over(row), F.lit(0))).withColumn("b", F.coalesce(F.lag("plane").over(col), F.lit(0))).withColumn("c", F.coalesce(F.lag("a").over(col), F.lit(0))).where("code is not null")
    return p.select(*(F.sum(F.expr(f"cast({x} as double) * {y}")).alias(f"{x}{y}") for x, y in ("aa", "ab", "ac", "bb", "bc", "cc")), *(F.sum(F.expr(f"cast({x} as double) * code")).alias(f"{x}y") for x in "abc"), F.count(F.lit(1)).alias("n"))


def delta_prev_frame(px: DataFrame, gop: int | None = None) -> DataFrame:
    """Code minus the last valid code of the same pixel in earlier frames of the sequence (column seq_id, where there is one).

    A pixel's history is one window partition, so long recordings should come with a sequence, or with gop: frames of one
    group of pictures, which restarts the prediction."""
    px, keys = (px.withColumn("_g", F.floor(F.col("frame_id") / gop)), ["_g"]) if gop else (px, [])
    w = Window.partitionBy(*keys, *(c for c in ("seq_id",) if c in px.columns), "row", "col").orderBy("frame_id")
    px = px.withColumn("delta", F.col("code") - F.coalesce(F.lag("code").over(w), F.lit(0)))
    return px.drop("_g")


def undo_prev_frame(deltas: DataFrame, gop: int | None = None) -> DataFrame:
    deltas, keys = (deltas.withColumn("_g", F.floor(F.col("frame_id") / gop)), ["_g"]) if gop else (deltas, [])
    w = Window.partitionBy(*keys, *(c for c in ("seq_id",) if c in deltas.columns), "row", "col").orderBy("frame_id").rowsBetween(Window.unboundedPreceding, 0)
    return deltas.withColumn("code", F.sum("delta").over(w)).drop("_g")


PREDICTORS = {"none": delta_none, "left": delta_left, "three": delta_three, "up": lambda p: neighbour(p, "up"), "mean": lambda p: neighbour(p, "mean"), "gradient": lambda p: neighbour(p, "gradient"), "prev_frame": delta_prev_frame}
