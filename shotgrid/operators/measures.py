"""Rate, accuracy and distortion measures."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .geometry import nearest


def entropy_h0(deltas: DataFrame, by: list[str] | None = None, column: str = "delta") -> DataFrame:
    """Order-0 entropy in bits per valid pixel: two-level aggregation, the histogram never leaves the executors."""
    by = by or []
    hist = deltas.groupBy(*by, column).count()
    total = hist.groupBy(*by).agg(F.sum("count").alias("t"))
    both = hist.join(total, by) if by else hist.crossJoin(F.broadcast(total))
    return both.groupBy(*by).agg(F.round(-F.sum(F.col("count") / F.col("t") * F.log2(F.col("count") / F.col("t"))), 6).alias("h0"), F.sum("count").alias("n_valid"))


def entropy_raw(deltas: DataFrame) -> DataFrame:
    """entropy_h0 of the whole table without rounding: column h."""
    hist = deltas.groupBy("delta").count()
    total = hist.agg(F.sum("count").alias("t"))
    return hist.crossJoin(F.broadcast(total)).agg((-F.sum(F.col("count") / F.col("t") * F.log2(F.col("count") / F.col("t")))).alias("h"))


def entropy_ctx(deltas: DataFrame) -> DataFrame:
    """Conditional entropy given the size class (0, 1-2, more) of the delta to the left."""
    w = Window.partitionBy("frame_id", "row").orderBy("col")
    size = F.abs(F.coalesce(F.lag("delta").over(w), F.lit(0)))
    d = deltas.withColumn("ctx", F.when(size == 0, 0).when(size <= 2, 1).otherwise(2))
    per = entropy_h0(d, ["ctx"])
    return per.agg(F.round(F.sum(F.col("h0") * F.col("n_valid")) / F.sum("n_valid"), 5).alias("h_ctx"), F.sum("n_valid").alias("n_valid"))


def accuracy(deltas: DataFrame, all_pixels: int | None = None) -> DataFrame:
    """Share of pixels with zero delta, in percent, over valid pixels; void ones count as zero if all_pixels is given."""
    zero = F.sum((F.col("delta") == 0).cast("long"))
    n = F.count(F.lit(1))
    share = zero / n if all_pixels is None else (zero + F.lit(all_pixels) - n) / F.lit(all_pixels)
    return deltas.agg(F.round(100 * share, 6).alias("accuracy"), n.alias("n_valid"))


def residual_histogram(deltas: DataFrame, lo: int = -20, hi: int = 20) -> DataFrame:
    return deltas.groupBy(F.greatest(F.lit(lo), F.least(F.lit(hi), F.col("delta"))).cast("long").alias("delta")).agg(F.count(F.lit(1)).alias("n"))


def displacement(px: DataFrame, d: float) -> DataFrame:
    """Mean and largest absolute error of the decoded range."""
    from .linear import decode, encode

    err = F.abs(decode(encode("range", d), d) - F.col("range"))
    return px.agg(F.round(F.avg(err), 6).alias("mean_error"), F.round(F.max(err), 6).alias("max_error"), F.count(F.lit(1)).alias("n_valid"))


def chamfer_oneway(p: DataFrame, q: DataFrame, cell: float) -> DataFrame:
    """Mean distance of each frame's points to the nearest point of q; points of frames that q lacks have no distance and don't count."""
    return nearest(p, q, cell).groupBy("frame_id").agg(F.round(F.avg("dist"), 6).alias("chamfer"), F.count(F.lit(1)).alias("n"))


def chamfer_sym(p: DataFrame, q: DataFrame, cell: float) -> DataFrame:
    a, b = chamfer_oneway(p, q, cell), chamfer_oneway(q, p, cell)
    return a.join(b.select("frame_id", F.col("chamfer").alias("back")), "frame_id").select("frame_id", F.greatest("chamfer", "back").alias("chamfer"))


def resolution(p: DataFrame, cell: float) -> DataFrame:
    """(frame_id, r): the largest distance of a point to its nearest other point."""
    return nearest(p, p, cell, other=True).groupBy("frame_id").agg(F.max("dist").alias("r"))


def psnr(p: DataFrame, q: DataFrame, cell: float) -> DataFrame:
    """(frame_id, r, mse, back, psnr): point-to-plane error of both directions against the intrinsic resolution.

    p has normals nx, ny, nz beside its points; the normal of the original point of a matched pair counts in both directions."""
    n = p.select("frame_id", F.col("id").alias("_n"), "nx", "ny", "nz")
    off = lambda: F.pow((F.col("x") - F.col("qx")) * F.col("nx") + (F.col("y") - F.col("qy")) * F.col("ny") + (F.col("z") - F.col("qz")) * F.col("nz"), 2)
    there = nearest(p, q, cell).withColumn("_n", F.col("id")).join(n, ["frame_id", "_n"]).groupBy("frame_id").agg(F.avg(off()).alias("mse"))
    back = nearest(q, p, cell).withColumn("_n", F.col("qid")).join(n, ["frame_id", "_n"]).groupBy("frame_id").agg(F.avg(off()).alias("back"))
    both = resolution(p, cell).join(there, "frame_id").join(back, "frame_id")
    worst = F.greatest("mse", "back")
    return both.select("frame_id", F.round("r", 6).alias("r"), F.round("mse", 6).alias("mse"), F.round("back", 6).alias("back"), F.round(F.when(worst > 0, 10 * F.log10(F.col("r") * F.col("r") / worst)), 5).alias("psnr"))


def error_map(p: DataFrame, q: DataFrame, cell: float, step: float) -> DataFrame:
    """(frame_id, bin, n): points by their distance to the nearest point of q, in bins of width step."""
    return nearest(p, q, cell).groupBy("frame_id", F.floor(F.col("dist") / F.lit(step)).alias("bin")).agg(F.count(F.lit(1)).alias("n"))


def rd_compare(curves: DataFrame, at: float) -> DataFrame:
    """(method, bpp): each method's rate at distortion `at`, linear between the neighbouring points of its curve (method, distortion, bpp).

    Curves have a handful of points each, so their windows are small; methods whose curve does not reach `at` are not returned."""
    w = Window.partitionBy("method").orderBy("distortion")
    pair = curves.withColumns({"_d": F.lead("distortion").over(w), "_b": F.lead("bpp").over(w)})
    inside = pair.where((F.col("distortion") <= at) & (F.col("_d") > at))
    share = (F.lit(float(at)) - F.col("distortion")) / (F.col("_d") - F.col("distortion"))
    return inside.select("method", F.round(F.col("bpp") + share * (F.col("_b") - F.col("bpp")), 6).alias("bpp"))


def mean_ap(scored: DataFrame) -> DataFrame:
    return average_precision(scored).agg(F.round(F.avg("ap"), 6).alias("map"), F.count(F.lit(1)).alias("classes"))


def precision_curve(scored: DataFrame, slices: int = 64) -> DataFrame:
    """average_precision() for classes of any size: ranks come from a range partition of the scores and its totals, not from one task.

    Rows (class, id, score, positive). Each slice of the score order is counted, the counts of the slices before it are
    added (a table of slices x classes rows), and only then windows run inside a slice."""
    parts = scored.repartitionByRange(slices, F.desc("score"), "id").withColumn("_p", F.spark_partition_id())
    total = parts.groupBy("class", "_p").agg(F.count(F.lit(1)).alias("n"), F.sum(F.col("positive").cast("long")).alias("h"))
    before = Window.partitionBy("class").orderBy("_p").rowsBetween(Window.unboundedPreceding, -1)
    base = total.select("class", "_p", F.coalesce(F.sum("n").over(before), F.lit(0)).alias("n0"), F.coalesce(F.sum("h").over(before), F.lit(0)).alias("h0"))
    w = Window.partitionBy("class", "_p").orderBy(F.desc("score"), "id")
    r = parts.join(F.broadcast(base), ["class", "_p"]).withColumn("rank", F.row_number().over(w) + F.col("n0")).withColumn("hits", F.sum(F.col("positive").cast("long")).over(w.rowsBetween(Window.unboundedPreceding, 0)) + F.col("h0"))
    return r.where("positive").groupBy("class").agg(F.round(F.avg(F.col("hits") / F.col("rank")), 6).alias("ap"), F.count(F.lit(1)).alias("positives"))


def average_precision(scored: DataFrame) -> DataFrame:
    """AP of each class from class, id, score, positive: precision at each positive, ranked by score, ties by id."""
    w = Window.partitionBy("class").orderBy(F.desc("score"), "id")
    r = scored.withColumn("rank", F.row_number().over(w)).withColumn("hits", F.sum(F.col("positive").cast("long")).over(w.rowsBetween(Window.unboundedPreceding, 0)))
    return r.where("positive").groupBy("class").agg(F.round(F.avg(F.col("hits") / F.col("rank")), 6).alias("ap"), F.count(F.lit(1)).alias("positives"))
