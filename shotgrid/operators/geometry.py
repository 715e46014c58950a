"""Geometry of laser shots: calibration, poses, image to cloud and back, and neighbour searches inside a frame.

Points are rows (frame_id, id, x, y, z). Neighbour joins turn distance into equi-joins on cells of the frame: the asking
side is filed under the 27 cells around it, so the side that is searched is never copied."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.shipping import ship
from ..functions.storage import stored

#: A point with its squared distance to a partner, both sides' columns being in scope.
SQUARED = "(x - qx) * (x - qx) + (y - qy) * (y - qy) + (z - qz) * (z - qz)"


def calibration(rows: DataFrame, columns: int = 240) -> tuple[DataFrame, DataFrame]:
    """Beam table (row, hs, dz) and azimuth table (col, hx, hy) of the scene's sensor, in rational numbers.

    rows has one column `row`. A shot's direction is (hx * hs, hy * hs, dz). Both tables are tiny, so joins broadcast them."""
    r = F.col("row").cast("double")
    te = F.lit(0.04) - F.lit(0.26) * r * r / F.lit(576.0)
    beams = rows.select("row", te.alias("te")).select("row", ((F.lit(1.0) - F.col("te") * F.col("te")) / (F.lit(1.0) + F.col("te") * F.col("te"))).alias("hs"), (F.lit(2.0) * F.col("te") / (F.lit(1.0) + F.col("te") * F.col("te"))).alias("dz"))
    c = F.col("id").cast("int")
    ta = F.lit(2.0) * ((c % 60).cast("double") + F.lit(0.5)) / F.lit(60.0) - F.lit(1.0)
    turns = rows.sparkSession.range(columns).select(c.alias("col"), F.floor(c / 60).alias("q"), ta.alias("ta"))
    turns = turns.withColumn("ux", (F.lit(1.0) - F.col("ta") * F.col("ta")) / (F.lit(1.0) + F.col("ta") * F.col("ta"))).withColumn("uy", F.lit(2.0) * F.col("ta") / (F.lit(1.0) + F.col("ta") * F.col("ta")))
    ux, uy = F.col("ux"), F.col("uy")
    pick = lambda *v: F.when(F.col("q") == 0, v[0]).when(F.col("q") == 1, v[1]).when(F.col("q") == 2, v[2]).otherwise(v[3])
    return beams, turns.select("col", pick(ux, -uy, -ux, uy).alias("hx"), pick(uy, ux, -uy, -ux).alias("hy"))


def attach_pose(px: DataFrame, poses: DataFrame, keys: list[str]) -> DataFrame:
    """Equi form: poses (keys, rot of 9, t of 3) of a bounded number of frames are broadcast."""
    return px.join(F.broadcast(poses), keys)


def asof(shots: DataFrame, poses: DataFrame, by: list[str], ts: str, values: list[str], bucket: str = "day") -> DataFrame:
    """Each shot with the last pose of its group at or before its time (null if there is none).

    Groups are cut into time buckets, so no window spans a sensor's whole history: the last pose before a bucket comes
    from a second window over one row for each bucket."""
    b = F.date_trunc(bucket, F.col(ts)).alias("_b")
    held = F.struct(*(F.col(v) for v in values)).alias("_v")
    last = poses.select(*by, b, ts, held).groupBy(*by, "_b").agg(F.max_by("_v", ts).alias("_last"))
    both = shots.select(*by, b, ts, F.struct(*shots.columns).alias("_s"), F.lit(None).cast(poses.select(held).schema["_v"].dataType).alias("_v"), F.lit(1).alias("_k"))
    both = both.unionByName(poses.select(*by, b, ts, held, F.lit(0).alias("_k")), allowMissingColumns=True)
    w = Window.partitionBy(*by, "_b").orderBy(ts, "_k").rowsBetween(Window.unboundedPreceding, 0)
    both = both.withColumn("_near", F.last("_v", True).over(w)).where("_k = 1")
    every = both.select(*by, "_b").distinct().unionByName(last.select(*by, "_b")).distinct().join(last, [*by, "_b"], "left")
    before = Window.partitionBy(*by).orderBy("_b").rowsBetween(Window.unboundedPreceding, -1)
    every = every.select(*by, "_b", F.last("_last", True).over(before).alias("_early"))
    out = both.join(every, [*by, "_b"], "left").withColumn("_v", F.coalesce("_near", "_early"))
    return out.select("_s.*", *(F.col(f"_v.{v}").alias(v) for v in values))


def unproject(px: DataFrame, beams: DataFrame, turns: DataFrame, poses: DataFrame | None = None, value: str = "range") -> DataFrame:
    """Adds x, y, z: direction times range in the sensor's frame, then the frame's pose if poses (frame_id, rot, t) are given."""
    at = px.join(F.broadcast(beams), "row").join(F.broadcast(turns), "col")
    v = F.col(value)
    at = at.withColumns({"_x": F.col("hx") * F.col("hs") * v, "_y": F.col("hy") * F.col("hs") * v, "_z": F.col("dz") * v})
    if poses is None:
        return at.select(*px.columns, F.col("_x").alias("x"), F.col("_y").alias("y"), F.col("_z").alias("z"))
    at = attach_pose(at, poses, ["frame_id"])
    turned = lambda i: F.col("rot")[3 * i] * F.col("_x") + F.col("rot")[3 * i + 1] * F.col("_y") + F.col("rot")[3 * i + 2] * F.col("_z") + F.col("t")[i]
    return at.select(*px.columns, *(turned(i).alias(c) for i, c in enumerate("xyz")))


def project(points: DataFrame, poses: DataFrame) -> DataFrame:
    """Adds azimuth, elevation and range of global points as seen from their frame's pose (inverse of the pose first)."""
    at = attach_pose(points, poses, ["frame_id"])
    moved = [F.col(c) - F.col("t")[i] for i, c in enumerate("xyz")]
    local = [F.col("rot")[i] * moved[0] + F.col("rot")[3 + i] * moved[1] + F.col("rot")[6 + i] * moved[2] for i in range(3)]
    at = at.withColumns(dict(zip(("_x", "_y", "_z"), local))).withColumn("range", F.sqrt(F.col("_x") * F.col("_x") + F.col("_y") * F.col("_y") + F.col("_z") * F.col("_z")))
    return at.select(*points.columns, F.atan2("_y", "_x").alias("azimuth"), F.when(F.col("range") > 0, F.asin(F.col("_z") / F.col("range"))).otherwise(F.lit(0.0)).alias("elevation"), "range")


def pseudo_image(cloud: DataFrame, height: int = 64, width: int = 2088, low: float = -0.45, high: float = 0.05) -> DataFrame:
    """Range image of a bare cloud: elevation bins between low and high (radians, outside ones go to the border rows), azimuth bins; the nearest return of a pixel stays."""
    r = F.sqrt(F.col("x") * F.col("x") + F.col("y") * F.col("y") + F.col("z") * F.col("z"))
    at = cloud.withColumn("range", r).where("range > 0")
    row = F.floor((F.lit(high) - F.asin(F.col("z") / F.col("range"))) / F.lit((high - low) / height))
    col = F.floor((F.atan2("y", "x") + F.lit(np.pi)) / F.lit(2 * np.pi / width))
    at = at.select("frame_id", F.greatest(F.lit(0), F.least(F.lit(height - 1), row)).cast("int").alias("row"), F.least(F.lit(width - 1), col).cast("int").alias("col"), "range")
    return at.groupBy("frame_id", "row", "col").agg(F.min("range").alias("range"))


def _cell(side: float, c: str) -> Column:
    return F.floor(F.col(c) / F.lit(float(side))).cast("long")


def _candidates(p: DataFrame, q: DataFrame, side: float) -> DataFrame:
    """p rows with every q row of the 27 cells around them: an equi-join on (frame, cell)."""
    shift = F.expr("transform(sequence(0, 26), i -> struct(i % 3 - 1 as a, (i div 3) % 3 - 1 as b, i div 9 - 1 as c))")
    asks = p.withColumn("_o", F.explode(shift)).withColumns({f"_k{c}": _cell(side, c) + F.col(f"_o.{o}") for c, o in zip("xyz", "abc")}).drop("_o")
    filed = q.select("frame_id", F.col("id").alias("qid"), *(F.col(c).alias(f"q{c}") for c in "xyz"), *(_cell(side, c).alias(f"_k{c}") for c in "xyz"))
    return asks.join(filed, ["frame_id", "_kx", "_ky", "_kz"]).withColumn("d2", F.expr(SQUARED))


def brute(p: DataFrame, q: DataFrame) -> DataFrame:
    """Reference: every q row of the frame beside each p row."""
    return p.join(q.select("frame_id", F.col("id").alias("qid"), *(F.col(c).alias(f"q{c}") for c in "xyz")), "frame_id").withColumn("d2", F.expr(SQUARED))


def knn(p: DataFrame, q: DataFrame, k: int, side: float, rounds: int = 6, other: bool = False) -> DataFrame:
    """The k nearest q points of each p point in its frame: frame_id, id, qid, qx, qy, qz, dist, rank (1 is nearest; ties by qid).

    Exact. A point is settled when its k-th candidate lies within the cell side; the others go on with twice the side, and
    those that are left after `rounds` (far from everything, or in frames of fewer than k points) meet their whole frame.
    Each round is written out, so the plan does not grow. other=True leaves out the point of the same id. Points of
    frames where q has none are not returned."""
    rank = Window.partitionBy("frame_id", "id").orderBy("d2", "qid")
    keep = ["frame_id", "id", "qid", "qx", "qy", "qz", "d2"]
    differ = F.col("id") != F.col("qid") if other else F.lit(True)
    out, left = None, p.select("frame_id", "id", "x", "y", "z").join(q.select("frame_id").distinct(), "frame_id", "left_semi")
    for n in range(rounds + 1):
        met = _candidates(left, q, side) if n < rounds else brute(left, q)
        top = met.where(differ).withColumn("rank", F.row_number().over(rank)).where(F.col("rank") <= k).select(*keep, "rank")
        if n == rounds:
            out = top if out is None else out.unionByName(top)
            break
        top = stored(top.withColumn("_far", F.max(F.when(F.col("rank") == k, F.col("d2"))).over(Window.partitionBy("frame_id", "id"))).withColumn("_ok", F.coalesce(F.col("_far") <= F.lit(float(side) ** 2), F.lit(False))), f"knn-{n}")
        sure = top.where("_ok").drop("_far", "_ok")
        out = sure if out is None else out.unionByName(sure)
        left = stored(left.join(sure.select("frame_id", "id").distinct(), ["frame_id", "id"], "left_anti"), f"knn-left-{n}")
        if left.isEmpty():
            break
        side *= 2
    return out.withColumn("dist", F.sqrt("d2")).drop("d2")


def nearest(p: DataFrame, q: DataFrame, side: float, rounds: int = 6, other: bool = False) -> DataFrame:
    """frame_id, id, dist, qid, qx, qy, qz of the nearest q point; null where the frame has none (or only the point itself)."""
    return p.select("frame_id", "id", "x", "y", "z").join(knn(p, q, 1, side, rounds, other).drop("rank"), ["frame_id", "id"], "left")


def nearest_aligned(p: DataFrame, q: DataFrame, bound: float) -> DataFrame:
    """nearest() in one round where every p point is known to have a q point within `bound`, as decoded pixels are of their own originals."""
    d = F.min(F.struct("d2", "qid", "qx", "qy", "qz")).alias("_m")
    best = _candidates(p, q, bound).groupBy("frame_id", "id", "x", "y", "z").agg(d)
    return best.select("frame_id", "id", "x", "y", "z", *(F.col(f"_m.{c}").alias(c) for c in ("qid", "qx", "qy", "qz")), F.sqrt("_m.d2").alias("dist"))


def moments(neighbours: DataFrame) -> DataFrame:
    """Means and covariances of each point's neighbours: frame_id, id, n, mx, my, mz, cxx, cxy, cxz, cyy, cyz, czz."""
    mean = neighbours.groupBy("frame_id", "id").agg(F.count(F.lit(1)).alias("n"), *(F.avg(f"q{c}").alias(f"m{c}") for c in "xyz"))
    pairs = ("xx", "xy", "xz", "yy", "yz", "zz")
    spread = neighbours.join(mean, ["frame_id", "id"]).groupBy("frame_id", "id").agg(*(F.avg(F.expr(f"(q{a} - m{a}) * (q{b} - m{b})")).alias(f"c{a}{b}") for a, b in pairs))
    return mean.join(spread, ["frame_id", "id"])


def normals(p: DataFrame, side: float, k: int = 12) -> DataFrame:
    """frame_id, id, nx, ny, nz: smallest eigenvector of the covariance of the k nearest points (the point itself included).

    Its sign is chosen so that the first component that isn't zero is positive; projections don't depend on it."""
    ship(p.sparkSession)

    def run(batches):
        for b in batches:
            c = {x: b.column(f"c{x}").to_numpy() for x in ("xx", "xy", "xz", "yy", "yz", "zz")}
            m = np.stack([np.stack([c["xx"], c["xy"], c["xz"]], 1), np.stack([c["xy"], c["yy"], c["yz"]], 1), np.stack([c["xz"], c["yz"], c["zz"]], 1)], 1)
            v = np.linalg.eigh(m)[1][:, :, 0] if len(m) else np.zeros((0, 3))
            lead = np.take_along_axis(v, (np.abs(v) > 1e-12).argmax(1)[:, None], 1)
            v = v * np.where(lead < 0, -1.0, 1.0)
            yield pa.RecordBatch.from_arrays([b.column("frame_id"), b.column("id"), *(pa.array(v[:, i].copy()) for i in range(3))], ["frame_id", "id", "nx", "ny", "nz"])

    return moments(knn(p, p, k, side)).mapInArrow(run, "frame_id long, id long, nx double, ny double, nz double")


class LocalTree:
    """kd-tree of one frame's points for tasks that hold a frame: all queries go down the tree together.

    A node that lies farther than a query's k-th distance is passed over, for those queries only. Ties in distance go to
    the smaller index, so results don't depend on the order of the visits."""

    LEAF = 24

    def __init__(self, points: np.ndarray):
        self.points = points
        self.root = self._built(np.arange(len(points)))

    def _built(self, at: np.ndarray):
        p = self.points[at]
        low, high = (p.min(0), p.max(0)) if len(p) else (np.zeros(3), np.zeros(3))
        if len(at) <= self.LEAF:
            return low, high, at, None
        axis = int((high - low).argmax())
        order = np.argpartition(p[:, axis], len(at) // 2)
        half = len(at) // 2
        return low, high, None, (self._built(np.sort(at[order[:half]])), self._built(np.sort(at[order[half:]])))

    def query(self, q: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray]:
        """Indices and squared distances of the k nearest points of each query; -1 and infinity where there are fewer."""
        at, far = np.full((len(q), k), -1), np.full((len(q), k), np.inf)
        stack = [(self.root, np.arange(len(q)))]
        while stack:
            (low, high, leaf, parts), who = stack.pop()
            gap = np.maximum(np.maximum(low - q[who], q[who] - high), 0)
            who = who[(gap * gap).sum(1) <= far[who, -1]]
            if not len(who):
                continue
            if parts is None:
                step = q[who][:, None, :] - self.points[leaf][None, :, :]
                d = step[:, :, 0] * step[:, :, 0] + step[:, :, 1] * step[:, :, 1] + step[:, :, 2] * step[:, :, 2]
                d, i = np.concatenate([far[who], d], 1), np.concatenate([at[who], np.broadcast_to(leaf, (len(who), len(leaf)))], 1)
                order = np.lexsort((i, d))[:, :k]
                far[who], at[who] = np.take_along_axis(d, order, 1), np.take_along_axis(i, order, 1)
                continue
            first, second = parts
            near = ((q[who] - (first[0] + first[1]) / 2) ** 2).sum(1) <= ((q[who] - (second[0] + second[1]) / 2) ** 2).sum(1)
            stack += [(second, who[near]), (first, who[~near]), (first, who[near]), (second, who[~near])]
        return at, far


def context_points(px: DataFrame, h: int, w: int, value: str = "code") -> DataFrame:
    """Rows (frame_id, row, col, di, dj, near): the valid pixels of the h x w window whose bottom right corner is the pixel itself.

    Offsets are exploded on the asking side, then one equi-join on (frame_id, row, col)."""
    offsets = F.expr(f"filter(transform(sequence(0, {h * w - 1}), i -> struct(cast(i div {w} as int) as di, cast(i % {w} as int) as dj)), o -> o.di + o.dj > 0)")
    asks = px.select("frame_id", "row", "col", F.explode(offsets).alias("o")).select("frame_id", "row", "col", "o.di", "o.dj", (F.col("row") - F.col("o.di")).alias("_r"), (F.col("col") - F.col("o.dj")).alias("_c"))
    there = px.select("frame_id", F.col("row").alias("_r"), F.col("col").alias("_c"), F.col(value).alias("near"))
    return asks.join(there, ["frame_id", "_r", "_c"]).select("frame_id", "row", "col", "di", "dj", "near")


def anchor_labels(px: DataFrame, h: int, w: int) -> DataFrame:
    """The class of each pixel for training: frame_id, row, col, di, dj, gap (|anchor - code|) of the context pixel nearest in value.

    Ties go to the smaller di + dj, then to the smaller di: pixels close in angle first. Pixels without context have no row."""
    near = context_points(px.select("frame_id", "row", "col", "code"), h, w)
    both = near.join(px.select("frame_id", "row", "col", "code"), ["frame_id", "row", "col"])
    best = F.min(F.struct(F.abs(F.col("near") - F.col("code")).alias("gap"), (F.col("di") + F.col("dj")).alias("s"), "di", "dj")).alias("m")
    return both.groupBy("frame_id", "row", "col").agg(best).select("frame_id", "row", "col", "m.di", "m.dj", "m.gap")


def anchor_share(px: DataFrame, h: int, w: int) -> DataFrame:
    """Reference level: percent of pixels with a context pixel of their very code, and the mean gap to the nearest one."""
    n = px.agg(F.count(F.lit(1)).alias("n_valid"))
    got = anchor_labels(px, h, w).agg(F.sum((F.col("gap") == 0).cast("long")).alias("hits"), F.avg("gap").alias("gap"))
    return got.crossJoin(F.broadcast(n)).select(F.round(100 * F.col("hits") / F.col("n_valid"), 6).alias("accuracy"), F.round("gap", 6).alias("mean_gap"), "n_valid")
