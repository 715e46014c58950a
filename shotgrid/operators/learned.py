"""Training of the learned predictors on Spark tables: patch samples, splits, and gradients summed over the cluster."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.shipping import ship
from . import anchor, codec

#: Rows of samples that reach the driver at most: the documented bound of a training set held there.
MOST = 20_000
SAMPLE = "frame_id long, row int, col int, precision double, value array<double>, ok array<boolean>, daz array<int>, del array<int>, time array<int>, target double"


def sample_precision(keys: list[str], seed: int = 0, bins: int = 5000, size: float = 0.0001) -> Column:
    """Mixed strategy: a precision from size to bins * size for each row, even over the bins, by a portable integer mix of its keys."""
    h = F.lit(seed + 1).cast("long")
    for k in keys:
        h = F.pmod(h * F.lit(1_103_515_245) + F.col(k).cast("long") * F.lit(12_345) + F.lit(1), F.lit(2_147_483_647))
    return (F.pmod(h, F.lit(bins)) + F.lit(1)).cast("double") * F.lit(size)


def split(df: DataFrame, column: str, percent: int, seed: int = 0) -> DataFrame:
    """Adds train: whole sequences (values of column) go to one side, `percent` of them to training."""
    return df.withColumn("train", F.pmod(F.crc32(F.concat_ws("/", F.lit(str(seed)), F.col(column).cast("string"))), F.lit(100)) < percent)


def samples(px: DataFrame, spec: codec.CodecSpec, net: anchor.NetSpec, every: int, seed: int = 0, sensor: codec.Sensor | None = None, mixed: bool = False) -> DataFrame:
    """Contexts of one valid pixel in `every`, chosen by its place: inputs quantised, targets in full precision.

    With mixed=True the inputs stay in metres and are quantised when a batch is drawn, by a precision of their own."""
    h, w = spec.block
    ship(px.sparkSession)
    v = codec.to_blocks(px, spec, "range").withColumn("gop", F.floor(F.col("frame_id") / spec.gop))
    rows = F.array_sort(F.collect_list(F.struct("frame_id", "r", "c", "v"))).alias("f")
    groups = v.groupBy("gop", "block_row", "block_col").agg(rows).select("block_row", "block_col", *(F.col(f"f.{c}").alias(c) for c in ("frame_id", "r", "c", "v")))

    def run(batches):
        probe = anchor.build(net)
        for b in batches:
            for g in b.to_pylist():
                before, i0, j0 = None, g["block_row"] * h, g["block_col"] * w
                for f, r, c, x in zip(g["frame_id"], g["r"], g["c"], g["v"]):
                    raw, valid = np.zeros((1, h, w)), np.zeros((1, h, w), bool)
                    raw[0, r, c], valid[0, r, c] = x, True
                    code = np.floor(raw / spec.precision + 0.5).astype(np.int64)
                    _, i, j = np.nonzero(valid)
                    mark = (((f * 64 + i + i0) * 4096 + j + j0) * 2_654_435_761 >> 7) % every == seed % every
                    i, j = i[mark], j[mark]
                    k = np.zeros(len(i), np.int64)
                    p = anchor.patch(net, raw if mixed else code, valid, k, i, j, i0, j0)
                    if net.temporal != "none":
                        p = anchor.joined(p, codec._extra(probe, before, spec.precision, sensor, f, valid[0], i0, j0)(k, i, j, code))
                    before = (code[0], valid[0], f)
                    as_list = lambda x, t: pa.array(list(x), pa.list_(t))
                    yield pa.RecordBatch.from_arrays(
                        [pa.array(np.full(len(i), f)), pa.array((i + i0).astype(np.int32)), pa.array((j + j0).astype(np.int32)), pa.array(np.full(len(i), spec.precision)), as_list(p["value"].astype(float), pa.float64()), as_list(p["ok"], pa.bool_()), *(as_list(p[n].astype(np.int32), pa.int32()) for n in ("daz", "del", "time")), pa.array(raw[0, i, j])],
                        [c.split()[0] for c in SAMPLE.split(", ")],
                    )

    return groups.mapInArrow(run, SAMPLE)


def held(rows: DataFrame, most: int = MOST) -> dict:
    """Samples as arrays on the driver, `most` rows at most, smallest hash of their place first."""
    got = rows.orderBy(F.xxhash64("frame_id", "row", "col"), "frame_id", "row", "col").limit(most).toArrow()
    if not got.num_rows:
        raise ValueError("no samples to train on")
    wide = lambda c, t: np.stack([np.asarray(x, t) for x in got.column(c).to_pylist()])
    return {"value": wide("value", float), "ok": wide("ok", bool), "daz": wide("daz", np.int64), "del": wide("del", np.int64), "time": wide("time", np.int64), "target": got.column("target").to_numpy(), "precision": got.column("precision").to_numpy()}


def batch(data: dict, at: np.ndarray, spec: anchor.NetSpec, precision: float | np.ndarray, mixed: bool) -> dict:
    p = {k: data[k][at] for k in ("value", "ok", "daz", "del", "time")}
    wide = precision[:, None] if np.ndim(precision) else precision
    p["value"] = np.floor(p["value"] / wide + 0.5).astype(np.int64) if mixed else p["value"].astype(np.int64)
    return anchor.samples_of(p, data["target"][at], precision, spec)


def drawer(data: dict, spec: anchor.NetSpec, precision: float | None):
    """Batches at random; precision None: the mixed strategy, 0.0001 to 0.5 in steps of 0.0001."""

    def draw(n: int, rng):
        at = rng.integers(0, len(data["target"]), n)
        d = precision if precision is not None else (rng.integers(1, 5001, n) * 0.0001)
        return batch(data, at, spec, d, precision is None)

    return draw


def train(px: DataFrame, net: anchor.NetSpec, spec: codec.CodecSpec, steps: int, every: int = 1, sensor=None, mixed: bool = False, rate: float = 5e-5, milestones=(1_500_000, 3_000_000), batch_size: int = 128, seed: int = 0, most: int = MOST) -> tuple[anchor.Net, list[float]]:
    """Samples px, trains on the driver, returns the network and its losses."""
    data = held(samples(px, spec, net, every, seed, sensor, mixed), most)
    return anchor.fit(net, drawer(data, net, None if mixed else spec.precision), steps, batch_size, rate, milestones, seed=seed)


def gradient_sums(rows: DataFrame, net: anchor.Net, gamma: float = 0.01) -> DataFrame:
    """One step's gradient over all samples, summed on the executors: (name, part, value array, n), one row per tensor.

    Each task sums its own batches, so what is shuffled is the network's size times the number of tasks."""
    ship(rows.sparkSession)
    raw = net.dumps()

    def run(batches):
        own, total, n = anchor.Net.loads(raw), {}, 0
        for b in batches:
            if not b.num_rows:
                continue
            wide = lambda c, t: np.stack([np.asarray(x, t) for x in b.column(c).to_pylist()])  # noqa: E731, B023
            data = {"value": wide("value", float), "ok": wide("ok", bool), "daz": wide("daz", np.int64), "del": wide("del", np.int64), "time": wide("time", np.int64), "target": b.column("target").to_numpy()}
            got = batch(data, np.arange(b.num_rows), own.spec, float(b.column("precision")[0].as_py()), False)
            live = int(got["ok"].any(1).sum())
            _, grads = own.loss(got, gamma)
            for k, pair in grads.items():
                for part, g in enumerate(pair):
                    total[k, part] = total.get((k, part), 0) + g.ravel() * live
            n += live
        if total:
            yield pa.RecordBatch.from_arrays([pa.array([k for k, _ in total]), pa.array([p for _, p in total], pa.int32()), pa.array(list(total.values()), pa.list_(pa.float64())), pa.array([n] * len(total), pa.int64())], ["name", "part", "value", "n"])

    parts = rows.mapInArrow(run, "name string, part int, value array<double>, n long")
    each = parts.select("name", "part", "n", F.posexplode("value").alias("at", "x")).groupBy("name", "part", "at").agg(F.sum("x").alias("x"), F.sum("n").alias("n"))
    return each.groupBy("name", "part").agg(F.transform(F.array_sort(F.collect_list(F.struct("at", "x"))), lambda v: v["x"]).alias("value"), F.max("n").alias("n"))


def train_on_cluster(rows: DataFrame, spec: anchor.NetSpec, steps: int, rate: float = 5e-5, gamma: float = 0.01, seed: int = 0) -> anchor.Net:
    """Full-batch steps: gradients are summed by executors, Adam runs on the driver. rows should be written out or cached by the caller."""
    net, opt = anchor.build(spec, seed), anchor.Adam(rate)
    for _ in range(steps):
        got = gradient_sums(rows, net, gamma).collect()
        grads: dict = {}
        for r in got:
            pair = grads.setdefault(r.name, [None, None])
            pair[r.part] = (np.array(r.value) / max(1, r.n)).reshape(net.w[r.name].shape if r.part == 0 else net.b[r.name].shape)
        opt.step(net, grads)
    return net
