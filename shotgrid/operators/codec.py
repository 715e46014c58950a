"""Block codec: quantise, predict, entropy-code and decode range images; one container row for each block.

Blocks are independent (prediction starts anew in each), so encoding and decoding run in parallel and any box of pixels
needs only its own blocks. One exchange by (frame, block) builds the blocks; the rest is Arrow batches of bounded rows, in
which all blocks of a batch are predicted together. Temporal predictors group the frames of a block into groups of
pictures that start with a key frame, so decoding is as deep as a group and no deeper."""

from __future__ import annotations

import zlib
from dataclasses import dataclass, replace

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.shipping import ship
from . import anchor, coders, masks
from .linear import encode as quantise

CONTAINER = "frame_id long, block_row int, block_col int, predictor string, model_id string, coder string, precision double, h int, w int, n_valid int, crc long, min_code long, max_code long, mask_bytes binary, payload binary, bits long"
NAMES = [c.strip().split()[0] for c in CONTAINER.split(",")]
KINDS = {"long": pa.int64(), "int": pa.int32(), "string": pa.string(), "double": pa.float64(), "binary": pa.binary()}
TYPES = [KINDS[c.strip().split()[1]] for c in CONTAINER.split(",")]


@dataclass(frozen=True)
class CodecSpec:
    """predictor: none, left, three or learned (with a network). coder, mask: a name or auto. gop: frames of a group of pictures (temporal networks)."""

    precision: float = 0.1
    predictor: str = "three"
    block: tuple[int, int] = (16, 50)
    coder: str = "auto"
    mask: str = "auto"
    gop: int = 4


@dataclass(frozen=True)
class Sensor:
    """What temporal neighbours need: direction of every pixel (rows, columns, 3) and position of the sensor at every frame (step per frame)."""

    directions: np.ndarray
    step: tuple[float, float, float] = (1.0, 0.0, 0.0)

    def at(self, frame: int) -> np.ndarray:
        return np.array(self.step) * float(frame)


def plane(code: np.ndarray, valid: np.ndarray) -> np.ndarray:
    """Codes with void pixels holding the last valid code to the left, 0 at the start of a row; any leading axes."""
    at = np.maximum.accumulate(np.where(valid, np.arange(code.shape[-1]) + 1, 0), axis=-1)
    return np.where(at > 0, np.take_along_axis(code, np.maximum(at - 1, 0), -1), 0)


def _shifted(x: np.ndarray, axis: int) -> np.ndarray:
    """x moved by one along an axis, zero at the start."""
    out = np.roll(x, 1, axis)
    out[(Ellipsis, 0) if axis == -1 else (Ellipsis, 0, slice(None))] = 0
    return out


def predict(code: np.ndarray, valid: np.ndarray, kind: str) -> np.ndarray:
    if kind == "none":
        return np.zeros_like(code)
    f = plane(code, valid)
    left = _shifted(f, -1)
    return left if kind == "left" else left + _shifted(f, -2) - _shifted(left, -2)


def restore(delta: np.ndarray, valid: np.ndarray, kind: str) -> np.ndarray:
    """Inverse of delta = code - predict(code) at valid pixels, by running sums."""
    step = np.where(valid, delta, 0)
    if kind == "none":
        return step
    if kind != "left":
        for i in range(1, step.shape[-2]):
            step[..., i, :] = np.where(valid[..., i, :], step[..., i, :] + step[..., i - 1, :], 0)
    return np.cumsum(step, axis=-1)


def to_blocks(px: DataFrame, spec: CodecSpec, value: str = "code") -> DataFrame:
    """One row for each non-empty block: (frame_id, block_row, block_col, r, c, v), arrays in raster order. value: code or range."""
    h, w = spec.block
    v = quantise("range", spec.precision) if value == "code" else F.col(value)
    q = px.select("frame_id", F.floor(F.col("row") / h).cast("int").alias("block_row"), F.floor(F.col("col") / w).cast("int").alias("block_col"), (F.col("row") % h).cast("int").alias("r"), (F.col("col") % w).cast("int").alias("c"), v.alias("v"))
    px = F.array_sort(F.collect_list(F.struct("r", "c", "v")))
    return q.groupBy("frame_id", "block_row", "block_col").agg(px.alias("px")).select("frame_id", "block_row", "block_col", *(F.col(f"px.{c}").alias(c) for c in ("r", "c", "v")))


def to_pixels(blocks: DataFrame, spec: CodecSpec) -> DataFrame:
    """(frame_id, row, col, code) of a block table."""
    h, w = spec.block
    px = blocks.select("frame_id", "block_row", "block_col", F.explode(F.arrays_zip("r", "c", "v")).alias("p"))
    return px.select("frame_id", (F.col("block_row") * h + F.col("p.r")).cast("int").alias("row"), (F.col("block_col") * w + F.col("p.c")).cast("int").alias("col"), F.col("p.v").alias("code"))


def dense(b: pa.RecordBatch, h: int, w: int, kind=np.int64) -> tuple[np.ndarray, np.ndarray]:
    """Values and mask of the blocks of a batch, from list offsets; a pixel that stands twice in a block raises."""
    r = b.column("r")
    sizes = r.value_lengths().to_numpy(zero_copy_only=False)
    n = np.repeat(np.arange(len(sizes)), sizes)
    flat = (n * h + r.flatten().to_numpy()) * w + b.column("c").flatten().to_numpy()
    if len(flat) > 1 and (np.diff(flat) <= 0).any():
        raise ValueError("a pixel stands twice in its frame: keep first returns only")
    out, valid = np.zeros(len(sizes) * h * w, kind), np.zeros(len(sizes) * h * w, bool)
    out[flat], valid[flat] = b.column("v").flatten().to_numpy(), True
    return out.reshape(-1, h, w), valid.reshape(-1, h, w)


def _learned(net: anchor.Net, code: np.ndarray, valid: np.ndarray, d: float, i0: np.ndarray, j0: np.ndarray, extra=None) -> np.ndarray:
    """Predictions of all valid pixels, from contexts that are known when encoding."""
    out = np.zeros_like(code)
    b, i, j = np.nonzero(valid)
    for a in range(0, len(b), 20_000):
        x, y, z = b[a : a + 20_000], i[a : a + 20_000], j[a : a + 20_000]
        p = anchor.patch(net.spec, code, valid, x, y, z, i0[x], j0[x])
        if extra is not None:
            p = anchor.joined(p, extra(x, y, z, code))
        out[x, y, z] = net.predict(p, d)
    return out


def _rows(frames, block_rows, block_cols, code, delta, valid, spec: CodecSpec, model: str):
    """Container columns of blocks."""
    rows = []
    for f, br, bc, c, e, v in zip(frames, block_rows, block_cols, code, delta, valid):
        own = c[v]
        name, body = coders.smallest(e[v]) if spec.coder == "auto" else (spec.coder, coders.CODERS[spec.coder][0](e[v]))
        mask = masks.encode(v, spec.mask)
        rows.append((f, br, bc, spec.predictor, model, name, spec.precision, *v.shape, len(own), zlib.crc32(own.astype("<i8").tobytes()), int(own.min()), int(own.max()), mask, body, 8 * (len(mask) + len(body))))
    return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(list(zip(*rows)) or [[]] * len(TYPES), TYPES)], NAMES)


def encode(px: DataFrame, spec: CodecSpec = CodecSpec(), net: anchor.Net | None = None, size: tuple[int, int] | None = None) -> DataFrame:
    """Container rows of an image (frame_id, row, col, range), a row for each block with valid pixels; the mask counts toward bits.

    With size=(height, width), px is the image with its void pixels as null ranges, and every frame also gets a header row
    (predictor 'frame', block -1, no bits), so frames that are void throughout and the image's size survive."""
    h, w = spec.block
    ship(px.sparkSession)
    raw = net.dumps() if net else None
    model = net.model_id if net else ""

    def run(batches):
        own = anchor.Net.loads(raw) if raw else None
        for b in batches:
            code, valid = dense(b, h, w)
            rows, cols = b.column("block_row").to_numpy(), b.column("block_col").to_numpy()
            guess = _learned(own, code, valid, spec.precision, rows * h, cols * w) if own else predict(code, valid, spec.predictor)
            yield _rows(b.column("frame_id").to_pylist(), rows.tolist(), cols.tolist(), code, code - guess, valid, spec, model)

    out = to_blocks(px.where("range is not null"), spec).mapInArrow(run, CONTAINER)
    if size is None:
        return out
    head = px.groupBy("frame_id").agg(F.count("range").cast("int").alias("n_valid"))
    given = {"block_row": -1, "block_col": -1, "predictor": "frame", "model_id": "", "coder": "", "precision": spec.precision, "h": size[0], "w": size[1], "crc": 0, "min_code": 0, "max_code": 0, "mask_bytes": b"", "payload": b"", "bits": 0}
    return out.unionByName(head.select("frame_id", "n_valid", *(F.lit(bytearray(v) if isinstance(v, bytes) else v).cast(c.strip().split()[1]).alias(k) for k, v in given.items() for c in CONTAINER.split(",") if c.strip().split()[0] == k)))


def headers(container: DataFrame) -> DataFrame:
    return container.where("predictor = 'frame'").select("frame_id", F.col("h").alias("height"), F.col("w").alias("width"), "n_valid")


def _unpacked(x: dict) -> tuple[np.ndarray, np.ndarray]:
    valid = masks.decode(x["mask_bytes"], x["h"], x["w"])
    delta = np.zeros(valid.shape, np.int64)
    delta[valid] = coders.CODERS[x["coder"]][1](x["payload"])
    return delta, valid


def _checked(x: dict, code: np.ndarray, valid: np.ndarray) -> None:
    if zlib.crc32(code[valid].astype("<i8").tobytes()) != x["crc"]:
        raise ValueError(f"block {x['frame_id']}/{x['block_row']}/{x['block_col']}: checksum differs")


PIXELS = "frame_id long, row int, col int, code long, range double"


def _pixels(rows: list[dict], code, valid):
    """Arrow columns of decoded blocks."""
    got: list = [[] for _ in range(5)]
    for x, c, v in zip(rows, code, valid):
        _checked(x, c, v)
        r, k = np.nonzero(v)
        for to, y in zip(got, (np.full(len(r), x["frame_id"]), r + x["block_row"] * x["h"], k + x["block_col"] * x["w"], c[r, k], c[r, k] * x["precision"])):
            to.append(y)
    cols = [np.concatenate(g) if g else np.zeros(0) for g in got]
    return pa.RecordBatch.from_arrays([pa.array(c.astype(t)) for c, t in zip(cols, ("i8", "i4", "i4", "i8", "f8"))], ["frame_id", "row", "col", "code", "range"])


def decode_rows(rows: list[dict], net: anchor.Net | None = None) -> pa.RecordBatch:
    """Pixels of container rows; a block whose checksum differs or that names another model raises."""
    out = []
    by: dict = {}
    for x in rows:
        if x["predictor"] != "frame":
            by.setdefault((x["predictor"], x["h"], x["w"], x["precision"]), []).append(x)
    for (kind, h, w, d), some in by.items():
        delta, valid = (np.stack(v) for v in zip(*map(_unpacked, some)))
        if some[0]["model_id"]:
            if net is None or any(x["model_id"] != net.model_id for x in some):
                raise ValueError(f"these blocks were written with model {some[0]['model_id']}")
            code = anchor.wavefront(net, delta, valid, d, np.array([x["block_row"] * h for x in some]), np.array([x["block_col"] * w for x in some]))
        else:
            code = restore(delta, valid, kind)
        out.append(_pixels(some, code, valid))
    return pa.Table.from_batches(out).combine_chunks().to_batches()[0] if out and sum(o.num_rows for o in out) else _pixels([], [], [])


def decode(container: DataFrame, net: anchor.Net | None = None) -> DataFrame:
    """Pixels (frame_id, row, col, code, range) of a container."""
    ship(container.sparkSession)
    raw = net.dumps() if net else None

    def run(batches):
        own = anchor.Net.loads(raw) if raw else None
        for b in batches:
            yield decode_rows(b.to_pylist(), own)

    return container.mapInArrow(run, PIXELS)


def deltas(px: DataFrame, spec: CodecSpec, net: anchor.Net | None = None) -> DataFrame:
    """(frame_id, row, col, code, delta) in block form: no window over rows or columns, one exchange."""
    h, w = spec.block
    ship(px.sparkSession)
    raw = net.dumps() if net else None

    def run(batches):
        own = anchor.Net.loads(raw) if raw else None
        for b in batches:
            code, valid = dense(b, h, w)
            rows, cols, frames = (b.column(c).to_numpy() for c in ("block_row", "block_col", "frame_id"))
            guess = _learned(own, code, valid, spec.precision, rows * h, cols * w) if own else predict(code, valid, spec.predictor)
            n, i, j = np.nonzero(valid)
            yield pa.RecordBatch.from_arrays([pa.array(frames[n]), pa.array((rows[n] * h + i).astype(np.int32)), pa.array((cols[n] * w + j).astype(np.int32)), pa.array(code[n, i, j]), pa.array((code - guess)[n, i, j])], ["frame_id", "row", "col", "code", "delta"])

    return to_blocks(px, spec).mapInArrow(run, "frame_id long, row int, col int, code long, delta long")


# Temporal forms: all frames of a group of pictures of one block stand in one row.


def _extra(net: anchor.Net, before: tuple | None, d: float, sensor: Sensor | None, frame: int, valid: np.ndarray, i0: int, j0: int):
    """Function that gives the context points of the previous frame (time 1); before: its codes, mask and frame number."""
    spec = net.spec
    if spec.temporal == "image":
        di, dj = (np.r_[0, v] for v in spec.offsets)

        def image(b, i, j, code):
            r, c = i[:, None] - di, j[:, None] - dj
            ok = (r >= 0) & (c >= 0)
            r, c = np.maximum(r, 0), np.maximum(c, 0)
            ok &= before[1][r, c] if before else False
            return {"value": np.where(ok, before[0][r, c], 0) if before else np.zeros(ok.shape, np.int64), "ok": ok, **anchor.angles(spec, i, j, r, c, i0, j0), "time": np.ones(ok.shape, np.int64)}

        return image
    from .geometry import LocalTree

    half = spec.points // 2
    place = sensor.at(frame)
    tree = None
    if before:
        r, c = np.nonzero(before[1])
        cloud = sensor.at(before[2]) + sensor.directions[r + i0, c + j0] * (before[0][r, c] * d)[:, None]
        tree = LocalTree(cloud) if len(cloud) else None

    def near(b, i, j, code):
        """Left and up estimates make one query point each; what they find is seen from this shot's place."""
        n = len(i)
        blank = {"value": np.zeros((n, 2 * half), np.int64), "ok": np.zeros((n, 2 * half), bool), "daz": np.zeros((n, 2 * half), np.int64), "del": np.zeros((n, 2 * half), np.int64), "time": np.ones((n, 2 * half), np.int64)}
        if tree is None:
            return blank
        now = np.where(valid, code[0], 0)
        ray = sensor.directions[i + i0, j + j0]
        flat = np.maximum(np.sqrt(ray[:, 0] * ray[:, 0] + ray[:, 1] * ray[:, 1]), 1e-9)
        for side, (di, dj) in enumerate(((0, 1), (1, 0))):
            r, c = i - di, j - dj
            has = (r >= 0) & (c >= 0) & valid[np.maximum(r, 0), np.maximum(c, 0)]
            who = np.flatnonzero(has)
            if not len(who):
                continue
            guess = place + ray[who] * (now[r[who], c[who]] * d)[:, None]
            at, _ = tree.query(guess, half)
            seen = tree.points[np.maximum(at, 0)] - place
            x, y, z = seen[:, :, 0], seen[:, :, 1], seen[:, :, 2]
            ground = np.maximum(np.sqrt(x * x + y * y), 1e-9)
            away = np.maximum(np.sqrt(x * x + y * y + z * z), 1e-9)
            u, v = (ray[who, 0] / flat[who])[:, None], (ray[who, 1] / flat[who])[:, None]
            cols = slice(side * half, (side + 1) * half)
            blank["value"][who, cols] = np.floor(away / d + 0.5).astype(np.int64)
            blank["ok"][who, cols] = at >= 0
            blank["daz"][who, cols] = np.floor((u * y - v * x) / ground * 1e6).astype(np.int64)
            blank["del"][who, cols] = np.floor((z / away - ray[who, 2][:, None]) * 1e6).astype(np.int64)
        return blank

    return near


def _groups(px: DataFrame, spec: CodecSpec) -> DataFrame:
    b = to_blocks(px, spec).withColumn("gop", F.floor(F.col("frame_id") / spec.gop))
    rows = F.array_sort(F.collect_list(F.struct("frame_id", "r", "c", "v"))).alias("f")
    return b.groupBy("gop", "block_row", "block_col").agg(rows).select("block_row", "block_col", *(F.col(f"f.{c}").alias(c) for c in ("frame_id", "r", "c", "v")))


def _sequence(net, group: dict, spec: CodecSpec, sensor):
    """(frame, code, mask, deltas) of each frame of a group, predicted from the one before it."""
    h, w = spec.block
    before = None
    for f, r, c, v in zip(group["frame_id"], group["r"], group["c"], group["v"]):
        code, valid = np.zeros((1, h, w), np.int64), np.zeros((1, h, w), bool)
        code[0, r, c], valid[0, r, c] = v, True
        i0, j0 = group["block_row"] * h, group["block_col"] * w
        extra = _extra(net, before, spec.precision, sensor, f, valid[0], i0, j0) if net.spec.temporal != "none" else None
        guess = _learned(net, code, valid, spec.precision, np.array([i0]), np.array([j0]), extra)
        yield f, code[0], valid[0], code[0] - guess[0]
        before = (code[0], valid[0], f)


def deltas_temporal(px: DataFrame, spec: CodecSpec, net: anchor.Net, sensor: Sensor | None = None) -> DataFrame:
    h, w = spec.block
    ship(px.sparkSession)
    raw = net.dumps()

    def run(batches):
        own = anchor.Net.loads(raw)
        for b in batches:
            for g in b.to_pylist():
                for f, code, valid, delta in _sequence(own, g, spec, sensor):
                    i, j = np.nonzero(valid)
                    yield pa.RecordBatch.from_arrays([pa.array(np.full(len(i), f)), pa.array((g["block_row"] * h + i).astype(np.int32)), pa.array((g["block_col"] * w + j).astype(np.int32)), pa.array(code[i, j]), pa.array(delta[i, j])], ["frame_id", "row", "col", "code", "delta"])

    return _groups(px, spec).mapInArrow(run, "frame_id long, row int, col int, code long, delta long")


def encode_temporal(px: DataFrame, spec: CodecSpec, net: anchor.Net, sensor: Sensor | None = None) -> DataFrame:
    """Container rows of groups of pictures: the first frame of a group is a key frame, the others see the frame before them."""
    ship(px.sparkSession)
    raw, model = net.dumps(), net.model_id

    def run(batches):
        own = anchor.Net.loads(raw)
        for b in batches:
            for g in b.to_pylist():
                f, code, valid, delta = zip(*_sequence(own, g, spec, sensor))
                yield _rows(f, [g["block_row"]] * len(f), [g["block_col"]] * len(f), code, delta, valid, replace(spec, predictor=f"{own.spec.head}-{own.spec.temporal}"), model)

    return _groups(px, spec).mapInArrow(run, CONTAINER)


def decode_temporal(container: DataFrame, spec: CodecSpec, net: anchor.Net, sensor: Sensor | None = None) -> DataFrame:
    ship(container.sparkSession)
    raw = net.dumps()
    grouped = container.where("predictor <> 'frame'").withColumn("gop", F.floor(F.col("frame_id") / spec.gop))
    grouped = grouped.groupBy("gop", "block_row", "block_col").agg(F.array_sort(F.collect_list(F.struct(*NAMES))).alias("f"))

    def run(batches):
        own = anchor.Net.loads(raw)
        for b in batches:
            for group in b.column("f").to_pylist():
                before, out = None, []
                for x in group:
                    if x["model_id"] != own.model_id:
                        raise ValueError(f"these blocks were written with model {x['model_id']}")
                    delta, valid = _unpacked(x)
                    i0, j0 = x["block_row"] * x["h"], x["block_col"] * x["w"]
                    extra = _extra(own, before, x["precision"], sensor, x["frame_id"], valid, i0, j0) if own.spec.temporal != "none" else None
                    code = anchor.wavefront(own, delta[None], valid[None], x["precision"], np.array([i0]), np.array([j0]), extra)[0]
                    before = (code, valid, x["frame_id"])
                    out.append((x, code, valid))
                yield _pixels(*(list(v) for v in zip(*out)))

    return grouped.select("f").mapInArrow(run, PIXELS)


def bits_per_point(container: DataFrame, *by: str, include_mask: bool = True) -> DataFrame:
    bits = F.sum("bits") if include_mask else F.sum(8 * F.length("payload"))
    return container.where("predictor <> 'frame'").groupBy(*by).agg(F.round(bits / F.sum("n_valid"), 6).alias("bpp"), F.sum("n_valid").cast("long").alias("n_valid"))


def where_box(container: DataFrame, spec: CodecSpec, rows: tuple[int, int], cols: tuple[int, int]) -> DataFrame:
    """Only the blocks that a box of pixels touches: the pixel predicate turned into one on block keys, which the scan can use."""
    h, w = spec.block
    return container.where(F.col("block_row").between(rows[0] // h, rows[1] // h) & F.col("block_col").between(cols[0] // w, cols[1] // w))
