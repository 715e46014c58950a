"""Byte streams of the baselines, one row for each frame: octree, kd-tree, 16-bit image, field-wise points, and stand-ins (sur)
for video, cluster and transform coding. Codes of frames are independent, but for video, which sees the frame before."""

from __future__ import annotations

import zlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.shipping import ship
from . import coders

CODED = "frame_id long, n long, payload binary, bits long"


# Point codecs: integers x, y, z of every point of a frame.


def frames_of(points: DataFrame, scale: float, offset: float = 0.0) -> DataFrame:
    """(frame_id, x, y, z): arrays of the integer coordinates floor((v + offset) / scale + 0.5), in order of id."""
    q = {c: F.floor((F.col(c) + F.lit(float(offset))) / F.lit(float(scale)) + F.lit(0.5)).alias(c) for c in "xyz"}
    rows = F.array_sort(F.collect_list(F.struct("id", *"xyz"))).alias("p")
    return points.select("frame_id", "id", *q.values()).groupBy("frame_id").agg(rows).select("frame_id", *(F.col(f"p.{c}").alias(c) for c in "xyz"))


def morton(p: np.ndarray, depth: int) -> np.ndarray:
    key = np.zeros(len(p), np.int64)
    for i in range(depth):
        for k in range(3):
            key |= ((p[:, k] >> i) & 1) << (3 * i + k)
    return key


def unmorton(key: np.ndarray, depth: int) -> np.ndarray:
    out = np.zeros((len(key), 3), np.int64)
    for i in range(depth):
        for k in range(3):
            out[:, k] |= ((key >> (3 * i + k)) & 1) << i
    return out


def octree_pack(p: np.ndarray, depth: int, context: str = "parent") -> bytes:
    """Occupancy bytes level by level, adaptive arithmetic code; context: none, parent (children of the parent) or learned by the level too."""
    leaves = np.unique(morton(p, depth))
    levels, at = [], leaves
    for _ in range(depth):
        parent, where = np.unique(at >> 3, return_inverse=True)
        byte = np.zeros(len(parent), np.int64)
        np.bitwise_or.at(byte, where.ravel(), 1 << (at & 7))
        levels.append((parent, byte))
        at = parent
    levels.reverse()
    symbols, ctx, above = [], [], {}
    for n, (keys, bytes_) in enumerate(levels):
        for key, byte in zip(keys.tolist(), bytes_.tolist()):
            symbols.append(byte - 1)
            ctx.append(_octree_context(context, n, above.get(key >> 3, 0)))
        above = dict(zip(keys.tolist(), bytes_.tolist()))
    models: dict = {}

    def given():
        for c, s in zip(ctx, symbols):
            m = models.setdefault(c, coders._Adaptive(255, 32))
            yield m.cum()
            m.see(s)

    return coders.varints([len(leaves)]) + (coders.Range.encode_mixed(symbols, given()) if len(leaves) else b"")


def _octree_context(kind: str, level: int, parent: int) -> tuple:
    return () if kind == "none" else (bin(parent).count("1"),) if kind == "parent" else (min(level, 7), bin(parent).count("1"))


def octree_unpack(raw: bytes, depth: int, context: str = "parent") -> np.ndarray:
    """The distinct points, in Morton order."""
    (n,), at = coders.unvarints(raw, 1)
    if not n:
        return np.zeros((0, 3), np.int64)
    step, models, keys, above = coders.Range.decoder(raw[at:]), {}, [0], {}
    for level in range(depth):
        below, now = [], {}
        for key in keys:
            m = models.setdefault(_octree_context(context, level, above.get(key >> 3, 0) if level else 0), coders._Adaptive(255, 32))
            s = step(m.cum())
            m.see(s)
            now[key] = s + 1
            below += [key << 3 | b for b in range(8) if (s + 1) >> b & 1]
        keys, above = below, now
    return unmorton(np.array(keys, np.int64), depth)


class _Bits:
    def __init__(self):
        self.value, self.size = 0, 0

    def put(self, v: int, n: int) -> None:
        self.value, self.size = self.value << n | v, self.size + n

    def bytes(self) -> bytes:
        return (self.value << (-self.size % 8)).to_bytes((self.size + 7) // 8, "big")


def kdtree_pack(p: np.ndarray, depth: int) -> bytes:
    """Cells are halved along x, y, z in turns; each half is told by the number of points on its lower side. Repeats are kept."""
    bits = _Bits()
    bits.put(len(p), 32)
    todo = [(p, 3 * depth)]
    while todo:
        some, left = todo.pop()
        if not left or not len(some):
            continue
        if len(some) == 1:  # a single point: the rest of its bits as they are
            for k in range(left):
                axis, bit = (3 * depth - left + k) % 3, depth - 1 - (3 * depth - left + k) // 3
                bits.put(int(some[0, axis] >> bit & 1), 1)
            continue
        axis, bit = (3 * depth - left) % 3, depth - 1 - (3 * depth - left) // 3
        high = (some[:, axis] >> bit & 1).astype(bool)
        bits.put(int((~high).sum()), int(len(some)).bit_length())
        todo += [(some[high], left - 1), (some[~high], left - 1)]
    return bits.bytes()


def kdtree_unpack(raw: bytes, depth: int) -> np.ndarray:
    flat, at, out = np.unpackbits(np.frombuffer(raw, np.uint8)), 0, []

    def take(n):
        nonlocal at
        v = int("".join(map(str, flat[at : at + n])) or "0", 2)
        at += n
        return v

    todo = [(take(32), (0, 0, 0), 3 * depth)]
    while todo:
        n, cell, left = todo.pop()
        if not n:
            continue
        if not left:
            out += [cell] * n
            continue
        if n == 1:
            c = list(cell)
            for k in range(left):
                axis, bit = (3 * depth - left + k) % 3, depth - 1 - (3 * depth - left + k) // 3
                c[axis] |= take(1) << bit
            out.append(tuple(c))
            continue
        axis, bit = (3 * depth - left) % 3, depth - 1 - (3 * depth - left) // 3
        low = take(n.bit_length())
        up = tuple(v | (1 << bit) if i == axis else v for i, v in enumerate(cell))
        todo += [(n - low, up, left - 1), (low, cell, left - 1)]
    return np.array(out, np.int64).reshape(-1, 3)


def fieldwise_pack(p: np.ndarray) -> bytes:
    """Differences to the point before, axis by axis, each arithmetic coded."""
    parts = [coders.arith(np.diff(p[:, k], prepend=0)) for k in range(3)]
    return coders.varints([len(x) for x in parts]) + b"".join(parts)


def fieldwise_unpack(raw: bytes) -> np.ndarray:
    sizes, at = coders.unvarints(raw, 3)
    cols = []
    for n in sizes.astype(int).tolist():
        cols.append(np.cumsum(coders.unarith(raw[at : at + n])))
        at += n
    return np.stack(cols, 1)


POINTS = {
    "octree": (lambda p, depth: octree_pack(p, depth), lambda raw, depth: octree_unpack(raw, depth)),
    "octree_none": (lambda p, depth: octree_pack(p, depth, "none"), lambda raw, depth: octree_unpack(raw, depth, "none")),
    "octree_level": (lambda p, depth: octree_pack(p, depth, "level"), lambda raw, depth: octree_unpack(raw, depth, "level")),
    "kdtree": (kdtree_pack, kdtree_unpack),
    "fieldwise": (lambda p, depth: fieldwise_pack(p), lambda raw, depth: fieldwise_unpack(raw)),
}


def encode_points(frames: DataFrame, method: str, depth: int) -> DataFrame:
    """frames: arrays x, y, z of non-negative integers below 2**depth (field-wise: any integers)."""
    ship(frames.sparkSession)
    pack = POINTS[method][0]

    def run(batches):
        for b in batches:
            rows = []
            for f, *xyz in zip(*(b.column(c).to_pylist() for c in ("frame_id", "x", "y", "z"))):
                p = np.array(xyz, np.int64).T.reshape(-1, 3)
                if method != "fieldwise" and len(p) and (p.min() < 0 or p.max() >= 1 << depth):
                    raise ValueError(f"frame {f}: coordinates outside the cube")
                raw = pack(p, depth)
                rows.append((f, len(p), raw, 8 * len(raw)))
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(list(zip(*rows)) or [[]] * 4, (pa.int64(), pa.int64(), pa.binary(), pa.int64()))], ["frame_id", "n", "payload", "bits"])

    return frames.mapInArrow(run, CODED)


def decode_points(coded: DataFrame, method: str, depth: int) -> DataFrame:
    """(frame_id, x, y, z): the octree gives distinct points, the others all of them."""
    ship(coded.sparkSession)
    unpack = POINTS[method][1]

    def run(batches):
        for b in batches:
            for f, raw in zip(b.column("frame_id").to_pylist(), b.column("payload").to_pylist()):
                p = unpack(raw, depth)
                yield pa.RecordBatch.from_arrays([pa.array(np.full(len(p), f)), *(pa.array(p[:, k].copy()) for k in range(3))], ["frame_id", "x", "y", "z"])

    return coded.mapInArrow(run, "frame_id long, x long, y long, z long")


# Image codecs: 16-bit images of a frame; void pixels are 0.


def images_of(px: DataFrame, scale: float) -> DataFrame:
    """(frame_id, height, width, r, c, v): the pixels of each frame with 16-bit values floor(range * scale + 0.5), at least 1."""
    v = F.greatest(F.lit(1), F.least(F.lit(65535), F.floor(F.col("range") * F.lit(float(scale)) + F.lit(0.5)))).cast("long").alias("v")
    rows = F.array_sort(F.collect_list(F.struct("row", "col", "v"))).alias("p")
    got = px.select("frame_id", "row", "col", v).groupBy("frame_id").agg((F.max("row") + 1).alias("height"), (F.max("col") + 1).alias("width"), rows)
    return got.select("frame_id", "height", "width", F.col("p.row").alias("r"), F.col("p.col").alias("c"), F.col("p.v").alias("v"))


def _gradient(a, b, c):
    p = a + b - c
    pa_, pb_, pc_ = np.abs(p - a), np.abs(p - b), np.abs(p - c)
    return np.where((pa_ <= pb_) & (pa_ <= pc_), a, np.where(pb_ <= pc_, b, c))


def png16_pack(v: np.ndarray) -> bytes:
    """Each row under the filter (none, left, up, mean, gradient) of least absolute sum, then DEFLATE; two bytes a value, high first."""
    left, up = np.pad(v, ((0, 0), (1, 0)))[:, :-1], np.pad(v, ((1, 0), (0, 0)))[:-1]
    corner = np.pad(left, ((1, 0), (0, 0)))[:-1]
    made = np.stack([v, v - left, v - up, v - (left + up) // 2, v - _gradient(left, up, corner)])
    wrapped = (made + 32768) % 65536 - 32768
    best = np.abs(wrapped).sum(2).argmin(0)
    rows = made[best, np.arange(len(v))] % 65536
    return zlib.compress(best.astype(np.uint8).tobytes() + rows.astype(">u2").tobytes(), 9)


def png16_unpack(raw: bytes, h: int, w: int) -> np.ndarray:
    raw = zlib.decompress(raw)
    best, rows = raw[:h], np.frombuffer(raw[h:], ">u2").reshape(h, w).astype(np.int64)
    out = np.zeros((h + 1, w + 1), np.int64)
    for i in range(h):
        up, kind = out[i, 1:], best[i]
        if kind in (0, 2):
            out[i + 1, 1:] = rows[i] + (up if kind == 2 else 0)
        elif kind == 1:
            out[i + 1, 1:] = np.cumsum(rows[i])
        else:
            a, ups = 0, out[i].tolist()
            line = []
            for x, (r, b, c) in enumerate(zip(rows[i].tolist(), ups[1:], ups)):
                if kind == 3:
                    guess = (a + b) // 2
                else:
                    p = a + b - c
                    x, y, z = abs(p - a), abs(p - b), abs(p - c)
                    guess = a if x <= y and x <= z else b if y <= z else c
                a = (r + guess) % 65536
                line.append(a)
            out[i + 1, 1:] = line
        out[i + 1, 1:] %= 65536
    return out[1:, 1:]


def _flow(before: np.ndarray, v: np.ndarray, size: int, reach: int) -> tuple[np.ndarray, np.ndarray]:
    """For each block the shift of the frame before with the least absolute difference, and the prediction they make."""
    h, w = v.shape
    shifts = [(a, b) for a in range(-reach, reach + 1) for b in range(-reach, reach + 1)]
    shifts.sort(key=lambda s: (abs(s[0]) + abs(s[1]), s))
    padded = np.pad(before, reach)
    moved = np.stack([padded[reach + a : reach + a + h, reach + b : reach + b + w] for a, b in shifts])
    cost = np.abs(moved - v)
    rows, cols = np.arange(0, h, size), np.arange(0, w, size)
    cost = np.add.reduceat(np.add.reduceat(cost, rows, 1), cols, 2)
    best = cost.argmin(0)
    return best, np.take_along_axis(moved, np.repeat(np.repeat(best, size, 0), size, 1)[None, :h, :w], 0)[0]


def _flow_from(before, best, size, reach, h, w):
    shifts = [(a, b) for a in range(-reach, reach + 1) for b in range(-reach, reach + 1)]
    shifts.sort(key=lambda s: (abs(s[0]) + abs(s[1]), s))
    padded = np.pad(before, reach)
    moved = np.stack([padded[reach + a : reach + a + h, reach + b : reach + b + w] for a, b in shifts])
    return np.take_along_axis(moved, np.repeat(np.repeat(best, size, 0), size, 1)[None, :h, :w], 0)[0]


def video_pack(v: np.ndarray, before: np.ndarray | None, size: int = 8, reach: int = 2) -> bytes:
    """Stand-in for a video codec: every block from a shifted block of the frame before (the first frame: from its left neighbours)."""
    if before is None or before.shape != v.shape:
        body = coders.smallest((v - np.pad(v, ((0, 0), (1, 0)))[:, :-1]).ravel())
        flow = b""
    else:
        best, guess = _flow(before, v, size, reach)
        flow, body = zlib.compress(best.astype(np.uint8).tobytes(), 9), coders.smallest((v - guess).ravel())
    name = body[0].encode()
    return coders.varints([len(flow), len(name)]) + flow + name + body[1]


def video_unpack(raw: bytes, before: np.ndarray | None, h: int, w: int, size: int = 8, reach: int = 2) -> np.ndarray:
    (n, m), at = coders.unvarints(raw, 2)
    flow, name, body = raw[at : at + int(n)], raw[at + int(n) : at + int(n) + int(m)].decode(), raw[at + int(n) + int(m) :]
    delta = coders.CODERS[name][1](body).reshape(h, w)
    if not n:
        return np.cumsum(delta, axis=1)
    best = np.frombuffer(zlib.decompress(flow), np.uint8).reshape(-(-h // size), -(-w // size)).astype(np.int64)
    return delta + _flow_from(before, best, size, reach, h, w)


def clusters(v: np.ndarray, gap: int) -> np.ndarray:
    """Connected parts of a range image: neighbours in rows and columns whose values differ by `gap` at most; void is 0."""
    h, w = v.shape
    label = np.where(v > 0, np.arange(1, h * w + 1).reshape(h, w), 0)
    right = (v[:, 1:] > 0) & (v[:, :-1] > 0) & (np.abs(v[:, 1:] - v[:, :-1]) <= gap)
    down = (v[1:] > 0) & (v[:-1] > 0) & (np.abs(v[1:] - v[:-1]) <= gap)
    while True:
        new = label.copy()
        for a, b, ok in ((new[:, 1:], new[:, :-1], right), (new[1:], new[:-1], down)):
            low = np.minimum(a, b)
            a[ok], b[ok] = low[ok], low[ok]
        jump = np.r_[0, np.arange(1, h * w + 1)]
        flat = new.ravel()
        jump[flat[flat > 0]] = flat[flat - 1][flat > 0] if len(flat) else 0
        new = np.minimum(new, np.where(new > 0, flat[np.maximum(new - 1, 0)], 0))
        if (new == label).all():
            return label
        label = new


def cluster_pack(v: np.ndarray, ground: np.ndarray, gap: int = 60) -> bytes:
    """Stand-in for a segmenting codec: ground pixels as differences to the fitted plane, the others to the pixel before them in their part."""
    near = (v > 0) & (np.abs(v - ground) <= gap)
    part = np.where(near, 0, clusters(np.where(near, 0, v), gap))
    order = np.lexsort((np.arange(v.size), part.ravel()))
    order = order[(part.ravel()[order] > 0)]
    values = v.ravel()[order]
    new = np.r_[True, part.ravel()[order][1:] != part.ravel()[order][:-1]] if len(order) else np.zeros(0, bool)
    step = np.where(new, values, values - np.r_[0, values[:-1]]) if len(order) else values
    where = np.searchsorted(np.unique(np.r_[0, part.ravel()]), part.ravel())  # 0 is void or ground, parts from 1
    streams = [coders.rle_lzma(where - near.ravel()), coders.smallest((v - ground)[near]), coders.smallest(step)]
    head = [len(streams[0]), len(streams[1][1]), list(coders.CODERS).index(streams[1][0]), list(coders.CODERS).index(streams[2][0])]
    return coders.varints(head) + streams[0] + streams[1][1] + streams[2][1]


def cluster_unpack(raw: bytes, ground: np.ndarray) -> np.ndarray:
    (a, b, x, y), at = coders.unvarints(raw, 4)
    kinds = list(coders.CODERS.values())
    where = coders.unrle_lzma(raw[at : at + int(a)]).reshape(ground.shape)
    at += int(a)
    on_ground, step = kinds[int(x)][1](raw[at : at + int(b)]), kinds[int(y)][1](raw[at + int(b) :])
    out = np.zeros(ground.shape, np.int64)
    out[where == -1] = ground[where == -1] + on_ground
    flat = where.ravel()
    order = np.lexsort((np.arange(flat.size), flat))
    order = order[flat[order] > 0]
    if len(order):
        new = np.flatnonzero(np.r_[True, flat[order][1:] != flat[order][:-1]])
        total = np.cumsum(step)
        back = np.repeat(total[new] - step[new], np.diff(np.r_[new, len(order)]))
        out.ravel()[order] = total - back
    return out


def _dct(n: int = 8) -> np.ndarray:
    k = np.arange(n)
    m = np.cos(np.pi * (2 * k[None, :] + 1) * k[:, None] / (2 * n)) * np.sqrt(2 / n)
    m[0] /= np.sqrt(2)
    return m


def dct8(v: np.ndarray, step: float) -> tuple[np.ndarray, bytes]:
    """Lossy transform coding: 8 x 8 cosine transform, coefficients rounded to multiples of step. Returns the decoded image and the bytes."""
    h, w = v.shape
    p = np.pad(v.astype(float), ((0, -h % 8), (0, -w % 8)), mode="edge")
    b = p.reshape(p.shape[0] // 8, 8, p.shape[1] // 8, 8).transpose(0, 2, 1, 3)
    m = _dct()
    q = np.round(m @ b @ m.T / step).astype(np.int64)
    back = (m.T @ (q * step) @ m).transpose(0, 2, 1, 3).reshape(p.shape)[:h, :w]
    return back, coders.varint_lzma(q.transpose(2, 3, 0, 1).ravel())


def _image(x: dict) -> np.ndarray:
    v = np.zeros((x["height"], x["width"]), np.int64)
    v[x["r"], x["c"]] = x["v"]
    return v


IMAGE = "frame_id long, height int, width int, n long, payload binary, bits long"


def encode_images(images: DataFrame, method: str, ground: DataFrame | None = None, gop: int = 4) -> DataFrame:
    """png16 and cluster: frame by frame; video: groups of `gop` frames in one task. ground: rows (row, g), the plane's 16-bit value."""
    ship(images.sparkSession)
    plane = dict(ground.collect()) if ground is not None else {}  # one value for each laser row

    def coded(x: dict, v: np.ndarray, before):
        raw = png16_pack(v) if method == "png16" else video_pack(v, before) if method == "video" else cluster_pack(v, _ground(plane, v.shape))
        return x["frame_id"], x["height"], x["width"], len(x["r"]), raw, 8 * len(raw)

    def run(batches):
        for b in batches:
            rows = []
            for x in b.to_pylist():
                before = None
                for y in x["f"]:
                    v = _image(y)
                    rows.append(coded(y, v, before))
                    before = v
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(list(zip(*rows)) or [[]] * 6, (pa.int64(), pa.int32(), pa.int32(), pa.int64(), pa.binary(), pa.int64()))], ["frame_id", "height", "width", "n", "payload", "bits"])

    size = gop if method == "video" else 1
    rows = F.array_sort(F.collect_list(F.struct("frame_id", "height", "width", "r", "c", "v"))).alias("f")
    return images.groupBy(F.floor(F.col("frame_id") / size).alias("gop")).agg(rows).select("f").mapInArrow(run, IMAGE)


def _ground(plane: dict, shape) -> np.ndarray:
    return np.repeat(np.array([plane.get(i, 0) for i in range(shape[0])], np.int64)[:, None], shape[1], 1)


def decode_images(coded: DataFrame, method: str, ground: DataFrame | None = None, gop: int = 4) -> DataFrame:
    """(frame_id, row, col, v) of the pixels that are not void."""
    ship(coded.sparkSession)
    plane = dict(ground.collect()) if ground is not None else {}

    def run(batches):
        for b in batches:
            for x in b.to_pylist():
                before = None
                for y in x["f"]:
                    h, w = y["height"], y["width"]
                    v = png16_unpack(y["payload"], h, w) if method == "png16" else video_unpack(y["payload"], before, h, w) if method == "video" else cluster_unpack(y["payload"], _ground(plane, (h, w)))
                    before = v
                    r, c = np.nonzero(v)
                    yield pa.RecordBatch.from_arrays([pa.array(np.full(len(r), y["frame_id"])), pa.array(r.astype(np.int32)), pa.array(c.astype(np.int32)), pa.array(v[r, c])], ["frame_id", "row", "col", "v"])

    size = gop if method == "video" else 1
    rows = F.array_sort(F.collect_list(F.struct("frame_id", "height", "width", "payload"))).alias("f")
    return coded.groupBy(F.floor(F.col("frame_id") / size).alias("gop")).agg(rows).select("f").mapInArrow(run, "frame_id long, row int, col int, v long")


def ground_rows(px: DataFrame, scale: float) -> DataFrame:
    """(row, g): the 16-bit value of the ground in each laser row, where the fit -h / dz has one: h is the least-squares height.

    px has dz beside range; the height is fitted on the rows that look down, from three sums."""
    low = px.where("dz < 0")
    height = low.agg((F.sum(F.col("range") * -1 / F.col("dz")) / F.sum(1 / (F.col("dz") * F.col("dz")))).alias("h"))
    rows = low.groupBy("row").agg(F.min("dz").alias("dz")).crossJoin(F.broadcast(height))
    return rows.select("row", F.least(F.lit(65535), F.floor(-F.col("h") / F.col("dz") * F.lit(float(scale)) + F.lit(0.5))).cast("long").alias("g"))


# Auto-encoder stand-in: principal components of patches.


def patches(px: DataFrame, size: int) -> DataFrame:
    """(frame_id, block_row, block_col, v): square patches of ranges without void pixels, as arrays in raster order."""
    at = px.select("frame_id", F.floor(F.col("row") / size).alias("block_row"), F.floor(F.col("col") / size).alias("block_col"), "row", "col", "range")
    rows = F.array_sort(F.collect_list(F.struct("row", "col", "range"))).alias("p")
    return at.groupBy("frame_id", "block_row", "block_col").agg(rows).where(F.size("p") == size * size).select("frame_id", "block_row", "block_col", F.col("p.range").alias("v"))


def components(patch: DataFrame, k: int) -> tuple[np.ndarray, np.ndarray]:
    """Mean and the k first principal components; sums of products are aggregated by the executors, the driver gets one matrix."""
    pos = patch.select(F.posexplode("v").alias("i", "a"), "v")
    pair = pos.select("i", "a", F.posexplode("v").alias("j", "b")).groupBy("i", "j").agg(F.avg(F.col("a") * F.col("b")).alias("ab"), F.avg("a").alias("a"))
    got = pair.collect()
    n = max((r.i for r in got), default=-1) + 1
    m, mean = np.zeros((n, n)), np.zeros(n)
    for r in got:
        m[r.i, r.j], mean[r.i] = r.ab, r.a
    value, vector = np.linalg.eigh(m - np.outer(mean, mean))
    vector = vector[:, ::-1][:, :k]
    return mean, vector * np.where(vector[np.abs(vector).argmax(0), np.arange(vector.shape[1])] < 0, -1, 1)


def autoencode(patch: DataFrame, mean: np.ndarray, basis: np.ndarray, step: float) -> DataFrame:
    """(frame_id, block_row, block_col, codes, back): bottleneck codes rounded to multiples of step, and the decoded patch."""
    ship(patch.sparkSession)

    def run(batches):
        for b in batches:
            v = np.array(b.column("v").to_pylist(), float).reshape(-1, len(mean))
            q = np.round((v - mean) @ basis / step).astype(np.int64)
            back = q * step @ basis.T + mean
            yield pa.RecordBatch.from_arrays([b.column("frame_id"), b.column("block_row"), b.column("block_col"), pa.array(list(q), pa.list_(pa.int64())), pa.array(list(back), pa.list_(pa.float64()))], ["frame_id", "block_row", "block_col", "codes", "back"])

    return patch.mapInArrow(run, "frame_id long, block_row long, block_col long, codes array<long>, back array<double>")
