"""Coders of validity masks: which pixels of a block have a return. Each output starts with the name of its method (one byte)."""

from __future__ import annotations

import lzma
import zlib

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import coders

_FILTERS = [{"id": lzma.FILTER_LZMA2, "preset": 6, "dict_size": 1 << 16}]


def _runs(v: np.ndarray) -> bytes:
    """Lengths of alternating runs, void first."""
    flat = np.r_[False, v.ravel()]
    at = np.flatnonzero(np.r_[True, flat[1:] != flat[:-1]])
    lengths = np.diff(np.r_[at, len(flat)])
    lengths[0] -= 1
    return coders.varints(lengths)


def _unruns(raw: bytes, h: int, w: int) -> np.ndarray:
    n, _ = coders.unvarints(raw)
    return np.repeat(np.arange(len(n)) % 2 == 1, n.astype(np.int64)).reshape(h, w)


def _contexts(v: np.ndarray) -> np.ndarray:
    """Number of the neighbourhood (left, up, up-left, up-right) of every pixel."""
    p = np.pad(v.astype(np.int64), ((1, 0), (1, 1)))
    return p[1:, :-2] + 2 * p[:-1, 1:-1] + 4 * p[:-1, :-2] + 8 * p[:-1, 2:]


def _arith2d(v: np.ndarray) -> bytes:
    """Arithmetic code of each pixel given its neighbourhood; the 16 pairs of counts stand in front."""
    ctx, bit = _contexts(v).ravel(), v.ravel().astype(np.int64)
    counts = np.bincount(2 * ctx + bit, minlength=32).reshape(16, 2)
    scaled = np.maximum(1, counts * 4096 // np.maximum(1, counts.sum(1, keepdims=True)))
    cum = [[0, int(a), int(a + b)] for a, b in scaled]
    return coders.varints(scaled.ravel()) + coders.Range.encode_mixed(bit.tolist(), [cum[c] for c in ctx.tolist()])


def _unarith2d(raw: bytes, h: int, w: int) -> np.ndarray:
    scaled, at = coders.unvarints(raw, 32)
    cum = [[0, int(a), int(a + b)] for a, b in scaled.reshape(16, 2)]
    out = [[0] * (w + 2) for _ in range(h + 1)]
    step = coders.Range.decoder(raw[at:])
    for i in range(1, h + 1):
        up, row = out[i - 1], out[i]
        for j in range(1, w + 1):
            row[j] = step(cum[row[j - 1] + 2 * up[j] + 4 * up[j - 1] + 8 * up[j + 1]])
    return np.array(out, bool)[1:, 1:-1]


def _bits(raw: bytes, h: int, w: int) -> np.ndarray:
    return np.unpackbits(np.frombuffer(raw, np.uint8), count=h * w).reshape(h, w).astype(bool)


METHODS = {
    "raw": (lambda v: np.packbits(v).tobytes(), _bits),
    "rle": (_runs, _unruns),
    "deflate": (lambda v: zlib.compress(np.packbits(v).tobytes(), 9), lambda raw, h, w: _bits(zlib.decompress(raw), h, w)),
    "lzma": (lambda v: lzma.compress(np.packbits(v).tobytes(), lzma.FORMAT_RAW, filters=_FILTERS), lambda raw, h, w: _bits(lzma.decompress(raw, lzma.FORMAT_RAW, filters=_FILTERS), h, w)),
    "arith2d": (_arith2d, _unarith2d),
}
ORDER = list(METHODS)


def encode(valid: np.ndarray, method: str = "auto") -> bytes:
    """auto: the shortest of the methods that run at native speed (raw, rle, deflate)."""
    names = ("raw", "rle", "deflate") if method == "auto" else (method,)
    return min((bytes([ORDER.index(n)]) + METHODS[n][0](valid) for n in names), key=len)


def decode(raw: bytes, h: int, w: int) -> np.ndarray:
    return METHODS[ORDER[raw[0]]][1](raw[1:], h, w)


def mask_words(px: DataFrame, width: int = 32) -> DataFrame:
    """Masks as words of `width` bits in SQL: (frame_id, row, word, bits, n), bit k of a word for column word * width + k."""
    at = px.select("frame_id", "row", F.floor(F.col("col") / width).cast("int").alias("word"), F.expr(f"shiftleft(1L, cast(col % {width} as int))").alias("bit"))
    return at.groupBy("frame_id", "row", "word").agg(F.bit_or("bit").alias("bits"), F.count(F.lit(1)).alias("n"))
