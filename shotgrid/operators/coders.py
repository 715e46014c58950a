"""Entropy coders of residual streams: exact inverses on integer arrays, used block by block inside Arrow tasks."""

from __future__ import annotations

import heapq
import lzma
import zlib
from bisect import bisect_right
from collections import Counter

import numpy as np

_FILTERS = [{"id": lzma.FILTER_LZMA2, "preset": 6, "dict_size": 1 << 20}]


def zigzag(x: np.ndarray) -> np.ndarray:
    x = x.astype(np.int64)
    return ((x << 1) ^ (x >> 63)).astype(np.uint64)


def unzigzag(u: np.ndarray) -> np.ndarray:
    u = u.astype(np.uint64)
    return (u >> np.uint64(1)).astype(np.int64) ^ -(u & np.uint64(1)).astype(np.int64)


def varints(u) -> bytes:
    """Seven bits a byte, low ones first; the high bit says that more follow."""
    u = np.asarray(u).astype(np.uint64).ravel()
    if not len(u):
        return b""
    groups = np.ones(len(u), np.int64)
    for k in range(1, 10):
        groups += u >= np.uint64(1 << (7 * k))
    width = int(groups.max())
    at = np.arange(width)
    part = (u[:, None] >> (7 * at).astype(np.uint64)).astype(np.uint8) & 127
    part |= np.where(at < groups[:, None] - 1, 128, 0).astype(np.uint8)
    return part[at < groups[:, None]].tobytes()


def unvarints(raw: bytes, n: int | None = None) -> tuple[np.ndarray, int]:
    """n values (or all) and the bytes that they took."""
    b = np.frombuffer(raw if n is None else raw[: 10 * n], np.uint8)
    ends = np.flatnonzero(b < 128)[:n]
    if not len(ends):
        return np.zeros(0, np.uint64), 0
    b = b[: ends[-1] + 1].astype(np.uint64)
    starts = np.r_[0, ends[:-1] + 1]
    place = np.arange(len(b)) - np.repeat(starts, ends - starts + 1)
    return np.bitwise_or.reduceat((b & np.uint64(127)) << (7 * place).astype(np.uint64), starts), len(b)


class Range:
    """Integer arithmetic coder with a carry-less 32-bit range, total frequency at most 2**16.

    cum holds the cumulative counts of an alphabet: symbol s takes cum[s]..cum[s + 1]."""

    TOP, LOW = 1 << 24, 1 << 16

    @classmethod
    def encode(cls, symbols: list[int], cum: list[int]) -> bytes:
        return cls.encode_mixed(symbols, [cum] * len(symbols))

    @classmethod
    def encode_mixed(cls, symbols: list[int], models) -> bytes:
        """Every symbol under a model of its own; models may be an iterator that adapts to the symbols before."""
        low, rng, out, top, least = 0, 0xFFFFFFFF, bytearray(), cls.TOP, cls.LOW
        for s, cum in zip(symbols, models):
            rng //= cum[-1]
            low += cum[s] * rng
            rng *= cum[s + 1] - cum[s]
            while (low ^ (low + rng)) < top or rng < least:
                if (low ^ (low + rng)) >= top:
                    rng = -low & (least - 1)
                out.append(low >> 24 & 255)
                low, rng = low << 8 & 0xFFFFFFFF, rng << 8
        return bytes(out) + low.to_bytes(4, "big")

    @classmethod
    def decoder(cls, raw: bytes):
        """A function that gives the next symbol under a model."""
        low, rng, at, code, top, least = 0, 0xFFFFFFFF, 4, int.from_bytes(raw[:4].ljust(4, b"\0"), "big"), cls.TOP, cls.LOW

        def step(cum: list[int]) -> int:
            nonlocal low, rng, at, code
            rng //= cum[-1]
            s = bisect_right(cum, min(cum[-1] - 1, ((code - low) & 0xFFFFFFFF) // rng)) - 1
            low += cum[s] * rng
            rng *= cum[s + 1] - cum[s]
            while (low ^ (low + rng)) < top or rng < least:
                if (low ^ (low + rng)) >= top:
                    rng = -low & (least - 1)
                code = (code << 8 | (raw[at] if at < len(raw) else 0)) & 0xFFFFFFFF
                low, rng = low << 8 & 0xFFFFFFFF, rng << 8
                at += 1
            return s

        return step

    @classmethod
    def decode(cls, raw: bytes, n: int, cum: list[int]) -> list[int]:
        step = cls.decoder(raw)
        return [step(cum) for _ in range(n)]


def _scaled(counts: list[int]) -> list[int]:
    total = sum(counts)
    return [max(1, c * 32768 // total) for c in counts] if total > 32768 else counts


def arith(x: np.ndarray) -> bytes:
    """Static order-0 arithmetic code: alphabet and counts in front, then the coded symbols."""
    values, where, counts = np.unique(x, return_inverse=True, return_counts=True)
    head = varints([len(x), len(values)])
    if not len(x):
        return head
    counts = _scaled(counts.tolist())
    return head + varints(zigzag(np.diff(values, prepend=0))) + varints(counts) + Range.encode(where.ravel().tolist(), np.r_[0, np.cumsum(counts)].tolist())


def unarith(raw: bytes) -> np.ndarray:
    (n, k), at = unvarints(raw, 2)
    if not n:
        return np.zeros(0, np.int64)
    steps, used = unvarints(raw[at:], int(k))
    at += used
    counts, used = unvarints(raw[at:], int(k))
    at += used
    values = np.cumsum(unzigzag(steps))
    return values[Range.decode(raw[at:], int(n), np.r_[0, np.cumsum(counts.astype(np.int64))].tolist())]


def _alphabet(x: np.ndarray) -> tuple[bytes, np.ndarray, np.ndarray]:
    values, where = np.unique(x, return_inverse=True)
    return varints([len(x), len(values)]) + varints(zigzag(np.diff(values, prepend=0))), values, where.ravel()


def _unalphabet(raw: bytes) -> tuple[int, np.ndarray, int]:
    (n, k), at = unvarints(raw, 2)
    steps, used = unvarints(raw[at:], int(k))
    return int(n), np.cumsum(unzigzag(steps)), at + used


class _Adaptive:
    """Counts that start at 1 and grow with every symbol, halved before their sum leaves the coder's bounds."""

    def __init__(self, size: int, grow: int = 24):
        self.counts, self.grow = [1] * size, grow

    def cum(self) -> list[int]:
        out, total = [0], 0
        for c in self.counts:
            total += c
            out.append(total)
        return out

    def see(self, s: int) -> None:
        self.counts[s] += self.grow
        if sum(self.counts) > 60_000:
            self.counts = [(c + 1) >> 1 for c in self.counts]


def arith_adaptive(x: np.ndarray) -> bytes:
    """Adaptive order-0 arithmetic code: only the alphabet stands in front, counts are learned on the way."""
    head, values, where = _alphabet(x)
    model = _Adaptive(len(values))

    def models():
        for s in where.tolist():
            yield model.cum()
            model.see(s)

    return head + Range.encode_mixed(where.tolist(), models()) if len(x) else head


def unarith_adaptive(raw: bytes) -> np.ndarray:
    n, values, at = _unalphabet(raw)
    if not n:
        return np.zeros(0, np.int64)
    model, step, out = _Adaptive(len(values)), Range.decoder(raw[at:]), []
    for _ in range(n):
        out.append(step(model.cum()))
        model.see(out[-1])
    return values[out]


def arith_ctx(x: np.ndarray) -> bytes:
    """Adaptive arithmetic code with a model for each size class (0, 1 to 2, more) of the residual before."""
    head, values, where = _alphabet(x)
    size = np.minimum(np.abs(np.r_[0, x[:-1]]), 3) if len(x) else x
    ctx, kinds = np.array([0, 1, 1, 2])[size].tolist() if len(x) else [], [_Adaptive(len(values)) for _ in range(3)]

    def models():
        for c, s in zip(ctx, where.tolist()):
            yield kinds[c].cum()
            kinds[c].see(s)

    return head + Range.encode_mixed(where.tolist(), models()) if len(x) else head


def unarith_ctx(raw: bytes) -> np.ndarray:
    n, values, at = _unalphabet(raw)
    if not n:
        return np.zeros(0, np.int64)
    kinds, step, out, sizes = [_Adaptive(len(values)) for _ in range(3)], Range.decoder(raw[at:]), [], np.array([0, 1, 1, 2])[np.minimum(np.abs(values), 3)].tolist()
    c = 0
    for _ in range(n):
        s = step(kinds[c].cum())
        kinds[c].see(s)
        out.append(s)
        c = sizes[s]
    return values[out]


def _sparse(index):
    """Coder of non-zero residuals: their positions by index = (to numbers, back to positions), and their values, each arithmetic coded."""
    there, back = index

    def pack(x: np.ndarray) -> bytes:
        at = np.flatnonzero(x)
        place, values = arith(there(at, len(x))), arith(x[at])
        return varints([len(x), len(place)]) + place + values

    def unpack(raw: bytes) -> np.ndarray:
        (n, size), at = unvarints(raw, 2)
        place, values = unarith(raw[at : at + int(size)]), unarith(raw[at + int(size) :])
        out = np.zeros(int(n), np.int64)
        out[back(place, int(n))] = values
        return out

    return pack, unpack


def _split(n: int) -> int:
    return max(1, int(np.ceil(np.sqrt(n))))


#: Positions as gaps, as they are, or as a row and a column of a square of the residuals.
INDEX = {
    "flat_gap": (lambda at, n: np.diff(at, prepend=-1) - 1, lambda g, n: np.cumsum(g + 1) - 1),
    "flat": (lambda at, n: at, lambda g, n: g),
    "rowcol": (lambda at, n: np.r_[np.diff(at // _split(n), prepend=0), at % _split(n)], lambda g, n: np.cumsum(g[: len(g) // 2]) * _split(n) + g[len(g) // 2 :]),
}
sparse, unsparse = _sparse(INDEX["flat_gap"])


def runs(x: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    at = np.flatnonzero(np.r_[True, x[1:] != x[:-1]]) if len(x) else np.zeros(0, np.int64)
    return x[at], np.diff(np.r_[at, len(x)])


def rle_lzma(x: np.ndarray) -> bytes:
    values, lengths = runs(x)
    return lzma.compress(varints(np.stack([zigzag(values), lengths.astype(np.uint64)], 1).ravel()), lzma.FORMAT_RAW, filters=_FILTERS)


def unrle_lzma(raw: bytes) -> np.ndarray:
    u, _ = unvarints(lzma.decompress(raw, lzma.FORMAT_RAW, filters=_FILTERS))
    return np.repeat(unzigzag(u[::2]), u[1::2].astype(np.int64))


def varint_lzma(x: np.ndarray) -> bytes:
    return lzma.compress(varints(zigzag(x)), lzma.FORMAT_RAW, filters=_FILTERS)


def unvarint_lzma(raw: bytes) -> np.ndarray:
    return unzigzag(unvarints(lzma.decompress(raw, lzma.FORMAT_RAW, filters=_FILTERS))[0])


def deflate(x: np.ndarray) -> bytes:
    return zlib.compress(varints(zigzag(x)), 9)


def undeflate(raw: bytes) -> np.ndarray:
    return unzigzag(unvarints(zlib.decompress(raw))[0])


def code_lengths(counts: dict[int, int]) -> dict[int, int]:
    """Huffman code length of each symbol."""
    heap = [(c, i, [s]) for i, (s, c) in enumerate(sorted(counts.items()))]
    heapq.heapify(heap)
    length = dict.fromkeys(counts, 0 if len(counts) > 1 else 1)
    n = len(heap)
    while len(heap) > 1:
        (a, _, s), (b, _, t) = heapq.heappop(heap), heapq.heappop(heap)
        for v in s + t:
            length[v] += 1
        heapq.heappush(heap, (a + b, n, s + t))
        n += 1
    return length


def _book(length: dict[int, int]) -> dict[int, tuple[int, int]]:
    """Canonical codes from lengths."""
    code, last, out = 0, 0, {}
    for n, s in sorted((n, s) for s, n in length.items()):
        code <<= n - last
        out[s], code, last = (code, n), code + 1, n
    return out


def huffman(x: np.ndarray) -> bytes:
    length = code_lengths(Counter(x.tolist()))
    book = _book(length)
    symbols = sorted(length)
    bits = "".join(format(c, f"0{n}b") for c, n in map(book.__getitem__, x.tolist()))
    body = int(bits + "0" * (-len(bits) % 8), 2).to_bytes((len(bits) + 7) // 8, "big") if bits else b""
    return varints([len(x), len(symbols)]) + varints(zigzag(np.diff(np.array(symbols, np.int64), prepend=0)) if symbols else []) + bytes(length[s] for s in symbols) + body


def unhuffman(raw: bytes) -> np.ndarray:
    (n, k), at = unvarints(raw, 2)
    steps, used = unvarints(raw[at:], int(k))
    at += used
    symbols = np.cumsum(unzigzag(steps)).tolist() if k else []
    book = {(c, m): s for s, (c, m) in _book(dict(zip(symbols, raw[at : at + int(k)]))).items()}
    out, code, m = [], 0, 0
    for b in raw[at + int(k) :]:
        for i in range(7, -1, -1):
            code, m = code << 1 | b >> i & 1, m + 1
            if (s := book.get((code, m))) is not None:
                out.append(s)
                code, m = 0, 0
                if len(out) == n:
                    return np.array(out, np.int64)
    return np.array(out, np.int64)


CODERS = {
    "sparse_arith": (sparse, unsparse), "sparse_flat": _sparse(INDEX["flat"]), "sparse_rowcol": _sparse(INDEX["rowcol"]), "rle_lzma": (rle_lzma, unrle_lzma), "varint_lzma": (varint_lzma, unvarint_lzma),
    "huffman": (huffman, unhuffman), "arith": (arith, unarith), "arith_adaptive": (arith_adaptive, unarith_adaptive), "arith_ctx": (arith_ctx, unarith_ctx), "deflate": (deflate, undeflate),
}


def estimate(x: np.ndarray) -> float:
    """Bytes that the static arithmetic code takes, by its order-0 entropy and its table."""
    if not len(x):
        return 2.0
    values, n = np.unique(x, return_counts=True)
    table = len(varints(zigzag(np.diff(values, prepend=0)))) + len(varints(n)) + len(varints([len(x), len(values)]))
    return table + 5 - float((n * np.log2(n / len(x))).sum()) / 8


def smallest(x: np.ndarray) -> tuple[str, bytes]:
    """The shortest output of the coders that matter: the native ones are run, the arithmetic one only where its estimate is below them."""
    name, body = min(((n, CODERS[n][0](x)) for n in ("deflate", "varint_lzma", "rle_lzma")), key=lambda c: (len(c[1]), c[0]))
    if estimate(x) < len(body):
        other = arith(x)
        if len(other) < len(body):
            return "arith", other
    return name, body


def choose(x: np.ndarray, names=tuple(CODERS)) -> tuple[str, bytes]:
    """The shortest output of all the named coders, each run."""
    return min(((n, CODERS[n][0](x)) for n in names), key=lambda c: (len(c[1]), c[0]))
