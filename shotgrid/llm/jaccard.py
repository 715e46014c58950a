"""N-gram Jaccard join (operator 2) by partitioned universes and the pigeonhole principle, with exact verification.

Two sets whose similarity reaches the threshold differ in at most H tokens, H from the size of the smaller. Tokens are
dealt by hash to segments; segment i tolerates a_i - 1 differing tokens (a_i = 1: only equal segment subsets are found;
a_i = 2: also those that differ by one token, by one-deletion neighbourhoods). If the a_i sum to more than H, some segment
agrees within its allowance, so equal signatures find every pair. Segments that are empty on both sides tell nothing:
the sum has slack for them, and a set with more empty segments than the slack is dealt again with another seed.
"""

from __future__ import annotations

import hashlib
import math
import re
import uuid
from functools import lru_cache

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import xxhash
import zstandard
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import id_text, shared_dir, ship, small_batches, stored
from .graph import components

PIECE, LONG = 1 << 16, 4096  # bytes hashed at a time; words beyond LONG bytes are hashed by themselves
BASE = 0x9E3779B97F4A7C15 | 1
GROWTH = 1.5  # of the size bands
SEEDS = 8  # after so many seeds, empty segments are indexed as they are
FOLLOWERS = 2000  # pairs of one document that are verified together


def mixed(h: np.ndarray) -> np.ndarray:
    h = (h ^ (h >> np.uint64(33))) * np.uint64(0xFF51AFD7ED558CCD)
    h = (h ^ (h >> np.uint64(29))) * np.uint64(0xC4CEB9FE1A85EC53)
    return h ^ (h >> np.uint64(32))


@lru_cache(None)
def _tables() -> tuple[np.ndarray, np.ndarray, np.ndarray, bytes]:
    """A random number for each byte, powers of an odd base and their inverses, and which bytes are white space."""
    letters = mixed(np.arange(1, 257, dtype=np.uint64) * np.uint64(0xD6E8FEB86659FD93))
    power = lambda b: np.r_[np.uint64(1), np.cumprod(np.full(PIECE + LONG, b & (1 << 64) - 1, np.uint64))]
    blank = bytes(c == 0x20 or 0x09 <= c <= 0x0D for c in range(256))
    return letters, power(BASE), power(pow(BASE, -1, 1 << 64)), blank


def _piece_hashes(raw: bytes, starts: bool = False) -> np.ndarray | tuple[np.ndarray, np.ndarray]:
    letters, power, inverse, blank = _tables()
    b = np.frombuffer(raw, np.uint8)
    gap = np.frombuffer(b"".join((b"\1", raw.translate(blank), b"\1")), np.uint8)
    edge = (gap[1:] != gap[:-1]).nonzero()[0]  # starts and ends of words, in turns
    if not len(edge):
        return (np.zeros(0, np.uint64), edge) if starts else np.zeros(0, np.uint64)
    start, end = edge[::2], edge[1::2]
    total = np.zeros(len(b) + 1, np.uint64)
    np.add.accumulate(letters.take(b) * power[: len(b)], out=total[1:])
    size = end - start
    out = mixed((total[end] - total[start]) * inverse[start] + size.astype(np.uint64))
    for i in np.flatnonzero(size > LONG).tolist():
        out[i] = xxhash.xxh3_64_intdigest(raw[start[i] : end[i]])
    return (out, start) if starts else out


def word_hashes(text: bytes | str) -> np.ndarray:
    """Hashes of the words in text order: runs of characters other than ASCII white space, A-Z in lower case.

    A word's hash is a polynomial in its bytes, read off running sums of the whole text, so no word is touched one by one."""
    raw = (text.encode() if isinstance(text, str) else text).lower()
    if len(raw) <= PIECE:
        return _piece_hashes(raw)
    out, at = [], 0
    while at < len(raw):  # pieces end at white space
        end = min(len(raw), at + PIECE)
        if end < len(raw):
            found = max(raw.rfind(c, at, end) for c in BLANKS)
            if found < 0:  # a word beyond a piece
                hit = re.compile(rb"[\x20\x09-\x0D]").search(raw, end)
                end = hit.start() if hit else len(raw)
                out.append(np.array([xxhash.xxh3_64_intdigest(raw[at:end])], np.uint64))
                at = end
                continue
            end = found + 1
        out.append(_piece_hashes(raw[at:end]))
        at = end
    return np.concatenate(out)


BLANKS = [bytes([c]) for c in (0x20, *range(0x09, 0x0E))]


def shingles(words: np.ndarray | list[bytes], k: int) -> np.ndarray:
    """Hashes of all k-word shingles in text order, from words or their hashes; fewer words: the whole sequence as one; none: empty."""
    h = words if isinstance(words, np.ndarray) else word_hashes(b" ".join(words))
    n = len(h)
    if not n:
        return np.zeros(0, np.uint64)
    m = min(k, n)
    out = np.full(n - m + 1, m, np.uint64)
    for i in range(m):
        out += h[i : n - m + 1 + i] * np.uint64((2 * i + 1) * 0xBF58476D1CE4E5B9 & 0xFFFFFFFFFFFFFFFF)
    return mixed(out)


def hashes_of(texts: list[bytes], k: int = 0) -> list[np.ndarray]:
    """word_hashes of each text, or with k its shingles; short texts are hashed together, PIECE bytes at a time."""
    out: list = [None] * len(texts)
    at = 0
    while at < len(texts):
        end, size = at, 0
        while end < len(texts) and (end == at or size + len(texts[end]) < PIECE):
            size += len(texts[end]) + 1
            end += 1
        if end == at + 1:
            w = word_hashes(texts[at])
            out[at] = shingles(w, k) if k else w
        else:
            edge = np.cumsum([0, *(len(x) + 1 for x in texts[at:end])])
            w, start = _piece_hashes(b" ".join(texts[at:end]).lower(), True)
            s, cut = shingles(w, k) if k else w, np.searchsorted(start, edge).tolist()
            for i, (p, q) in enumerate(zip(cut, cut[1:]), at):
                out[i] = w[p:q] if not k else s[p : q - k + 1] if q - p >= k else shingles(w[p:q], k)
        at = end
    return out


def shingle_set(text: str, k: int) -> np.ndarray:
    return np.unique(shingles(word_hashes(text), k))


@lru_cache(None)
def band(n: int) -> tuple[int, int, int]:
    """Number, smallest and largest size of the band that n falls in."""
    at, lo = 0, 1
    while True:
        hi = max(lo, math.floor(lo * GROWTH) - 1) if lo > 1 else 1
        if n <= hi:
            return at, lo, hi
        at, lo = at + 1, hi + 1


@lru_cache(None)
def schemes(n: int, num: int, den: int) -> tuple[tuple[int, int, int], ...]:
    """Bands under which a set of n tokens is indexed: its own, and smaller ones that a partner may fall in."""
    out, (at, lo, hi) = [band(n)], band(n)
    while lo > 1:
        at, lo, hi = band(lo - 1)
        if num * n > den * hi:
            break
        out.append((at, lo, hi))
    return tuple(out)


def allocation(lo: int, hi: int, num: int, den: int, rows: float, match: float = 0.02, verify: float = 50.0) -> tuple[int, int, int]:
    """Segments of allowance 1, of allowance 2, and slack, of least cost for a band with `rows` sets.

    Cost of a set: its signatures, plus candidates from chance agreement at `verify` signatures each; a segment of s tokens
    agrees with another set's by chance with probability match**s."""
    most, best = den - num, None
    differ = most * hi // num
    for twos in sorted({0, (differ + 1) // 8, (differ + 1) // 4, (differ + 1) // 2}):
        for slack in range(0, 400):
            ones = max(0, differ + 1 + slack - 2 * twos)
            m = ones + twos
            if not m:
                continue
            s = lo / m
            empty = ones * math.exp(-s) + 2 * twos * math.exp(-s) * (1 + s)
            over = 0.0 if m == 1 else 1.0 - sum(math.exp(-empty) * empty**i / math.factorial(i) for i in range(min(slack, 120) + 1))
            if over > 0.05 and slack < 399 and not (m <= 4 and slack == 0):
                continue
            signatures = ones + twos * (1 + s)
            cost = signatures + verify * rows * (ones * match**s + twos * (1 + s) * match ** max(0.0, s - 1))
            if best is None or cost < best[0]:
                best = (cost, (ones, twos, slack))
            break
    return best[1] if best else (differ + 1, 0, 0)


def signatures(tokens: np.ndarray, num: int, den: int, plan: dict) -> np.ndarray:
    """Signatures of a set (sorted distinct hashes) under all its schemes. plan: allocation of each band."""
    out = []
    for at, lo, hi in schemes(len(tokens), num, den):
        ones, twos, slack = plan[at]
        m = ones + twos
        for seed in range(SEEDS + 1):
            salt = np.uint64((at * 64 + seed) * 0x9E3779B97F4A7C15 & 0xFFFFFFFFFFFFFFFF)
            h = mixed(tokens ^ salt)
            seg = (h % np.uint64(m)).astype(np.int64)
            size = np.bincount(seg, minlength=m)
            total = np.zeros(m, np.uint64)
            np.add.at(total, seg, h)  # a sum of mixed hashes stands for a subset, and deleting a token is a subtraction
            lost = int((size[:ones] == 0).sum()) + 2 * int((size[ones:] <= 1).sum()) if m > 1 else 0
            key = mixed(np.arange(m, dtype=np.uint64) + salt + np.uint64(1 << 40))
            full = mixed(total + key)
            use = size > 0 if seed < SEEDS else np.ones(m, bool)
            out.append(full[use])
            if twos:
                second = seg >= ones
                without = mixed(total[seg[second]] - h[second] + key[seg[second]])
                out.append(without if seed == SEEDS else without[size[seg[second]] > 1])
            if lost <= slack:
                break
    return np.concatenate(out)


KEYS = np.dtype([("key", "<u8"), ("doc", "<i8")])


def _groups(x: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Rows sorted by key, then doc; which of them start a key."""
    x = x[np.lexsort((x["doc"], x["key"]))]
    return x, np.r_[True, x["key"][1:] != x["key"][:-1]][: len(x)]


def _blob(x: np.ndarray) -> bytes:
    """Rows in order of doc: keys, then the differences of docs in byte planes, which compress away."""
    x = x[np.argsort(x["doc"], kind="stable")]
    return np.ascontiguousarray(x["key"]).tobytes() + _planes(np.diff(x["doc"], prepend=0))


def _unblob(blob: bytes) -> np.ndarray:
    n = len(blob) // 16
    raw, x = np.frombuffer(blob, "u1"), np.zeros(n, KEYS)
    x["key"], x["doc"] = raw[: 8 * n].view("<u8"), np.cumsum(_unplaned(raw[8 * n :], "<i8", n))
    return x


def _planes(x: np.ndarray) -> bytes:
    """Byte planes of integers: the high bytes of small numbers are runs of zeros."""
    return np.ascontiguousarray(x.view("u1").reshape(-1, x.itemsize).T).tobytes()


def _unplaned(raw: np.ndarray, kind: str, n: int) -> np.ndarray:
    return np.ascontiguousarray(raw.reshape(-1, n).T).view(kind).ravel() if n else np.zeros(0, kind)


def jaccard_components(docs: DataFrame, k: int = 4, num: int = 85, den: int = 100, id_col: str = "doc_id", text_col: str = "text", chunk: int = 400_000) -> DataFrame:
    """Per row: doc_id, n_shingles, component_id (smallest doc_id reachable by links with den * intersection >= num * union).

    Null and empty texts have no shingles and are linked with nothing; texts of fewer than k words are one shingle; a null
    doc_id stays null and takes part in nothing; repeated rows give repeated results. Of one doc_id with several texts, the
    text of smallest digest stands for it; the other rows keep their own n_shingles and get that document's component_id. Texts of equal words are one class
    and only its smallest doc_id is compared. In a group of equal signatures, members are compared with the group's
    smallest and largest doc. Where a group is then not within one component, only members of different components are
    compared that share a token at the front of both sets (_fronts), as every pair that reaches the threshold does."""
    spark = docs.sparkSession
    ship(spark)
    parts = int(spark.conf.get("spark.sql.shuffle.partitions"))

    def describe(batches):
        pack = zstandard.ZstdCompressor(level=3).compress
        for b in batches:
            texts = [t.encode() for t in b.column("text").to_pylist()]
            words = [word_hashes(t) for t in texts]
            yield pa.RecordBatch.from_arrays(
                [b.column("doc_id"), pa.array([hashlib.sha256(w.tobytes()).digest() for w in words], pa.binary()), pa.array([len(np.unique(shingles(w, k))) for w in words], pa.int64()), pa.array(map(pack, texts), pa.binary())],
                ["doc_id", "same", "n", "body"],
            )

    name = f"jaccard_{uuid.uuid4().hex}"
    described = id_text(docs, id_col, text_col).mapInArrow(describe, "doc_id long, same binary, n long, body binary")
    described.repartition(parts, "doc_id").write.bucketBy(parts, "doc_id").format("parquet").option("path", shared_dir(spark, name)).option("compression", "zstd").saveAsTable(name)
    try:
        table = spark.table(name)
        known = table.where("doc_id is not null and n > 0").groupBy("doc_id").agg(F.min(F.struct("same", "n")).alias("t"))
        classes = known.groupBy("t.same").agg(F.min("doc_id").alias("rep"), F.min("t.n").alias("n"))
        reps = stored(known.select("doc_id", "t.same").join(classes, "same").select("doc_id", "same", "rep", "n"), "jaccard-reps")
        base = stored(table.select("doc_id", "same", "n"), "jaccard-base")
        labels = components(_links(spark, table, reps, parts, k, num, den, chunk))
    finally:
        spark.sql(f"DROP TABLE IF EXISTS {name}")
    found = base.join(reps.select("doc_id", "rep"), "doc_id", "left").join(labels.withColumnRenamed("id", "rep"), "rep", "left")
    return found.select("doc_id", F.col("n").alias("n_shingles"), F.when(F.col("n") > 0, F.coalesce("label", "rep", "doc_id")).otherwise(F.col("doc_id")).alias("component_id"))


def _links(spark, table: DataFrame, reps: DataFrame, parts: int, k: int, num: int, den: int, chunk: int) -> DataFrame:
    """Pairs (a, b) of class representatives that reach the threshold, enough of them to join every component."""
    sizes = reps.where("doc_id = rep").select(F.floor(F.log(F.col("n").cast("double")) / math.log(GROWTH)).alias("b"), "n").groupBy("b").agg(F.count(F.lit(1)).alias("count"), F.max("n").alias("n")).collect()  # one row a band
    histogram = {r.b: r["count"] for r in sizes}
    plan, n, top = {}, 1, max((r.n for r in sizes), default=1)
    while n <= top:
        at, lo, hi = band(n)
        plan[at] = allocation(lo, hi, num, den, histogram.get(math.floor(math.log(hi) / math.log(GROWTH)), 1))
        n = hi + 1

    def index(batches):
        """Signatures of a chunk in blobs, one for each bucket: of each signature the smallest doc; the others as rows (sig, a, b) beside it."""
        open_zstd, held, count, first, ids = zstandard.ZstdDecompressor().decompress, [], 0, {}, []

        def flush():
            x = np.concatenate(held)
            x["doc"] = np.array(ids, np.int64)[x["doc"]]
            x, new = _groups(x)
            low = x["doc"][new][np.cumsum(new) - 1]
            other = np.flatnonzero(~new)
            for i in range(0, len(other), 200_000):
                o = other[i : i + 200_000]
                yield pa.RecordBatch.from_arrays([pa.array([-1] * len(o), pa.int32()), pa.nulls(len(o), pa.binary()), pa.array(x["key"][o].view(np.int64)), pa.array(low[o]), pa.array(x["doc"][o])], names)
            x = x[new]
            bucket = (x["key"] >> np.uint64(32)) % np.uint64(parts)
            order = np.argsort(bucket, kind="stable")
            x, edges = x[order], np.searchsorted(bucket[order], np.arange(parts + 1))
            some = [(i, _blob(x[a:b])) for i, (a, b) in enumerate(zip(edges, edges[1:])) if b > a]
            yield pa.RecordBatch.from_arrays([pa.array([i for i, _ in some], pa.int32()), pa.array([c for _, c in some], pa.binary()), *[pa.nulls(len(some), pa.int64())] * 3], names)

        for b in batches:
            for doc, same, body in zip(b.column("doc_id").to_pylist(), b.column("same").to_pylist(), b.column("body").to_pylist()):
                if same in first:  # a copy inside the chunk: the smallest doc_id stands for it
                    ids[first[same]] = min(ids[first[same]], doc)
                    continue
                first[same] = len(ids)
                ids.append(doc)
                s = np.unique(signatures(np.unique(shingles(word_hashes(open_zstd(body)), k)), num, den, plan))
                r = np.zeros(len(s), KEYS)
                r["key"], r["doc"] = s, first[same]
                held.append(r)
                count += len(r)
                if count >= chunk:
                    yield from flush()
                    held, count, first, ids = [], 0, {}, []
        if count:
            yield from flush()

    def match(batches):
        """Groups that meet in this partition: (sig, smallest doc, other doc)."""
        got: dict[int, list] = {}
        for x in batches:
            for i, blob in zip(x.column("bucket").to_pylist(), x.column("blob").to_pylist()):
                if blob is not None:
                    got.setdefault(i, []).append(_unblob(blob))
            own = x.filter(pc.is_null(x.column("blob")))
            if own.num_rows:
                yield pa.RecordBatch.from_arrays(own.columns[2:], names[2:])
        while got:
            x, new = _groups(np.concatenate(got.popitem()[1]))
            low = x["doc"][new][np.cumsum(new) - 1]
            other = np.flatnonzero(~new & (x["doc"] != low))
            for i in range(0, len(other), 200_000):
                o = other[i : i + 200_000]
                yield pa.RecordBatch.from_arrays([pa.array(x["key"][o].view(np.int64)), pa.array(low[o]), pa.array(x["doc"][o])], names[2:])

    names = ["bucket", "blob", "sig", "a", "b"]
    spread = F.when(F.col("bucket") >= 0, F.col("bucket")).otherwise(F.pmod(F.hash("sig"), F.lit(parts)))
    source = table.where("n > 0 and doc_id is not null").select("doc_id", "same", "body")
    met = source.mapInArrow(index, "bucket int, blob binary, sig long, a long, b long").repartition(parts, spread).mapInArrow(match, "sig long, a long, b long").where("a <> b")
    own = reps.where("doc_id = rep").select("rep", "n", "same")
    members = met.select("sig", F.explode(F.array("a", "b")).alias("rep")).distinct()
    members = stored(members.join(own.select("rep", "n"), "rep").select("sig", "rep", "n"), "jaccard-members")
    ends = members.groupBy("sig").agg(F.min("rep").alias("lo"), F.max("rep").alias("hi")).where("lo < hi")
    near = lambda x, y: (num * F.greatest(x, y) <= den * F.least(x, y))
    star = members.join(ends, "sig").select("sig", "rep", F.explode(F.array("lo", "hi")).alias("o")).where("rep <> o")
    pairs = stored(star.select(F.least("rep", "o").alias("a"), F.greatest("rep", "o").alias("b")).distinct(), "jaccard-pairs")
    its = own.select(F.col("rep").alias("doc_id"), F.col("same").alias("its"))
    # its and same are compared without an equality, which would make both join keys and shuffle the bucketed texts.
    texts = table.select("doc_id", "same", "body").join(its, "doc_id").where("not (same < its or same > its)").select("doc_id", "body").dropDuplicates(["doc_id"])
    links = _verified(pairs, texts, k, num, den)
    labels = components(links)
    named = members.join(labels.withColumnRenamed("id", "rep"), "rep", "left").select("sig", "rep", "n", F.coalesce("label", "rep").alias("label"))
    open_ = named.groupBy("sig").agg(F.min("label").alias("lo"), F.max("label").alias("hi")).where("lo < hi").select("sig")
    waiting = stored(named.join(open_, "sig").select("rep", "n", "label").distinct(), "jaccard-waiting")
    front = _fronts(waiting, texts, k, num, den)
    split = front.groupBy("token").agg(F.min("label").alias("l0"), F.max("label").alias("l1")).where("l0 < l1").select("token")
    front = stored(front.join(split, "token"), "jaccard-open")
    x, y = (front.select("token", *(F.col(c).alias(f"{c}{i}") for c in ("rep", "n", "label", "left"))) for i in (1, 2))
    fits = near(F.col("n1"), F.col("n2")) & ((num + den) * F.least("left1", "left2") >= num * (F.col("n1") + F.col("n2")))
    more = x.join(y, (x.token == y.token) & (F.col("rep1") < F.col("rep2")) & (F.col("label1") != F.col("label2")) & fits).select(F.col("rep1").alias("a"), F.col("rep2").alias("b")).distinct()
    more = stored(more.join(pairs, ["a", "b"], "left_anti"), "jaccard-more")
    return links.unionByName(_verified(more, texts, k, num, den)) if more.take(1) else links


def _fronts(members: DataFrame, texts: DataFrame, k: int, num: int, den: int, bits: int = 20) -> DataFrame:
    """Rows (rep, n, label, token, left) of the first tokens of each member, rare ones first; left: the tokens from this one on.

    Two sets that share at least t tokens have their first common one where both have t or more left, so n - t + 1 tokens
    are enough, in any order that is the same for all. Near misses of one template hold enough rare tokens of their own
    to fill their fronts, so they don't meet there. How often a token occurs is counted by its hash in 2**bits counters,
    all that reaches the driver; the order need not be exact."""
    spark = members.sparkSession
    both = members.join(texts.select(F.col("doc_id").alias("rep"), "body"), "rep")
    width, low = 1 << bits, np.uint64((1 << bits) - 1)
    names = ["rep", "n", "label", "token", "left"]

    def count(batches):
        seen, open_zstd = np.zeros(width, np.int64), zstandard.ZstdDecompressor().decompress
        for b in batches:
            for t in b.column("body").to_pylist():
                np.add.at(seen, (np.unique(shingles(word_hashes(open_zstd(t)), k)) & low).astype(np.int64), 1)
        at = np.flatnonzero(seen)
        for i in range(0, len(at), 100_000):
            yield pa.RecordBatch.from_arrays([pa.array(at[i : i + 100_000]), pa.array(seen[at[i : i + 100_000]])], ["at", "n"])

    with small_batches(spark, 1000):
        got = both.select("body").mapInArrow(count, "at long, n long").groupBy("at").agg(F.sum("n").alias("n")).toArrow()
    often = np.zeros(width, np.int64)
    often[got.column("at").to_numpy()] = got.column("n").to_numpy()
    sent = spark.sparkContext.broadcast(often)

    def run(batches):
        seen, open_zstd = sent.value, zstandard.ZstdDecompressor().decompress
        for b in batches:
            out: list = []
            for t, *row in zip(*(b.column(c).to_pylist() for c in ("body", *names[:3]))):
                u = np.unique(shingles(word_hashes(open_zstd(t)), k))
                n = len(u)
                first = u[np.lexsort((u, seen[(u & low).astype(np.int64)]))][: n - -(-num * n // den) + 1]
                out.append((*(np.full(len(first), v, np.int64) for v in row), first.view(np.int64), n - np.arange(len(first), dtype=np.int64)))
            yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(c)) for c in zip(*out)] if out else [pa.array([], pa.int64())] * 5, names)

    with small_batches(spark, 500):
        return stored(both.select(*names[:3], "body").mapInArrow(run, ", ".join(f"{c} long" for c in names)), "jaccard-fronts")


def _verified(pairs: DataFrame, texts: DataFrame, k: int, num: int, den: int) -> DataFrame:
    """Pairs (a, b) whose sets really reach the threshold. A document with many pairs is sent to as many places as it takes."""
    sized = pairs.groupBy("a").agg(F.ceil(F.count(F.lit(1)) / FOLLOWERS).cast("int").alias("places"))
    dealt = pairs.join(sized, "a").select("a", "b", F.pmod(F.xxhash64("b"), F.col("places")).cast("int").alias("place"))
    left = dealt.join(texts.select(F.col("doc_id").alias("b"), F.col("body").alias("tb")), "b")
    right = sized.join(texts.select(F.col("doc_id").alias("a"), F.col("body").alias("ta")), "a").select("a", "ta", F.explode(F.sequence(F.lit(0), F.col("places") - 1)).alias("place"))

    def run(batches):
        last, open_zstd = (None, None), zstandard.ZstdDecompressor().decompress
        for b in batches:
            keep = []
            for x, s, t in zip(*(b.column(c).to_pylist() for c in ("a", "ta", "tb"))):
                if last[0] != x:
                    last = (x, np.unique(shingles(word_hashes(open_zstd(s)), k)))
                u, v = last[1], np.unique(shingles(word_hashes(open_zstd(t)), k))
                inter = len(np.intersect1d(u, v, assume_unique=True))
                keep.append(den * inter >= num * (len(u) + len(v) - inter))
            yield pa.RecordBatch.from_arrays([b.column("a"), b.column("b")], ["a", "b"]).filter(pa.array(keep, pa.bool_()))

    with small_batches(pairs.sparkSession, 500):
        return stored(left.join(right, ["a", "place"]).select("a", "b", "ta", "tb").mapInArrow(run, "a long, b long"), "jaccard-links")
