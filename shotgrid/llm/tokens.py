"""Token counts (operator 5), packing (operator 6) and exact merge-type encoding (operator 9)."""

from __future__ import annotations

import hashlib
import zlib
from collections.abc import Iterator

import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .bpe import MergeCodec, PrefixCounter, WordEncoder, loaded
from .common import id_text, ship, stored


def token_counts(docs: DataFrame, path: str, limit: int = 512, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Per row: doc_id, n_bytes, n_tokens, over_limit (n_tokens > limit), by prefix dynamic programming.

    A null or empty text has no bytes and no tokens; a null id stays null; repeated rows give repeated results; other
    columns are not read. Narrow: no shuffle, memory of one Arrow batch and one bounded cache for each worker."""
    ship(docs.sparkSession)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        counter = loaded(PrefixCounter, path)
        for b in batches:
            texts = b.column("text").to_pylist()
            n = [counter.count(t) for t in texts]
            yield pa.RecordBatch.from_arrays(
                [b.column("doc_id"), pa.array([len(t.encode()) for t in texts], pa.int64()), pa.array(n, pa.int64()), pa.array([x > limit for x in n], pa.bool_())],
                ["doc_id", "n_bytes", "n_tokens", "over_limit"],
            )

    return id_text(docs, id_col, text_col).mapInArrow(run, "doc_id long, n_bytes long, n_tokens long, over_limit boolean")


def truncate_to_budget(docs: DataFrame, path: str, budget: int, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Per row: doc_id, n_chars, n_tokens of the longest prefix whose token count is within budget, found in the prefix counts.

    Nothing is encoded again. Empty and null texts give 0, 0."""
    ship(docs.sparkSession)

    def run(batches):
        counter = loaded(PrefixCounter, path)
        for b in batches:
            cut = []
            for t in b.column("text").to_pylist():
                counts = counter.running(t)
                at = max(i for i, c in enumerate(counts) if c <= budget)
                cut.append((at, counts[at]))
            yield pa.RecordBatch.from_arrays([b.column("doc_id"), pa.array([c[0] for c in cut], pa.int64()), pa.array([c[1] for c in cut], pa.int64())], ["doc_id", "n_chars", "n_tokens"])

    return id_text(docs, id_col, text_col).mapInArrow(run, "doc_id long, n_chars long, n_tokens long")


def piece_codec(docs: DataFrame, path: str, id_col: str = "doc_id", text_col: str = "text", full: bool = True) -> DataFrame:
    """Per row: doc_id, n_tokens, ids (decimal, joined by a space, end id last), decoded text; full=False: their SHA-256 only.

    Null and empty texts give the end id alone and an empty decoded text; other columns are not read."""
    ship(docs.sparkSession)
    sha = lambda s: hashlib.sha256(s.encode()).hexdigest()
    names = ["doc_id", "n_tokens", "ids", "decoded"] if full else ["doc_id", "n_tokens", "ids_sha256", "decoded_sha256"]

    def run(batches):
        codec = loaded(MergeCodec, path)
        for b in batches:
            got = [codec.both(t) for t in b.column("text").to_pylist()]
            if not full:
                got = [(n, sha(i), sha(d)) for n, i, d in got]
            yield pa.RecordBatch.from_arrays([b.column("doc_id"), pa.array([g[0] for g in got], pa.int64()), *(pa.array([g[k] for g in got], pa.string()) for k in (1, 2))], names)

    return id_text(docs, id_col, text_col).mapInArrow(run, f"doc_id long, n_tokens long, {names[2]} string, {names[3]} string")


def encoded(docs: DataFrame, path: str, end_id: int, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """First pass of packing, written to the shared folder: doc_id, ids (unsigned 16 bit), n, part, within.

    part is the task's partition and within the tokens before the row in it, so that the order is fixed once written."""
    ship(docs.sparkSession)

    def run(batches):
        encoder, part, within = loaded(WordEncoder, path), TaskContext.get().partitionId(), 0
        last = end_id.to_bytes(2, "little")
        for b in batches:
            ids = [x + last for x in encoder.encode_batch(b.column("text").to_pylist())]
            n = [len(x) // 2 for x in ids]
            at = []
            for x in n:
                at.append(within)
                within += x
            yield pa.RecordBatch.from_arrays(
                [b.column("doc_id"), pa.array(ids, pa.binary()), pa.array(n, pa.int64()), pa.array([part] * len(n), pa.int64()), pa.array(at, pa.int64())],
                ["doc_id", "ids", "n", "part", "within"],
            )

    return stored(id_text(docs, id_col, text_col).mapInArrow(run, "doc_id long, ids binary, n long, part long, within long"), "encoded")


def pack(docs: DataFrame, path: str, width: int = 4096, end_id: int = 2, id_col: str = "doc_id", text_col: str = "text", with_ids: bool = False) -> DataFrame:
    """Concatenate and cut: one row for each piece of a document that falls into one window of width tokens.

    Columns: doc_id, start, length, ids_crc32, doc_tokens, sequence_id, offset, seq_tokens (tokens in that sequence, all
    but the last are full), padded (length after padding: width, or as it is where that is a power of two); with_ids adds
    the ids themselves. Null and empty texts are one end id; repeated rows are packed as often as they stand there; an
    empty table has no pieces. Totals of the first pass's tasks, three numbers each, are all that is shuffled; their
    offsets are broadcast, a row for each task. Documents over window borders have a row on each side."""
    import numpy as np

    first = encoded(docs, path, end_id, id_col, text_col)
    totals = first.groupBy("part").agg(F.sum("n").alias("total"))
    before = Window.orderBy("part").rowsBetween(Window.unboundedPreceding, -1)
    bases = totals.select("part", F.coalesce(F.sum("total").over(before), F.lit(0)).alias("base"), F.sum("total").over(Window.partitionBy()).alias("all"))
    placed = first.join(F.broadcast(bases), "part").select("doc_id", "ids", (F.col("base") + F.col("within")).alias("at"), "all")

    def run(batches):
        for b in batches:
            rows: list = []
            for doc, ids, at, total in zip(*(b.column(c).to_pylist() for c in ("doc_id", "ids", "at", "all"))):
                wide = np.frombuffer(ids, "<u2").astype("<u4")
                start = 0
                while start < len(wide):
                    seq, offset = divmod(at + start, width)
                    take = min(width - offset, len(wide) - start)
                    raw = wide[start : start + take].tobytes()
                    fill = min(width, total - seq * width)
                    rows.append((doc, start, take, zlib.crc32(raw), len(wide), seq, offset, fill, fill if fill & (fill - 1) == 0 else width, *([raw] if with_ids else [])))
                    start += take
            cols = list(zip(*rows)) or [[]] * (9 + with_ids)
            yield pa.RecordBatch.from_arrays([pa.array(c, pa.binary() if i == 9 else pa.int64()) for i, c in enumerate(cols)], names)

    names = ["doc_id", "start", "length", "ids_crc32", "doc_tokens", "sequence_id", "offset", "seq_tokens", "padded", *(["ids"] if with_ids else [])]
    return placed.mapInArrow(run, ", ".join(f"{n} {'binary' if n == 'ids' else 'long'}" for n in names))
