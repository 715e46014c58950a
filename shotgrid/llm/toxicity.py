"""Toxicity (operator 4): linear classifier on character n-grams whose features are scaled by naive Bayes log-count ratios."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import id_text, ship

#: Bounds of the labelled sample that is fitted: rows, and bytes of text over all of them.
FIT_ROWS, FIT_BYTES = 4000, 24_000_000
SIZES = (3, 4, 5, 6)
SPACE = 20  # bits of the feature space


def grams(text: str, sizes: tuple[int, ...] = SIZES, bits: int = SPACE) -> np.ndarray:
    """Hashed features of all n-grams of the lower-cased text in UTF-8, with repeats."""
    raw = np.frombuffer(f" {text.lower()} ".encode(), np.uint8).astype(np.uint32)
    out, h = [], np.zeros(len(raw), np.uint32)
    for n in range(1, max(sizes) + 1):
        if len(raw) < n:
            break
        h = (h[: len(raw) - n + 1] * np.uint32(0x01000193)) ^ (raw[n - 1 :] + np.uint32(n))
        if n in sizes:
            out.append(((h * np.uint32(0x9E3779B1)) >> np.uint32(32 - bits)).astype(np.int32))
    return np.concatenate(out) if out else np.zeros(0, np.int32)


class Classifier:
    def __init__(self, weights: np.ndarray, bias: float):
        self.weights, self.bias = weights, bias

    def score(self, text: str) -> float:
        """Probability of label 1; the empty text gets that of a text without any feature."""
        g = grams(text)
        g = np.unique(g[self.used[g]]) if len(g) else g
        return float(1 / (1 + np.exp(-(self.weights[g].sum(dtype=np.float64) + self.bias))))

    @property
    def used(self) -> np.ndarray:
        if "_used" not in self.__dict__:
            self._used = self.weights != 0
        return self._used


def train(texts: list[str], labels: list[int], features: int = 1500, steps: int = 400, decay: float = 1e-3, rate: float = 0.05) -> Classifier:
    """Binary presence features times their log-count ratio, the `features` most telling ones, logistic loss by Adam.

    With one class only (or no rows) the score is that class's smoothed share for every text."""
    y = np.array(labels, np.float64)
    weights = np.zeros(1 << SPACE, np.float32)
    pos, neg = y.sum(), len(y) - y.sum()
    if not pos or not neg:
        return Classifier(weights, float(np.log((pos + 0.5) / (neg + 0.5))))
    sets = [np.unique(grams(t)) for t in texts]
    p, q = (sum((np.bincount(s, minlength=1 << SPACE) for s, v in zip(sets, labels) if v == k), np.zeros(1 << SPACE, np.int64)) for k in (1, 0))
    ratio = np.log((p + 1) / (pos + 2)) - np.log((q + 1) / (neg + 2))
    telling = np.abs(ratio) / np.sqrt(1 / (p + 1) + 1 / (q + 1)) * (p + q >= 3)
    chosen = np.sort(np.argsort(-telling, kind="stable")[:features])
    column = np.full(1 << SPACE, -1)
    column[chosen] = np.arange(len(chosen))
    x = np.zeros((len(y), len(chosen)), np.float32)
    for i, s in enumerate(sets):
        c = column[s]
        x[i, c[c >= 0]] = 1
    x *= ratio[chosen].astype(np.float32)
    w, b = np.zeros(len(chosen)), np.log(pos / neg)
    m, v = np.zeros(len(chosen) + 1), np.zeros(len(chosen) + 1)
    for t in range(1, steps + 1):
        error = 1 / (1 + np.exp(-(x @ w.astype(np.float32) + b))) - y
        g = np.append(x.T @ error.astype(np.float32) / len(y) + decay * w, error.mean())
        m, v = 0.9 * m + 0.1 * g, 0.999 * v + 0.001 * g * g
        move = rate * (m / (1 - 0.9**t)) / (np.sqrt(v / (1 - 0.999**t)) + 1e-8)
        w, b = w - move[:-1], b - move[-1]
    weights[chosen] = w * ratio[chosen]
    return Classifier(weights, float(b))


def held_out(id_col: str = "doc_id"):
    """Rows whose crc32(doc_id as text) mod 4 is 2; a null id is not held out."""
    return F.coalesce(F.crc32(F.col(id_col).cast("string")) % 4 == 2, F.lit(False))


def fit(docs: DataFrame, labels: DataFrame, rows: int = FIT_ROWS, most_bytes: int = FIT_BYTES, id_col: str = "doc_id", text_col: str = "text", label_col: str = "toxic") -> Classifier:
    """Fits on at most `rows` labelled rows that are not held out, smallest hash of doc_id first; null labels are not used.

    Of these, texts count in that order while their UTF-8 bytes sum up to `most_bytes` at most (a longer one is passed
    over). Sizes go to the driver first, then only the texts that count, so the bounds hold for its memory too. Of rows
    that repeat a doc_id each counts."""
    chosen = labels.select(F.col(id_col).cast("long").alias("_k"), F.col(label_col).cast("int").alias("label")).where("_k is not null and label is not null").where(~held_out("_k")).dropDuplicates(["_k"]).orderBy(F.xxhash64("_k"), "_k").limit(rows)
    labelled = id_text(docs, id_col, text_col).join(F.broadcast(chosen), F.col("doc_id") == F.col("_k"))
    order = lambda r: (r.doc_id * 2654435761 % 4294967296, r.doc_id)
    sizes = labelled.groupBy("doc_id").agg(F.sum(F.octet_length("text")).alias("n")).collect()
    use, size = [], 0
    for r in sorted(sizes, key=order):
        if size + r.n <= most_bytes:
            use.append((r.doc_id,))
            size += r.n
    used = docs.sparkSession.createDataFrame(use, "_u long")
    got = labelled.join(F.broadcast(used), F.col("doc_id") == F.col("_u")).select("doc_id", "text", "label").collect()
    got.sort(key=lambda r: (*order(r), r.text))
    return train([r.text for r in got], [r.label for r in got])


def toxicity(docs: DataFrame, model: Classifier, cut: float = 0.3, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Per row: doc_id, held_out, score, predicted (1 if score >= cut). Null texts count as empty; only id and text are read.

    Narrow: the weights (4 MB, fixed) go to every task, nothing is shuffled."""
    spark = docs.sparkSession
    ship(spark)
    sent = spark.sparkContext.broadcast((model.weights, model.bias))

    def run(batches):
        m = Classifier(*sent.value)
        for b in batches:
            s = [m.score(t) for t in b.column("text").to_pylist()]
            yield pa.RecordBatch.from_arrays([b.column("doc_id"), b.column("held_out"), pa.array(s, pa.float64()), pa.array([int(x >= cut) for x in s], pa.int32())], ["doc_id", "held_out", "score", "predicted"])

    return id_text(docs, id_col, text_col).withColumn("held_out", held_out("doc_id")).mapInArrow(run, "doc_id long, held_out boolean, score double, predicted int")
