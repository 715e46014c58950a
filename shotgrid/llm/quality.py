"""Quality rules (operator 8): text statistics and a learned decision list, in DataFrame functions only."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import id_text

#: Labelled rows that a rule list is fitted on at most, smallest hash of doc_id first.
FIT_ROWS = 20_000
#: Numerator and denominator of each feature that rules may test.
FEATURES = {
    "words": ("n_words", None), "word_len": ("word_chars", "n_words"), "symbol_share": ("n_symbols", "n_words"), "dup_line_share": ("n_dup_lines", "n_lines"),
    "repeat_share": ("n_repeat_words", "n_words"), "upper_share": ("n_upper", "word_chars"), "mark_share": ("n_marks", "n_words"),
}


def text_stats(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", keep: list[str] | None = None) -> DataFrame:
    """Per row: doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, n_lines, n_upper, n_marks.

    Null and empty texts give zeros. Everything is computed inside the row: nothing is exploded or shuffled. Repeated
    3-word windows are found by sorting (hash of window, position) and comparing neighbours. keep: input columns carried."""
    blank = r"[\x20\x09-\x0D]+"
    base = docs.select(*(keep or []), F.col(id_col).cast("long").alias("doc_id"), F.coalesce(F.col(text_col), F.lit("")).alias("_t")) if keep else id_text(docs, id_col, text_col).withColumnRenamed("text", "_t")
    w = base.withColumn("_w", F.filter(F.split("_t", blank), lambda x: x != "")).withColumn("_n", F.size("_w"))
    # Neighbours are paired by zipping shifted arrays, so a row costs n log n even where the optimizer copies expressions.
    windows = F.expr("array_sort(transform(slice(arrays_zip(_w, slice(_w, 2, _n + 1), slice(_w, 3, _n + 1)), 1, greatest(_n - 2, 0)), (x, i) -> struct(xxhash64(x.`_w`, x.`1`, x.`2`) as h, i as i)))")
    lines = F.filter(F.split("_t", "\n"), lambda x: x.rlike(r"[^\x20\x09-\x0D]"))
    s = w.withColumn("_s", windows).withColumn("_l", lines)
    twice = F.expr("array_sort(transform(filter(arrays_zip(_s, slice(_s, 2, size(_s) + 1), concat(array(cast(null as struct<h: bigint, i: int>)), _s)), x -> x.`_s` is not null and (x.`_s`.h <=> x.`1`.h or x.`_s`.h <=> x.`2`.h)), x -> x.`_s`.i))")
    s = s.withColumn("_r", twice)
    covered = F.expr("case when size(_r) = 0 then 0L else aggregate(_r, struct(0L as total, -9 as last), (a, i) -> struct(a.total + least(3, i - a.last) as total, i as last), a -> a.total) end")
    return s.select(
        *(keep or []), "doc_id", F.col("_n").cast("long").alias("n_words"), F.length(F.regexp_replace("_t", blank, "")).cast("long").alias("word_chars"),
        F.regexp_count("_t", F.lit("[#*$%&|<>]")).cast("long").alias("n_symbols"), (F.size("_l") - F.size(F.array_distinct("_l"))).cast("long").alias("n_dup_lines"),
        covered.alias("n_repeat_words"), F.size("_l").cast("long").alias("n_lines"), F.regexp_count("_t", F.lit("[A-Z]")).cast("long").alias("n_upper"),
        F.regexp_count("_t", F.lit("[!?]")).cast("long").alias("n_marks"),
    )


def base_failed() -> Column:
    """The fixed limits: fewer than 50 words, or over half of the words in repeated windows."""
    return (F.col("n_words") < 50) | (100 * F.col("n_repeat_words") > 50 * F.col("n_words"))


def feature(name: str) -> Column:
    a, b = FEATURES[name]
    return F.col(a).cast("double") if b is None else F.when(F.col(b) > 0, F.col(a) / F.col(b)).otherwise(F.lit(0.0))


@dataclass(frozen=True)
class Test:
    feature: str
    above: bool
    value: float

    def holds(self, row) -> bool:
        return (row[self.feature] >= self.value) if self.above else (row[self.feature] <= self.value)

    def column(self) -> Column:
        return feature(self.feature) >= F.lit(self.value) if self.above else feature(self.feature) <= F.lit(self.value)


class DecisionList:
    """Ordered rules; the first whose tests all hold rejects a row, and a row that none matches is kept."""

    def __init__(self, rules: list[tuple[Test, ...]]):
        self.rules = rules

    def rule(self) -> Column:
        """Number of the first rule that matches, from 1; 0 if none does: one CASE expression."""
        out = None
        for n, tests in enumerate(self.rules, 1):
            hold = tests[0].column()
            for t in tests[1:]:
                hold = hold & t.column()
            out = F.when(hold, F.lit(n)) if out is None else out.when(hold, F.lit(n))
        return F.lit(0) if out is None else out.otherwise(F.lit(0))

    def verdict(self, row) -> bool:
        return not any(all(t.holds(row) for t in tests) for tests in self.rules)


def learn(rows: list[dict], least: int = 3, precision: float = 0.95, most_rules: int = 12, most_tests: int = 3) -> DecisionList:
    """Sequential covering. rows: features and 'bad' (the label to reject). Two of three rows grow a rule, the third prunes it.

    A rule grows by the threshold test of greatest information gain; tests are dropped from its end while precision on
    the pruning rows doesn't fall. It is accepted if it is precise on both parts; its rows are then taken away. Thresholds
    lie midway between neighbouring values of bad and good rows. No rows, or one class only: no rules, all are kept."""
    from math import log2

    left, rules = list(rows), []
    rate = lambda part, tests: (lambda hit: (sum(r["bad"] for r in hit), len(hit)))([r for r in part if all(t.holds(r) for t in tests)])
    while len(rules) < most_rules and any(r["bad"] for r in left):
        grow, prune = [r for i, r in enumerate(left) if i % 3], [r for i, r in enumerate(left) if i % 3 == 0]
        tests: list[Test] = []
        covered = grow
        while len(tests) < most_tests:
            p0, n0 = sum(r["bad"] for r in covered), len(covered)
            if not p0 or p0 == n0:
                break
            best = (0.0, None)
            for f in FEATURES:
                ordered = sorted(covered, key=lambda r: r[f])  # noqa: B023
                p = 0
                for i in range(n0 - 1):
                    p += ordered[i]["bad"]
                    a, b = ordered[i][f], ordered[i + 1][f]
                    if a == b:
                        continue
                    for above, pp, nn in ((False, p, i + 1), (True, p0 - p, n0 - i - 1)):
                        if pp >= least and (gain := pp * (log2(pp / nn) - log2(p0 / n0))) > best[0] + 1e-9:
                            best = (gain, Test(f, above, (a + b) / 2))
            if best[1] is None:
                break
            tests.append(best[1])
            covered = [r for r in covered if best[1].holds(r)]
        while len(tests) > 1:
            (p, n), (q, m) = rate(prune, tests), rate(prune, tests[:-1])
            if not m or (n and q / m < p / n):
                break
            tests.pop()
        if not tests:
            break
        (p, n), (q, m) = rate(grow, tests), rate(prune, tests)
        if p + q < least or p + q < precision * (n + m) or (m and q < (precision - 0.1) * m):
            break
        rules.append(tuple(tests))
        left = [r for r in left if not all(t.holds(r) for t in tests)]
    return DecisionList(rules)


def fit(docs: DataFrame, labels: DataFrame, rows: int = FIT_ROWS, id_col: str = "doc_id", text_col: str = "text", label_col: str = "quality") -> DecisionList:
    """Rules from at most `rows` labelled documents that pass the fixed limits; a null label is not used.

    The chosen ids are broadcast (at most `rows`, two numbers each), so documents are not shuffled; the statistics of the
    labelled ones, some numbers each, go to the driver within that bound."""
    chosen = labels.select(F.col(id_col).cast("long").alias("_k"), (F.col(label_col) == 0).cast("int").alias("bad")).where("_k is not null and bad is not null").dropDuplicates(["_k"]).orderBy(F.xxhash64("_k"), "_k").limit(rows)
    joined = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("text")).join(F.broadcast(chosen), F.col("doc_id") == F.col("_k")).select("doc_id", "text", "bad")
    stats = text_stats(joined, keep=["bad"]).select("doc_id", "bad", base_failed().alias("failed"), *(feature(f).alias(f) for f in FEATURES))
    return learn([r.asDict() for r in sorted(stats.collect(), key=lambda r: (r.doc_id * 2654435761 % 4294967296, r.doc_id)) if not r.failed])


def quality_rules(docs: DataFrame, rules: DecisionList, id_col: str = "doc_id", text_col: str = "text", keep: list[str] | None = None) -> DataFrame:
    """text_stats with base_failed, rule (the rejecting rule's number, 0 for none) and kept.

    kept is false if a fixed limit fails, else the rule list's verdict. Null and empty texts have no words and fail."""
    s = text_stats(docs, id_col, text_col, keep)
    return s.withColumn("base_failed", base_failed()).withColumn("rule", rules.rule()).withColumn("kept", ~F.col("base_failed") & (F.col("rule") == 0))
