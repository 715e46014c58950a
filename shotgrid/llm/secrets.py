"""Secret scans (operator 3): fixed patterns, and character Markov models compared by log-likelihood ratio; native functions only."""

from __future__ import annotations

from collections import Counter
from math import log

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import id_text

# The three patterns of the base scan. For access and hex the least length is part of the pattern, which
# matches the same runs; assign is filtered after matching, since a match that fails still takes up its characters.
ASSIGN = r"""(?i:(password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+))"""
KEYWORDS = ("password", "passwd", "secret", "token", "apikey", "api_key")
ACCESS = r"AKIA[A-Z0-9]{12,}"
HEX = r"[0-9a-f]{32,}"
#: What the Markov models judge: unbroken runs of the characters that keys are written in, with a digit.
CANDIDATE = r"[A-Za-z0-9+/_=-]{20,}"
KINDS = ("assign", "access", "hex", "markov")
ALPHABET = "abcdefghijklmnopqrstuvwxyzABCDEFGHIJKLMNOPQRSTUVWXYZ0123456789+/_=-"
#: Generated strings that stand for random ones: labelled by the way they are made.
FIT_RANDOM = 3000


class MarkovPair:
    """Log-likelihood ratios of first-order character models: random strings over ordinary identifiers."""

    def __init__(self, ratios: list[float], threshold: float):
        self.ratios, self.threshold = ratios, threshold

    @classmethod
    def train(cls, random: list[str], ordinary: list[str], threshold: float = 0.6, smooth: float = 0.5) -> MarkovPair:
        """threshold: least mean ratio per character pair, in nats, of what is taken for a secret."""
        return cls.counted(*(Counter(p for s in sample for p in zip(s, s[1:])) for sample in (random, ordinary)), threshold, smooth)

    @classmethod
    def counted(cls, random: dict, ordinary: dict, threshold: float = 0.6, smooth: float = 0.5) -> MarkovPair:
        """From the numbers of each pair of neighbouring characters in both samples."""
        tables = []
        for sample in (random, ordinary):
            rows = [[sample.get((a, b), 0) + smooth for b in ALPHABET] for a in ALPHABET]
            tables.append([[log(x / sum(row)) for x in row] for row in rows])
        return cls([round(x - y, 4) for r, o in zip(*tables) for x, y in zip(r, o)], threshold)

    def score(self, s: str) -> float:
        at, k = {c: i for i, c in enumerate(ALPHABET)}, len(ALPHABET)
        pairs = [self.ratios[at[a] * k + at[b]] for a, b in zip(s, s[1:])]
        return sum(pairs) / max(1, len(pairs))


def word_pairs(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> Counter:
    """How many different words (runs of 2 to 30 letters, in lower case) of the whole table hold each pair of neighbouring
    letters; ^ stands for the start and $ for the end of a word.

    Words are taken once from each text, then once from the table; at most 28 x 28 numbers reach the driver."""
    words = id_text(docs, id_col, text_col).select(F.explode(F.array_distinct(F.regexp_extract_all(F.lower("text"), F.lit("(?<![a-z])([a-z]{2,30})(?![a-z])"), 1))).alias("w")).distinct()
    marked = F.concat(F.lit("^"), "w", F.lit("$"))
    pairs = words.select(F.explode(F.transform(F.sequence(F.lit(1), F.length("w") + 1), lambda i: F.substring(marked, i, F.lit(2)))).alias("p"))
    return Counter({(r.p[0], r.p[1]): r.n for r in pairs.groupBy("p").agg(F.count(F.lit(1)).alias("n")).collect()})


def identifier_pairs(words: Counter) -> Counter:
    """Pairs of characters of ordinary identifiers: those words joined by _ or -, in camel case, in capitals, or with a number at the end.

    A joint takes the last letter of one word and the first of another, each as often as words end or start so."""
    first, last, out = Counter(), Counter(), Counter()
    for (a, b), n in words.items():
        if a == "^":
            first[b] += n
        elif b == "$":
            last[a] += n
        else:
            out[a, b] += n
            out[a.upper(), b.upper()] += n / 4
    total = sum(first.values()) or 1
    for a, n in last.items():
        for joint, share in (("_", 0.4), ("-", 0.2), ("/", 0.1)):
            out[a, joint] += n * share
        for b, m in first.items():
            out[a, b.upper()] += n * m / total * 0.3
        for d in "0123456789":
            out[a, d] += n * 0.02
    for b, n in first.items():
        for joint, share in (("_", 0.4), ("-", 0.2), ("/", 0.1)):
            out[joint, b] += n * share
    for a, n in words.items():  # the second letter of a word that starts with a capital
        if a[0] == "^":
            for b in ALPHABET[:26]:
                out[a[1].upper(), b] += 0.3 * n * words.get((a[1], b), 0) / (sum(words.get((a[1], c), 0) for c in ALPHABET[:26]) or 1)
    for a in "0123456789":
        for b in "0123456789":
            out[a, b] += 0.002 * total
        for joint in "_-/":
            out[joint, a] += 0.005 * total
            out[a, joint] += 0.005 * total
    return out


def fit(docs: DataFrame, random: int = FIT_RANDOM, id_col: str = "doc_id", text_col: str = "text") -> MarkovPair:
    """Trains both models. Ordinary identifiers: what the words of all documents give (word_pairs, identifier_pairs). Random
    strings: hex, base64 and base62-like digests of 0..random-1. An empty table leaves the ordinary model flat."""
    spark = docs.sparkSession
    ordinary = identifier_pairs(word_pairs(docs, id_col, text_col))
    h = F.sha2(F.col("id").cast("string"), 256)
    made = spark.range(random).select(F.when(F.col("id") % 3 == 0, F.substring(h, 1, 40)).when(F.col("id") % 3 == 1, F.substring(F.base64(F.unhex(h)), 1, 40)).otherwise(F.regexp_replace(F.base64(F.unhex(h)), "[+/=]", "")).alias("s"))
    return MarkovPair.counted(Counter(p for r in made.collect() for p in zip(r.s, r.s[1:])), ordinary)


def _spans(pattern: str, kind: int, least: int = 0) -> Column:
    """Array of (start, end, kind) of a pattern's matches in text, in code points: the pieces between the matches give the places.

    Places are running sums of lengths, made in three steps (sums of blocks of about sqrt(n) matches, where each block
    starts, then places inside each block), so that n matches cost n sqrt(n) additions and no array grows by copying."""
    whole = F.regexp_extract_all("text", F.lit(f"({pattern})"), 1)
    value = F.regexp_extract_all("text", F.lit(pattern), 2) if least else whole
    pieces = F.arrays_zip(F.transform(F.split("text", pattern, -1), lambda p: F.length(p)).alias("p"), F.transform(whole, lambda m: F.length(m)).alias("m"), F.transform(value, lambda v: F.length(v)).alias("v"))
    held = F.struct(F.filter(pieces, lambda x: x["m"].isNotNull()).alias("x"), F.lit(0).alias("w"))
    # Each step binds its input by a transform over an array of one, since the optimizer would copy a column's expression.
    bind = lambda value, make: F.get(F.transform(F.array(value), make), F.lit(0))
    sums = lambda part, start: F.aggregate(part, start, lambda a, x: a + x["p"] + x["m"])

    def blocks(h):
        x = h["x"]
        width = F.greatest(F.lit(1), F.ceil(F.sqrt(F.size(x))).cast("int"))
        many = F.ceil(F.size(x) / width).cast("int")
        parts = F.transform(F.sequence(F.lit(0), F.greatest(many - 1, F.lit(0))), lambda i: F.slice(x, i * width + 1, width))
        return bind(parts, lambda y: bind(F.transform(y, lambda part: sums(part, F.lit(0))), lambda s: placed(y, s)))

    def placed(parts, totals):
        starts = F.transform(totals, lambda _, i: F.aggregate(F.slice(totals, F.lit(1), i), F.lit(0), lambda a, t: a + t))
        return F.flatten(F.zip_with(parts, starts, lambda part, start: F.transform(part, lambda x, i: bind(sums(F.slice(part, F.lit(1), i), start) + x["p"], lambda s: F.struct(s.alias("s"), (s + x["m"]).alias("e"), x["v"].alias("v"))))))

    spans = F.when(F.size(whole) > 0, bind(held, blocks))
    kept = F.transform(F.filter(spans, lambda x: x["v"] >= least), lambda x: F.struct(x["s"].alias("s"), x["e"].alias("e"), F.lit(kind).alias("k")))
    return F.coalesce(kept, F.expr("cast(array() as array<struct<s: int, e: int, k: int>>)"))


def secret_spans(docs: DataFrame, model: MarkovPair, id_col: str = "doc_id", text_col: str = "text", keep: list[str] | None = None) -> DataFrame:
    """Per row: doc_id, text, spans (array of start, end, kind number into KINDS; code points, end exclusive, by start then kind).

    Base spans always stay; a candidate run is added as kind markov if it has a digit, its mean ratio reaches the model's threshold and
    no base span overlaps it. Null and empty texts have no spans; repeated rows give repeated results; a run of any length
    is judged as a whole, in time that grows with its length. keep: input columns carried along."""
    none = F.expr("cast(array() as array<struct<s: int, e: int, k: int>>)")
    carried = keep or []
    base = docs.select(*carried, F.col(id_col).cast("long").alias("doc_id"), F.coalesce(F.col(text_col), F.lit("")).alias("text")) if keep else id_text(docs, id_col, text_col)
    low = F.lower("text")
    named = low.contains(KEYWORDS[0])
    for w in KEYWORDS[1:]:
        named = named | low.contains(w)
    found = base.withColumn("_a", F.when(named, _spans(ASSIGN, 0, 8)).otherwise(none))
    found = found.withColumn("_b", F.when(F.col("text").contains("AKIA"), _spans(ACCESS, 1)).otherwise(none))
    found = found.withColumn("_long", F.col("text").rlike(CANDIDATE) | F.col("text").rlike(HEX))
    found = found.withColumn("_c", F.when(F.col("_long"), _spans(HEX, 2)).otherwise(none))
    found = found.withColumn("_base", F.array_sort(F.concat("_a", "_b", "_c")))
    open_ = F.filter(_spans(CANDIDATE, 3), lambda x: ~F.exists(F.col("_base"), lambda b: (b["s"] < x["e"]) & (x["s"] < b["e"])))
    scored = F.filter(F.transform(open_, lambda x: F.struct(x["s"].alias("s"), x["e"].alias("e"), x["k"].alias("k"), F.substring(F.col("text"), x["s"] + 1, x["e"] - x["s"]).alias("w"))), lambda x: x["w"].rlike("[0-9]"))
    found = found.withColumn("_d", F.when(F.col("_long"), scored))
    judged = F.filter(F.coalesce(F.col("_d"), F.expr("cast(array() as array<struct<s: int, e: int, k: int, w: string>>)")), lambda x: model_score(model, x["w"]) >= model.threshold)
    added = F.transform(judged, lambda x: F.struct(x["s"].alias("s"), x["e"].alias("e"), x["k"].alias("k")))
    return found.select(*carried, "doc_id", "text", F.col("_base").alias("base"), F.array_sort(F.concat("_base", added)).alias("spans"))


def model_score(model: MarkovPair, w: Column) -> Column:
    """Mean ratio of neighbouring characters of w by table lookup."""
    k = len(ALPHABET)
    table = F.expr("cast(split('" + ",".join(map(str, model.ratios)) + "', ',') as array<double>)")  # folded into one literal
    spots = F.transform(F.split(w, ""), lambda c: F.call_function("locate", c, F.lit(ALPHABET)) - 1)
    held = F.struct(F.lit(0.0).alias("sum"), F.lit(-1).alias("last"))
    step = lambda a, i: F.struct((a["sum"] + F.when(a["last"] < 0, F.lit(0.0)).otherwise(F.coalesce(F.get(table, a["last"] * k + i), F.lit(0.0)))).alias("sum"), i.alias("last"))
    return F.aggregate(spots, held, step, lambda a: a["sum"]) / F.greatest(F.length(w) - 1, F.lit(1))


def joined_spans(spans: str) -> Column:
    """kind:start:end, comma-joined."""
    names = F.array(*(F.lit(k) for k in KINDS))
    return F.array_join(F.transform(F.col(spans), lambda x: F.concat_ws(":", F.get(names, x["k"]), x["s"].cast("string"), x["e"].cast("string"))), ",")


def ordered(spans: str) -> Column:
    """By start, then kind as listed."""
    turned = F.array_sort(F.transform(F.col(spans), lambda x: F.struct(x["s"].alias("s"), x["k"].alias("k"), x["e"].alias("e"))))
    return F.transform(turned, lambda x: F.struct(x["s"].alias("s"), x["e"].alias("e"), x["k"].alias("k")))


def scan(docs: DataFrame, model: MarkovPair, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Per row: doc_id, n_assign, n_access, n_hex, n_markov, base_sha256, spans (written form, all kinds)."""
    s = secret_spans(docs, model, id_col, text_col).withColumn("base", ordered("base")).withColumn("spans", ordered("spans"))
    count = lambda k: F.size(F.filter("spans", lambda x: x["k"] == k)).cast("long").alias(f"n_{KINDS[k]}")
    return s.select("doc_id", *(count(k) for k in range(4)), F.sha2(joined_spans("base"), 256).alias("base_sha256"), joined_spans("spans").alias("spans"))


def redact(docs: DataFrame, model: MarkovPair, mask: str = "[secret]", id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """The input with every span of its text replaced by mask, overlapping spans as one; rows, columns and clean texts stay as they are.

    A null text stays null."""
    columns = docs.columns
    packed = docs.select(F.struct(*(F.col(f"`{c}`") for c in columns)).alias("_row"), F.col(id_col).alias("doc_id"), F.col(text_col).alias("text"))
    s = secret_spans(packed, model, keep=["_row"]).withColumn("spans", ordered("spans"))
    held = F.struct(F.lit(0).alias("at"), F.lit("").alias("out"))
    step = lambda a, x: F.when(x["e"] <= a["at"], a).otherwise(
        F.struct(x["e"].alias("at"), F.when((x["s"] < a["at"]) & (a["at"] > 0), a["out"]).otherwise(F.concat(a["out"], F.substring(F.col("text"), a["at"] + 1, x["s"] - a["at"]), F.lit(mask))).alias("out"))
    )
    clean = F.aggregate("spans", held, step, lambda a: F.concat(a["out"], F.substring(F.col("text"), a["at"] + 1, F.length("text"))))
    new = F.when(F.size("spans") > 0, clean).otherwise(F.col(f"_row.`{text_col}`"))
    return s.select(*(new.alias(c) if c == text_col else F.col(f"_row.`{c}`").alias(c) for c in columns))
