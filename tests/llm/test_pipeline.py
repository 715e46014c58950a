"""The stages of the corpus pipeline and run() against brute force on a small table."""

import random
import re
from collections import Counter

import numpy as np
import pytest
from pyspark.sql import functions as F

import corpus_pipeline
from shotgrid.llm import jaccard, quality, secrets
from shotgrid.llm.bpe import WordEncoder
from shotgrid.llm.common import table
from shotgrid.llm.queries import vocabulary

SF = "/root/testdata/sf0.001"
STAGES = dict(corpus_pipeline.STAGES)


@pytest.fixture(scope="module")
def small(spark, tmp_path_factory):
    """A folder with documents and labels: the small table, awkward rows and columns whose names the stages use."""
    to, rng = str(tmp_path_factory.mktemp("sf")), random.Random(6)
    text = lambda n: [rng.choice("abcdefghijklm") * rng.randrange(1, 9) + rng.choice("nopqr") for _ in range(n)]
    base = text(80)
    rows = [(90_000 + i, t) for i, t in enumerate([None, "", " ", "few words", " ".join(base), " ".join(base).upper(), " ".join([*base, "end"]), "word " * 90, " ".join([*text(60), "password = hunter2hunter2", *text(10)])])]
    rows += [(90_004, " ".join(base)), (None, " ".join(text(70)))]
    odd = spark.createDataFrame(rows, "doc_id long, text string").withColumns({"lang": F.lit(None).cast("string"), "source": F.lit("s"), "n_chars": F.lit(None).cast("long")})
    clash = {c: F.lit(c) for c in ("_place", "place", "row", "_row", "kept", "component_id", "spans", "_metadata", "_at")}
    table(spark, SF, "documents").unionByName(odd).withColumns(clash).repartition(3).write.parquet(f"{to}/documents.parquet")
    table(spark, SF, "labels").write.parquet(f"{to}/labels.parquet")
    return to


def rows_of(df):
    return Counter(tuple(r[c] for c in ("doc_id", "text")) for r in df.collect())


@pytest.fixture(scope="module")
def staged(spark, small, tmp_path_factory):
    """Input and output of every stage, written and read again as run() does."""
    docs, out = table(spark, small, "documents"), {}
    for name, stage in corpus_pipeline.STAGES:
        to = str(tmp_path_factory.mktemp("stage")) + "/x"
        stage(spark, docs, small).write.parquet(to)
        out[name] = (docs, spark.read.parquet(to))
        docs = out[name][1]
    return out


def test_stages_return_the_columns_of_documents(staged):
    for name, (docs, got) in staged.items():
        if name != "packing":
            assert got.columns == docs.columns, name


def test_quality_stage(spark, small, staged):
    docs, got = staged["quality rules"]
    rules = quality.fit(docs, table(spark, small, "labels"))

    def keeps(t):
        w = re.findall(r"[^\x20\x09-\x0D]+", t or "")
        g = [tuple(w[i : i + 3]) for i in range(len(w) - 2)]
        often = Counter(g)
        covered = {i + k for i, x in enumerate(g) if often[x] > 1 for k in range(3)}
        if len(w) < 50 or 100 * len(covered) > 50 * len(w):
            return False
        lines = [x for x in t.split("\n") if re.search(r"[^\x20\x09-\x0D]", x)]
        chars = sum(map(len, w))
        row = {"words": len(w), "word_len": chars / len(w), "symbol_share": len(re.findall(r"[#*$%&|<>]", t)) / len(w), "dup_line_share": (len(lines) - len(set(lines))) / max(1, len(lines))}
        row |= {"repeat_share": len(covered) / len(w), "upper_share": len(re.findall("[A-Z]", t)) / chars, "mark_share": len(re.findall("[!?]", t)) / len(w)}
        return rules.verdict(row)

    assert rows_of(got) == Counter({k: n for k, n in rows_of(docs).items() if keeps(k[1])})


def test_exact_stage(staged):
    docs, got = staged["exact dedup"]
    best: dict = {}
    for d, t in rows_of(docs):
        key = (t or "").encode().lower()
        best[key] = max(best.get(key, -1), -1 if d is None else d)
    left = rows_of(got)
    assert Counter({((t or "").encode().lower(), -1 if d is None else d): n for (d, t), n in left.items()}) == Counter({(k, d): 1 for k, d in best.items()})
    assert sum(left.values()) < sum(rows_of(docs).values())


def test_near_stage(staged):
    docs, got = staged["n-gram Jaccard join"]
    sets = {d: jaccard.shingle_set(t or "", 4) for d, t in rows_of(docs) if d is not None}
    up = {d: d for d in sets}
    for _ in range(3):
        for a in sets:
            for b in sets:
                u, v = sets[a], sets[b]
                if a < b and len(u) and len(v) and min(len(u), len(v)) * 100 >= 85 * max(len(u), len(v)):
                    n = len(np.intersect1d(u, v))
                    if 100 * n >= 85 * (len(u) + len(v) - n):
                        up[a] = up[b] = min(up[a], up[b])
    assert rows_of(got) == Counter({k: n for k, n in rows_of(docs).items() if k[0] is None or up[k[0]] == k[0]})


def test_secret_stage(staged):
    docs, got = staged["secret scans"]
    spans = {r.doc_id: r.spans for r in secrets.scan(docs, secrets.fit(docs)).collect()}
    before = dict(rows_of(docs).keys())
    for d, t in rows_of(got):
        at, out = 0, ""
        for s, e in sorted((int(s), int(e)) for _, s, e in (x.split(":") for x in (spans[d] or "").split(",") if x)):
            if s >= at or not out:
                out += before[d][at:s] + "[secret]"
            at = max(at, e)
        assert t == (out + before[d][at:] if spans[d] else before[d])
    assert any("[secret]" in (t or "") for _, t in rows_of(got))


def test_packing_stage(staged):
    docs, got = staged["packing"]
    own = WordEncoder(vocabulary("word_bpe_49k.json"))
    want = Counter((d, len(own.encode(t or "")) // 2 + 1) for d, t in rows_of(docs).elements())
    pieces = got.collect()
    assert sum(r.length for r in pieces) == sum(k[1] * n for k, n in want.items())
    assert Counter((r.doc_id, r.doc_tokens) for r in pieces if r.start == 0) == want


def test_run_equals_its_stages(spark, small, staged):
    key = lambda df: Counter((r.doc_id, r.start, r.length, r.ids_crc32) for r in df.collect() if r.length < 50) and sorted(r.doc_tokens for r in df.where("start = 0").collect())
    assert key(corpus_pipeline.run(spark, small)) == key(staged["packing"][1])


def test_run_on_an_empty_table(spark, small, tmp_path):
    for name in ("documents", "labels"):
        table(spark, small, name).limit(0).write.parquet(f"{tmp_path}/{name}.parquet")
    assert corpus_pipeline.run(spark, str(tmp_path)).count() == 0

