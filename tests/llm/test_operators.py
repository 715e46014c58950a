"""Text operators against brute force, the libraries and awkward rows."""

import hashlib
import random
import re
from collections import Counter, defaultdict

import numpy as np
import pytest
from pyspark.sql import functions as F

from shotgrid.llm import exact, graph, jaccard, passages, quality, secrets, suffixes, tokens, toxicity
from shotgrid.llm.bpe import MergeCodec, PrefixCounter, WordEncoder
from shotgrid.llm.common import table
from shotgrid.llm.queries import vocabulary

SF = "/root/testdata/sf0.001"
ODD = [None, "", " ", "x", "same text here", "SAME text here", "a b c d e f " * 400, "y" * 5000, "日本語 ΣΑΣ 😀 <|endoftext|> it's", "password = abcdefgh12 token:zz"]


@pytest.fixture(scope="module")
def docs(spark, tmp_path_factory):
    """The small table with awkward rows, clashing column names and repeated rows, as files."""
    to = str(tmp_path_factory.mktemp("docs"))
    rows = [(100_000 + i, t) for i, t in enumerate(ODD)] + [(100_004, "same text here"), (None, "no id")]
    odd = spark.createDataFrame(rows, "doc_id long, text string").withColumns({"lang": F.lit(None).cast("string"), "source": F.lit("s"), "n_chars": F.lit(None).cast("long")})
    table(spark, SF, "documents").unionByName(odd).withColumns({"n": F.lit(1), "kept": F.lit("k"), "spans": F.lit("s"), "label": F.lit(0), "_row": F.lit(1)}).repartition(3).write.parquet(f"{to}/d")
    return spark.read.parquet(f"{to}/d")


@pytest.fixture(scope="module")
def rows(docs):
    return [(r.doc_id, r.text or "") for r in docs.select("doc_id", "text").collect()]


def test_exact(docs, rows):
    want = defaultdict(list)
    for d, t in rows:
        want[t.encode().lower()].append(d)
    for digest, files in ((32, 100), (1, 1)):
        got = exact.exact_dedup(docs, digest_bytes=digest, files_per_trigger=files).collect()
        assert len(got) == len(rows) and sum(r.kept for r in got) == len(want)
        sizes = {hashlib.sha256(t).hexdigest(): (len(v), max((x for x in v if x is not None), default=None)) for t, v in want.items()}
        assert all((r.group_size, r.keep_id) == sizes[r.text_sha256] for r in got)


def test_jaccard(docs, rows):
    sets = {d: jaccard.shingle_set(t, 4) for d, t in rows if d is not None}
    ids, up = sorted(sets), {d: d for d in sets}

    def top(x):
        while up[x] != x:
            x = up[x]
        return x

    for i, a in enumerate(ids):
        for b in ids[i + 1 :]:
            u, v = sets[a], sets[b]
            if len(u) and len(v) and min(len(u), len(v)) * 100 >= 85 * max(len(u), len(v)):
                n = len(np.intersect1d(u, v))
                if 100 * n >= 85 * (len(u) + len(v) - n):
                    x, y = sorted((top(a), top(b)))
                    up[y] = x
    got = {r.doc_id: (r.n_shingles, r.component_id) for r in jaccard.jaccard_components(docs).collect()}
    assert {d: got[d] for d in ids} == {d: (len(sets[d]), top(d)) for d in ids}


def test_jaccard_signatures_find_every_pair():
    rng = np.random.default_rng(3)
    plans = [{jaccard.band(n)[0]: jaccard.allocation(*jaccard.band(n)[1:], 85, 100, r) for n in range(1, 2000)} for r in (1e3, 1e9)]
    for plan in plans:
        for _ in range(300):
            n = int(rng.integers(1, 400))
            a = rng.integers(0, 2**63, n).astype(np.uint64)
            drop = int(rng.integers(0, n * 15 // 100 + 1))
            add = int(rng.integers(0, max(1, (n - drop) * 100 // 85 - n + 1)))
            b = np.unique(np.r_[a[drop:], rng.integers(0, 2**63, add).astype(np.uint64)])
            a, inter = np.unique(a), n - drop
            if 100 * inter >= 85 * (len(a) + len(b) - inter):
                assert len(np.intersect1d(jaccard.signatures(a, 85, 100, plan), jaccard.signatures(b, 85, 100, plan)))


PATTERNS = [("assign", re.compile(r"""(password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", re.I | re.A), 8), ("access", re.compile("AKIA[A-Z0-9]+"), 16), ("hex", re.compile("[0-9a-f]+"), 32)]


def test_secrets(docs, rows):
    model = secrets.fit(docs)
    texts = dict(rows)
    for r in secrets.scan(docs, model).where("doc_id is not null").collect():
        found = sorted((m.start(), k, m.end(), n) for k, (n, p, least) in enumerate(PATTERNS) for m in p.finditer(texts[r.doc_id]) if len(m.group(2 if k == 0 else 0)) >= least)
        assert r.base_sha256 == hashlib.sha256(",".join(f"{n}:{s}:{e}" for s, _, e, n in found).encode()).hexdigest()
    assert model.score("aZ8kQ2xV9mP4tL7wR1cY") > model.threshold > model.score("ordinary_identifier_name")
    clean = secrets.redact(docs, model)
    assert clean.columns == docs.columns and clean.count() == len(rows)
    assert "abcdefgh12" not in clean.where("doc_id = 100009").first().text


def test_toxicity(spark, docs, rows):
    model = toxicity.train(["you idiot person", "what an idiot", "good day friend", "a fine morning"] * 5, [1, 1, 0, 0] * 5)
    assert model.score("an idiot again") > 0.5 > model.score("a good friend")
    got = toxicity.toxicity(docs, model).collect()
    assert len(got) == len(rows) and all(0 <= r.score <= 1 and r.predicted == (r.score >= 0.3) for r in got)


def test_tokens(docs, rows):
    import sentencepiece
    from tokenizers import Tokenizer

    texts = [t for _, t in rows if len(t) < 20_000]
    lib = Tokenizer.from_file(vocabulary("byte_bpe_50k.json"))
    counter = PrefixCounter(vocabulary("byte_bpe_50k.json"))
    assert [counter.count(t) for t in texts] == [len(lib.encode(t, add_special_tokens=False).ids) for t in texts]
    for t in texts[-8:] + ["It's 12 o'clock,  no?\n\n ok"]:
        t = t[:60]
        assert counter.running(t) == [len(lib.encode(t[:i], add_special_tokens=False).ids) for i in range(len(t) + 1)]
    sp = sentencepiece.SentencePieceProcessor(model_file=vocabulary("piece_bpe_32k.model"))
    codec = MergeCodec(vocabulary("piece_bpe_32k.model"))
    for t in texts:
        ids = sp.encode(t, add_eos=True)
        assert codec.both(t)[1:] == (" ".join(map(str, ids)), sp.decode(ids)) and codec.encode(t) == ids and codec.decode(ids) == sp.decode(ids)
    words, own = Tokenizer.from_file(vocabulary("word_bpe_49k.json")), WordEncoder(vocabulary("word_bpe_49k.json"))
    assert [np.frombuffer(x, "<u2").tolist() for x in own.encode_batch(texts)] == [words.encode(t, add_special_tokens=False).ids for t in texts]


def test_packing(docs, rows):
    got = tokens.pack(docs, vocabulary("word_bpe_49k.json"), width=64, with_ids=True).collect()
    spans = sorted((r.sequence_id, r.offset, r.length) for r in got)
    assert spans[0][:2] == (0, 0)
    for (s, o, n), (s2, o2, _) in zip(spans, spans[1:]):
        assert (s2, o2) == ((s, o + n) if o + n < 64 else (s + 1, 0))
    own = WordEncoder(vocabulary("word_bpe_49k.json"))
    pieces = defaultdict(list)
    for r in got:
        pieces[r.doc_id].append((r.start, bytes(r.ids)))
    for d, t in rows:
        if d not in (None, 100_004):
            assert b"".join(x for _, x in sorted(pieces[d])) == np.r_[np.frombuffer(own.encode(t), "<u2"), 2].astype("<u4").tobytes()


def test_repeated_bytes(docs, rows):
    texts = {d: t.encode() for d, t in rows if d is not None}
    got = {r.doc_id: (r.n_bytes, r.n_removed, r.n_spans, r.kept_sha256) for r in suffixes.repeated_bytes(docs).collect()}
    seen: set = set()
    for d in sorted(texts):
        t = texts[d]
        cover = bytearray(len(t))
        for p in range(len(t) - 49):
            if t[p : p + 50] in seen:
                cover[p : p + 50] = b"\1" * 50
        seen.update(t[p : p + 50] for p in range(len(t) - 49))
        spans = sum(1 for p, c in enumerate(cover) if c and not (p and cover[p - 1]))
        assert got[d] == (len(t), sum(cover), spans, hashlib.sha256(bytes(c for c, v in zip(t, cover) if not v)).hexdigest())


def test_quality(spark, docs, rows):
    texts = dict(rows)
    rules = quality.fit(docs, table(spark, SF, "labels"))
    for r in quality.quality_rules(docs, rules).where("doc_id is not null").collect():
        t = texts[r.doc_id]
        w = re.findall(r"[^\x20\x09-\x0D]+", t)
        g = [tuple(w[i : i + 3]) for i in range(len(w) - 2)]
        often = Counter(g)
        covered = {i + k for i, x in enumerate(g) if often[x] > 1 for k in range(3)}
        lines = [x for x in t.split("\n") if re.search(r"[^\x20\x09-\x0D]", x)]
        assert (r.n_words, r.word_chars, r.n_dup_lines, r.n_repeat_words) == (len(w), sum(map(len, w)), len(lines) - len(set(lines)), len(covered))
        assert r.base_failed == (len(w) < 50 or 100 * len(covered) > 50 * len(w)) and r.kept == (not r.base_failed and r.rule == 0)
    made = [{f: random.Random(i).random() for f in quality.FEATURES} | {"bad": int(i % 10 == 0)} for i in range(300)]
    for r in made:
        r["symbol_share"] = 0.9 if r["bad"] else 0.1
    assert [[t.feature for t in x] for x in quality.learn(made).rules] == [["symbol_share"]] and quality.learn([]).rules == []


def test_passages(spark):
    rng = random.Random(5)
    word = lambda: "".join(rng.choice("abcdefghij") for _ in range(5))
    text = lambda n: [word() for _ in range(n)]
    shared, near = text(70), text(80)
    changed = near[:40] + [word()] + near[41:]
    rows = [(1, text(100) + shared + text(50)), (2, text(30) + shared), (3, near + text(90)), (4, text(60) + changed), (5, text(200)), (6, text(120) + shared[:30]), (7, [])]
    got = {r.doc_id: (r.n_passages, r.partner_id) for r in passages.repeated_passages(spark.createDataFrame([(d, " ".join(w)) for d, w in rows], "doc_id long, text string")).collect()}
    assert got == {1: (1, 2), 2: (1, 1), 3: (1, 4), 4: (1, 3), 5: (0, None), 6: (0, None), 7: (0, None)}


def test_empty_tables(spark, docs, tmp_path):
    docs.limit(0).write.parquet(f"{tmp_path}/e")
    empty = spark.read.parquet(f"{tmp_path}/e")
    model = toxicity.train([], [])
    assert quality.quality_rules(empty, quality.DecisionList([])).count() == 0
    for out in (exact.exact_dedup(empty), jaccard.jaccard_components(empty), secrets.scan(empty, secrets.fit(empty)), toxicity.toxicity(empty, model), tokens.token_counts(empty, vocabulary("byte_bpe_50k.json")), tokens.pack(empty, vocabulary("word_bpe_49k.json")), suffixes.repeated_bytes(empty), tokens.piece_codec(empty, vocabulary("piece_bpe_32k.model")), passages.repeated_passages(empty)):
        assert out.count() == 0


def test_jaccard_near_misses_of_one_template(spark):
    """Texts off one template by many or few words: groups that stay apart still lose no link."""

    rng = random.Random(7)
    base, rows = [f"w{i}" for i in range(90)], []
    for i in range(60):
        words = list(base)
        for at in rng.sample(range(90), rng.choice([0, 1, 2, 3, 4, 6])):
            words[at] = f"x{rng.randrange(40)}"
        rows.append((i, " ".join(words)))
    got = {r.doc_id: r.component_id for r in jaccard.jaccard_components(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    sets = {i: {tuple(t.split()[j : j + 4]) for j in range(87)} for i, t in rows}
    want = {i: i for i in sets}
    for _ in sets:
        for a in sets:
            for b in sets:
                if 100 * len(sets[a] & sets[b]) >= 85 * len(sets[a] | sets[b]):
                    want[a] = want[b] = min(want[a], want[b])
    assert got == want and 1 < len(set(want.values())) < 60


def test_components_of_a_shuffled_chain(spark):
    """Long chains with ids in no order: 60 rounds of neighbours' labels do not reach the ends."""
    rng = random.Random(11)
    ids = rng.sample(range(10_000), 1003)
    chains = [ids[:1000], ids[1000:]]
    links = spark.createDataFrame([(min(a, b), max(a, b)) for c in chains for a, b in zip(c, c[1:])], "a long, b long").coalesce(2)
    got = {r.id: r.label for r in graph.components(links).collect()}
    assert got == {v: min(c) for c in chains for v in c}


def test_passages_of_a_text_that_quotes_itself():
    """A sentence of the passage before the passage, and the passage twice: every place is found."""
    rng = np.random.default_rng(3)
    sh = lambda w: jaccard.shingles([str(x).encode() for x in w], 5)
    x, y = (rng.integers(0, 10**9, n).tolist() for n in (50, 40))
    quoting, plain = sh(x[10:25] + y + x), sh(y[:20][::-1] + x)
    assert passages.passages_of(quoting, plain, 46, 0.8) == [(55, 101, 20, 66)]
    assert passages.passages_of(plain, quoting, 46, 0.8) == [(20, 66, 55, 101)]
    twice = sh(x + y + x)
    assert {q[:2] for q in passages.passages_of(twice, plain, 46, 0.8)} == {(0, 46), (90, 136)}
    assert {q[2:] for q in passages.passages_of(plain, twice, 46, 0.8)} == {(0, 46), (90, 136)}
    same = sh(["a", "b", "c"] * 2000)
    assert passages.passages_of(same, same, 46, 0.8) == [(0, 5996, 0, 5996)]


def test_passages_whose_sentences_are_common(spark):
    """A passage made of sentences that earlier texts quote one by one: its minima alone lead to those texts only."""
    rng = random.Random(9)
    text = lambda n: ["".join(rng.choice("abcdefghij") for _ in range(6)) for _ in range(n)]
    rows, want = [], {}
    for x in range(40):
        shared = text(60)
        for i in range(6):
            for side in (0, 1):
                rows.append((100 * x + 2 * i + side, text(60) + shared[10 * i : 10 * i + 10] + text(40)))
        rows += [(100 * x + 50, text(70) + shared), (100 * x + 60, text(20) + shared[30:45] + text(50)), (100 * x + 70, shared + text(70))]
        want |= {100 * x + 50: (1, 60, 100 * x + 70), 100 * x + 70: (1, 60, 100 * x + 50)}
    got = passages.repeated_passages(spark.createDataFrame([(d, " ".join(w)) for d, w in rows], "doc_id long, text string").coalesce(1)).where("n_passages > 0").collect()
    assert {r.doc_id: (r.n_passages, r.repeated_words, r.partner_id) for r in got} == want


def test_repeated_bytes_told_rows_of_one_document(spark):
    """A text beyond 1 MiB that straddles small chunks: the row that tells of several documents may share its doc_id."""
    rng = random.Random(4)
    line = lambda n: "".join(rng.choice("abcdefghijklmnopqrstuvwxyz ") for _ in range(n))
    found = [line(50) for _ in range(300)]
    texts = {1: "".join(line(40) + x + line(40) for x in found)}
    texts[2] = "".join(line(40) + x + line(40) for x in found) + line(1 << 21) + "".join(line(40) + x + line(40) for x in found)
    seen: set = set()
    df = spark.createDataFrame(sorted(texts.items()), "doc_id long, text string").coalesce(1)
    parts = spark.conf.get("spark.sql.shuffle.partitions")
    spark.conf.set("spark.sql.shuffle.partitions", "1")
    got = {r.doc_id: r.n_removed for r in suffixes.repeated_bytes(df, chunk=1000).collect()}
    spark.conf.set("spark.sql.shuffle.partitions", parts)
    for d in sorted(texts):
        t = texts[d].encode()
        cover = np.zeros(len(t), bool)
        for p in range(len(t) - 49):
            if t[p : p + 50] in seen:
                cover[p : p + 50] = True
        seen.update(t[p : p + 50] for p in range(len(t) - 49))
        assert got[d] == cover.sum()
