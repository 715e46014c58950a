"""Awkward rows and long texts of the text operators, against brute force and the libraries."""

import hashlib
import random
import re
from collections import Counter

import numpy as np
import pytest
from pyspark.sql import functions as F

from shotgrid.llm import exact, jaccard, passages, quality, secrets, suffixes, tokens, toxicity
from shotgrid.llm.bpe import WordEncoder
from shotgrid.llm.common import table
from shotgrid.llm.queries import vocabulary
from tests.llm.test_operators import PATTERNS

SF = "/root/testdata/sf0.001"


def frame(spark, rows):
    return spark.createDataFrame(rows, "doc_id long, text string")


def test_word_ids_equal_the_library_below_u0250():
    from tokenizers import Tokenizer

    rng, lib, own = random.Random(2), Tokenizer.from_file(vocabulary("word_bpe_49k.json")), WordEncoder(vocabulary("word_bpe_49k.json"))
    texts = ["ƊR", "Ɛî", "ȾĲ", "İstanbul ıI", "ǅ ǈ ß ẞ"] + ["".join(chr(rng.choice([rng.randrange(1, 0x250), rng.randrange(0x20, 0x7F)])) for _ in range(rng.randrange(1, 12))) for _ in range(2000)]
    assert [np.frombuffer(x, "<u2").tolist() for x in own.encode_batch(texts)] == [lib.encode(t, add_special_tokens=False).ids for t in texts]


def test_exact_with_clashing_names_and_without_files(spark, tmp_path):
    rows = [(1, "A b"), (2, "a B"), (3, None), (4, ""), (2, "a B"), (None, "z")]
    made = frame(spark, rows)
    made.withColumns({"_metadata": F.lit("m"), "place": F.lit("p"), "digest": F.lit(1), "row": F.lit(2)}).write.parquet(f"{tmp_path}/d")
    for docs in (made, spark.read.parquet(f"{tmp_path}/d"), made.where("doc_id > 0 or doc_id is null")):
        got = exact.exact_dedup(docs)
        assert sorted((r.doc_id or 0, r.keep_id or 0, r.group_size) for r in got.collect()) == [(0, 0, 1), (1, 2, 3), (2, 2, 3), (2, 2, 3), (3, 4, 2), (4, 4, 2)]
        assert got.where("kept").count() == 3


def test_secrets_of_long_runs_and_many_matches(spark):
    rng = random.Random(1)
    blob = "".join(rng.choice("ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789+/") for _ in range(300_000))
    many = " ".join(f"token=abcdefgh{i}" for i in range(20_000))
    rows = [(1, blob), (2, many), (3, "x" * 100_000), (4, None), (5, "key zq8Vt3Lm0XwP7rKd2Yb5 and plain_identifier_name_2 here"), (5, "again")]
    rows += [(10 + i, t) for i, t in enumerate(("ordinary words of a language", "some_identifier_with_words", "anotherIdentifierInCamelCase"))]
    docs = frame(spark, rows)
    model = secrets.fit(docs)
    got = secrets.scan(docs, model).collect()
    for r, (d, t) in zip(sorted(got, key=lambda r: r.doc_id), sorted(rows, key=lambda x: x[0])):
        found = sorted((m.start(), k, m.end(), n) for k, (n, p, least) in enumerate(PATTERNS) for m in p.finditer(t or "") if len(m.group(2 if k == 0 else 0)) >= least)
        if d != 5:
            assert r.doc_id == d and r.base_sha256 == hashlib.sha256(",".join(f"{n}:{s}:{e}" for s, _, e, n in found).encode()).hexdigest()
    by = {r.doc_id: r for r in got if r.spans}
    assert by[1].spans == "markov:0:300000" and by[2].n_assign == 20_000 and 3 not in by
    assert by[5].spans == "markov:4:24" and by[5].n_assign == 0


def test_markov_model_counts_all_documents(spark):
    few = [(i, "zebra quilt") for i in range(30)]
    assert secrets.word_pairs(frame(spark, few + [(99, "jazz " * 9)])) == Counter({(a, b): n for w in ("^zebra$", "^quilt$", "^jazz$") for a, b in zip(w, w[1:]) for n in [sum((a, b) in list(zip(x, x[1:])) for x in ("^zebra$", "^quilt$", "^jazz$"))]})


def test_toxicity_bounds_and_held_out(spark):
    import zlib

    bad, good = ["you idiot person", "what an idiot", "idiot go away"], ["good day friend", "a fine morning", "the weather is fine"]
    rows = [(i, (bad if i % 3 == 0 else good)[i % 3 if i % 3 else i // 3 % 3] + f" {i % 7}") for i in range(300)] + [(900, None), (901, "ü" * 60_000)]
    docs, labels = frame(spark, rows), spark.createDataFrame([(i, int(i % 3 == 0)) for i in range(300)] + [(901, 0), (None, 1), (902, None)], "doc_id long, toxic int")
    model = toxicity.fit(docs, labels, rows=200, most_bytes=50_000)
    got = {r.doc_id: r for r in toxicity.toxicity(docs, model).collect()}
    assert all(r.held_out == (zlib.crc32(str(d).encode()) % 4 == 2) for d, r in got.items())
    held = [(r.predicted, int(d % 3 == 0)) for d, r in got.items() if r.held_out and d < 300]
    assert len(held) > 40 and sum(p == y for p, y in held) == len(held)
    assert toxicity.fit(docs, labels, rows=200, most_bytes=0).score("idiot") == toxicity.train([], []).score("idiot")


def test_toxicity_held_out_accuracy(spark):
    """Figures on the given table: most held-out toxic rows are found, few others are marked."""
    docs, labels = table(spark, "/root/testdata/sf0.1", "documents"), table(spark, "/root/testdata/sf0.1", "labels")
    got = toxicity.toxicity(docs, toxicity.fit(docs, labels)).where("held_out").join(labels, "doc_id").groupBy("toxic").agg(F.avg("predicted").alias("p")).collect()
    share = {r.toxic: r.p for r in got}
    assert share[1] > 0.8 and share[0] < 0.03


def test_token_queries(spark):
    import sentencepiece
    from tokenizers import Tokenizer

    rows = [(1, "Hello there,  world"), (1, "Hello there,  world"), (2, None), (3, ""), (None, "naïve 日本"), (4, "ab " * 3000), (5, "q" * 200_000)]
    docs = frame(spark, rows).withColumns({"n_tokens": F.lit("x"), "ids": F.lit(0)})
    lib = Tokenizer.from_file(vocabulary("byte_bpe_50k.json"))
    key = lambda x: (x[0] is None, x[0] or 0, *x[1:])
    want = sorted(((d, len((t or "").encode()), (n := len(lib.encode(t or "", add_special_tokens=False).ids)), n > 512) for d, t in rows), key=key)
    assert sorted((tuple(r) for r in tokens.token_counts(docs, vocabulary("byte_bpe_50k.json")).collect()), key=key) == want
    short = [(d, t) for d, t in rows if t is None or len(t) < 50]
    for r, (d, t) in zip(tokens.truncate_to_budget(frame(spark, short), vocabulary("byte_bpe_50k.json"), 3).collect(), short):
        n = [len(lib.encode((t or "")[:i], add_special_tokens=False).ids) for i in range(len(t or "") + 1)]
        at = max(i for i, c in enumerate(n) if c <= 3)
        assert (r.doc_id, r.n_chars, r.n_tokens) == (d, at, n[at])
    sp = sentencepiece.SentencePieceProcessor(model_file=vocabulary("piece_bpe_32k.model"))
    sha = lambda s: hashlib.sha256(s.encode()).hexdigest()
    want = sorted(((d, len(i := sp.encode(t or "", add_eos=True)), sha(" ".join(map(str, i))), sha(sp.decode(i))) for d, t in rows), key=key)
    assert sorted((tuple(r) for r in tokens.piece_codec(docs, vocabulary("piece_bpe_32k.model"), full=False).collect()), key=key) == want


def test_packed_ids_and_checksums(spark):
    import zlib

    from tokenizers import Tokenizer

    lib = Tokenizer.from_file(vocabulary("word_bpe_49k.json"))
    rows = [(1, "some words " * 3000), (2, None), (3, "tail"), (3, "tail")]
    got = tokens.pack(frame(spark, rows), vocabulary("word_bpe_49k.json")).collect()
    ids = {d: lib.encode(t or "", add_special_tokens=False).ids + [2] for d, t in rows}
    for r in got:
        piece = np.array(ids[r.doc_id][r.start : r.start + r.length], "<u4")
        assert r.doc_tokens == len(ids[r.doc_id]) and r.ids_crc32 == zlib.crc32(piece.tobytes()) and r.offset + r.length <= 4096
    assert sum(r.length for r in got) == sum(len(ids[d]) for d, _ in rows)


def test_quality_counts_of_symbols_and_long_texts(spark):
    rows = [(1, "a#b $$ % plain <x>|y"), (2, "word " * 60_000), (3, None), (4, "\n\n \n"), (4, "\n\n \n"), (5, " ".join(f"w{i}" for i in range(40_000)))]
    got = {r.doc_id: r for r in quality.quality_rules(frame(spark, rows).withColumn("kept", F.lit(1)), quality.DecisionList([])).collect()}
    assert {d: r.n_symbols for d, r in got.items()} == {d: len(re.findall(r"[#*$%&|<>]", t or "")) for d, t in rows}
    assert (got[2].n_words, got[2].n_repeat_words, got[2].kept) == (60_000, 60_000, False) and got[5].kept and got[5].n_repeat_words == 0
    assert (got[3].n_words, got[3].base_failed, got[4].n_dup_lines) == (0, True, 0)


def test_quality_rules_on_rows_not_fitted(spark):
    made = [{f: random.Random(7 * i).random() for f in quality.FEATURES} | {"bad": int(i % 8 == 0)} for i in range(900)]
    for i, r in enumerate(made):
        if r["bad"]:
            r["symbol_share" if i % 16 else "upper_share"] = 5.0 + random.Random(i).random()
    random.Random(0).shuffle(made)  # fit() hands rows over in order of a hash
    rules = quality.learn(made[:600])
    assert all(rules.verdict(r) == (not r["bad"]) for r in made[600:])


def test_jaccard_of_awkward_rows_and_one_id_with_two_texts(spark):
    long = " ".join(f"w{i}" for i in range(60_000))
    rows = [(1, long), (2, long + " more"), (3, None), (4, ""), (5, "one two"), (6, "ONE  two"), (7, "a b c d e"), (7, "f g h i j"), (8, "f g h i j"), (9, "a b c d e"), (None, "one two"), (5, "one two")]
    got = sorted(((r.doc_id or 0, r.n_shingles, r.component_id or 0) for r in jaccard.jaccard_components(frame(spark, rows).withColumns({"n": F.lit(0), "same": F.lit(1), "label": F.lit(2)})).collect()))
    assert [g for g in got if g[0] not in (7, 8, 9)] == [(0, 1, 0), (1, 59_997, 1), (2, 59_998, 1), (3, 0, 3), (4, 0, 4), (5, 1, 5), (5, 1, 5), (6, 1, 5)]
    assert sorted(g[0] for g in got if g[2] == 7) in ([7, 7, 8], [7, 7, 9]) and sum(g[2] in (8, 9) for g in got) == 1


def test_words_are_hashed_alike_wherever_they_stand():
    rng, seen = random.Random(1), {}
    texts = ["".join(rng.choice(["a", "B", " ", "\n", "\x1c", "é", "ab", "\t", "Zz"]) for _ in range(rng.choice([0, 1, 50, 300]))) for _ in range(400)]
    texts.append(" ".join(rng.choice(["x" * rng.choice([1, 4095, 4096, 4097, 70_000, 140_000]), "foo"]) for _ in range(40)))
    for t in texts:
        words = re.findall(rb"[^\x20\x09-\x0D]+", t.encode().lower())
        h = jaccard.word_hashes(t).tolist()
        assert len(words) == len(h) and all(seen.setdefault(w, x) == x for w, x in zip(words, h))
    assert len(set(seen.values())) == len(seen)


def test_repeated_bytes_of_texts_over_two_buffers(spark):
    rng = random.Random(8)
    line = lambda n: "".join(rng.choices("abcdefghijklmnopqrstuvwxyz ", k=n))
    shared = [line(70) for _ in range(50)]
    texts = {1: line(30).join(shared), 2: line(1_200_000).join(shared[:3]), 3: line(2_500_000) + shared[4] + "é" * 60, 4: "é" * 80, 5: None, 6: ""}
    rows = list(texts.items()) + [(4, "é" * 80), (None, shared[0])]
    got = {r.doc_id: r.n_removed for r in suffixes.repeated_bytes(frame(spark, rows).withColumn("spans", F.lit(0)).repartition(2)).collect() if r.doc_id}
    seen: set = set()
    for d in sorted(texts):
        t = (texts[d] or "").encode()
        cover = np.zeros(len(t), bool)
        for p in range(len(t) - 49):
            if t[p : p + 50] in seen:
                cover[p : p + 50] = True
        seen.update(t[p : p + 50] for p in range(len(t) - 49))
        assert got[d] == cover.sum()


def covered(texts, t=46, share=0.8):
    """Words of each text that lie in a window of 50 words similar to some window of another text, by brute force."""
    windows = [(d, s, frozenset(tuple(w[i : i + 5]) for i in range(s, s + t))) for d, w in texts.items() for s in range(len(w) - 49)]
    holds: dict = {}
    for i, (_, _, w) in enumerate(windows):
        for x in w:
            holds.setdefault(x, []).append(i)
    out = {d: set() for d in texts}
    for d, s, w in windows:
        hits = Counter(i for x in w for i in holds[x] if windows[i][0] != d)
        if any(n >= share * (len(w) + len(windows[i][2]) - n) for i, n in hits.items()):
            out[d].update(range(s, s + 50))
    return out


@pytest.mark.parametrize("edit", [0, 1, 2])
def test_passages_found_of_those_brute_force_finds(spark, edit):
    """Passages in two texts each, whose first 44 words stand in 14 others; edit: words changed in one of the two."""
    rng = random.Random(13 + edit)
    text = lambda n: ["".join(rng.choices("abcdefghij", k=6)) for _ in range(n)]
    texts: list = []
    for _ in range(12):
        shared = text(60)
        texts += [text(30) + shared[:44] + text(30) for _ in range(14)]
        changed = list(shared)
        for at in rng.sample(range(8, 52), edit):
            changed[at] = text(1)[0]
        texts += [text(40) + shared + text(20), text(15) + changed + text(50)]
    rng.shuffle(texts)
    named = dict(enumerate(texts))
    want = {d: x for d, x in covered(named).items() if x}
    got = {r.doc_id: r for r in passages.repeated_passages(frame(spark, [(d, " ".join(w)) for d, w in named.items()])).collect()}
    found = {d: {p for x in r.passages for p in range(x.s, x.e)} for d, r in got.items()}
    hit, total = sum(len(found[d] & x) for d, x in want.items()), sum(map(len, want.values()))
    assert total and hit >= 0.9 * total
    assert all(not r.n_passages for d, r in got.items() if d not in want and len(found[d] - want.get(d, set())) > 12)


def test_passages_of_awkward_rows(spark):
    rng = random.Random(3)
    text = lambda n: " ".join("".join(rng.choices("abcdefghij", k=6)) for _ in range(n))
    a, b, long, other = text(60), text(70), text(60_000), text(60)
    stands = min((b, other), key=lambda x: hashlib.sha256(jaccard.word_hashes(x).tobytes()).digest())
    rows = [(1, a), (1, a), (2, None), (3, ""), (4, "short text"), (None, a), (5, text(10) + " " + a), (6, b), (6, other), (7, b), (8, long + " " + text(9)), (9, text(3) + " " + long)]
    got = sorted(((r.doc_id or 0), r.n_passages, r.partner_id or 0) for r in passages.repeated_passages(frame(spark, rows).withColumns({"same": F.lit(1), "n": F.lit(2), "rep": F.lit(3), "s": F.lit(4), "found": F.lit(5)})).collect())
    assert [g for g in got if g[0] != 6] == [(0, 0, 0), (1, 1, 5), (1, 1, 5), (2, 0, 0), (3, 0, 0), (4, 0, 0), (5, 1, 1), (7, 1, 6) if stands == b else (7, 0, 0), (8, 1, 9), (9, 1, 8)]


def test_repeated_bytes_leaves_no_shuffle_files(spark):
    """Each step's shuffle files are gone when it ends, so the steps do not add up on the disks; the session's setting is as before."""
    files = spark._jvm.org.apache.spark.SparkEnv.get().blockManager().diskBlockManager()
    held = lambda: {str(f) for f in files.getAllFiles().mkString("\n").split("\n") if "shuffle_" in f}
    key = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"
    before, was = held(), spark.conf.get(key, None)
    docs = spark.createDataFrame([(i, f"{i} " + "the same sixty letters stand in each of these texts, as it is " * 3) for i in range(40)], "doc_id long, text string")
    out = suffixes.repeated_bytes(docs)
    assert not held() - before and spark.conf.get(key, None) == was
    assert sum(r.n_removed > 0 for r in out.collect()) == 39


def test_passages_of_a_large_group_of_near_misses_are_all_tried(spark, monkeypatch):
    """Texts of one template that differ in a few words each: no fewer words are found than by pairing all rows of every group."""
    rng = random.Random(8)
    base, rows = [f"w{rng.randrange(10**6)}" for _ in range(56)], []
    for pair in range(110):  # two texts a pair, one word apart; two pairs are three or four words apart
        for d in range(2):
            one = random.Random(pair)
            words = list(base)
            for i in sorted(one.sample(range(6, 50), 2)):
                words[i] = f"x{i}y{pair}"
            if d:
                words[28] = f"z{pair}"
            rows.append((2 * pair + d, " ".join(words)))
    docs = frame(spark, rows)
    found = lambda: {r.doc_id: r.repeated_words for r in passages.repeated_passages(docs).collect()}
    for name, value in (("FIRST", 1), ("SMALL", 1), ("SKETCH", 1)):  # the nearest by such a coarse sketch is often a miss
        monkeypatch.setattr(passages, name, value)
    got = found()
    monkeypatch.setattr(passages, "SMALL", 10**6)
    want = found()
    assert sum(want.values()) > 0 and [d for d in want if got[d] < want[d]] == []


def test_hashes_of_texts_together():
    """Short texts hashed together, with long, empty and wordless ones among them, have the hashes of each alone."""
    rng = random.Random(2)
    texts = ["".join(rng.choice(["a", "B", " ", "\n", "\x1c", "é", "ab", "\t", "x" * 300]) for _ in range(rng.choice([0, 1, 2, 5, 50, 3000]))).encode() for _ in range(300)]
    texts.insert(100, b" ".join(b"x" * n for n in (4095, 4097, 70_000, 140_000)))
    for k in (0, 5):
        want = [jaccard.shingles(w, k) if k else w for w in map(jaccard.word_hashes, texts)]
        assert all(np.array_equal(a, b) for a, b in zip(jaccard.hashes_of(texts, k), want, strict=True))


def test_passages_of_a_large_group_with_a_common_repeated_line(monkeypatch):
    """Documents that repeat one line, one group of long runs: every start has its partner, without the windows of each being paired with all."""
    rng = np.random.default_rng(4)
    line, t = rng.integers(1, 1 << 62, 12, np.uint64), 46
    rows = [(d, True, 7, 250, 5, np.resize(line, 250 + t).tobytes()) for d in range(400)]  # equal
    near = np.resize(line, 250 + t)
    near[100::60] = rng.integers(1, 1 << 62, len(near[100::60]), np.uint64)
    rows += [(400 + d, True, 7, 250, 5, x.tobytes()) for d, x in enumerate((near, rng.integers(1, 1 << 62, 250 + t, np.uint64)))]  # a shingle changed here and there; all changed
    count, alike = [0], passages.windows_alike
    monkeypatch.setattr(passages, "windows_alike", lambda sa, sb, xa, *x: count.__setitem__(0, count[0] + len(xa)) or alike(sa, sb, xa, *x))
    found: dict = {}
    for doc, s, e, other in passages._group_passages(rows, 5, t, 0.8):
        assert doc != other
        found.setdefault(doc, set()).update(range(s, e))
    sets = lambda d: [set(np.frombuffer(rows[d][5], np.uint64)[p : p + t].tolist()) for p in range(251)]
    want = {7 + p + i for p, (a, b) in enumerate(zip(sets(0), sets(400))) if len(a & b) >= 0.8 * len(a | b) for i in range(t + 4)}
    assert found == {**{d: set(range(7, 7 + 250 + t + 4)) for d in range(400)}, **({400: want} if want else {})}
    assert count[0] < 2000  # 400 * 400 * 251 pairs of windows
