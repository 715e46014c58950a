"""Exact subword tokenisation by automaton matches and pair compatibility, with per-process caches.

Two facts are used. A token sequence is what byte-pair merging gives if and only if every neighbouring pair
of it is what merging gives for that pair's own characters. So the last token of every prefix can be found left to
right from the matches that end there, and a whole unit can be encoded by longest matches with backtracking.
"""

from __future__ import annotations

import heapq
import json
import re
import unicodedata

import ahocorasick
import numpy as np

#: Entries that a per-process cache of words may hold before it starts anew.
CACHE_ENTRIES = 250_000
#: Longer units are not cached.
CACHE_UNIT = 64
#: Texts of characters below this one are split by the patterns here; others by the library's own splitter.
PLAIN = 0x250
_OUTSIDE = re.compile(f"[^\\x00-{chr(PLAIN - 1)}]")


def char_class(kind: str) -> str:
    """Members below PLAIN of a general category (by its first letter), or of white space, for a character class."""
    has = str.isspace if kind == "space" else lambda c: unicodedata.category(c)[0] == kind
    codes = [i for i in range(PLAIN) if has(chr(i)) and not (kind == "space" and 0x1C <= i <= 0x1F)]
    runs = [(a, b) for a, b in zip([i for i in codes if i - 1 not in codes], [i for i in codes if i + 1 not in codes])]
    return "".join(f"\\u{a:04x}-\\u{b:04x}" for a, b in runs)


class Cache(dict):
    """dict that fills itself by make(key) and is emptied when it is full."""

    def __init__(self, make, most=CACHE_ENTRIES):
        self.make, self.most = make, most

    def __missing__(self, key):
        value = self.make(key)
        if len(key) <= CACHE_UNIT:
            if len(self) >= self.most:
                self.clear()
            self[key] = value
        return value


def merge(symbols: list, rank, steps: list | None = None) -> list:
    """Byte-pair merging of a list of symbols: the lowest rank(a, b) first, leftmost among equals; None: no merge.

    Linked list and heap, so long units cost n log n."""
    n = len(symbols)
    sym, nxt, prv = list(symbols), list(range(1, n + 1)), list(range(-1, n - 1))
    heap = []
    for i in range(n - 1):
        if (r := rank(sym[i], sym[i + 1])) is not None:
            heap.append((r, i, sym[i], sym[i + 1]))
    heapq.heapify(heap)
    while heap:
        _, i, a, b = heapq.heappop(heap)
        j = nxt[i] if sym[i] is not None else n
        if j >= n or sym[i] != a or sym[j] != b:
            continue
        sym[i], sym[j] = a + b, None
        if steps is not None:
            steps.append((a, b))
        nxt[i] = nxt[j]
        if nxt[i] < n:
            prv[nxt[i]] = i
            if (r := rank(sym[i], sym[nxt[i]])) is not None:
                heapq.heappush(heap, (r, i, sym[i], sym[nxt[i]]))
        if (p := prv[i]) >= 0 and (r := rank(sym[p], sym[i])) is not None:
            heapq.heappush(heap, (r, p, sym[p], sym[i]))
    return [s for s in sym if s is not None]


def byte_letters() -> list[str]:
    """The printable character that stands for each byte in byte-level vocabularies."""
    plain = [b for b in range(256) if 33 <= b <= 126 or 161 <= b <= 172 or b >= 174]
    rest = iter(range(256, 512))
    return [chr(b) if b in set(plain) else chr(next(rest)) for b in range(256)]


class Pairs:
    """Whether two tokens may stand side by side: re-merging their joined characters must give them back.

    Merging a token's own characters builds a tree. Its right edge (left edge for the second token) is kept as a list of
    symbols, innermost first, each with the rank at which the next merge takes it away. Re-merging only has to follow the
    two edges: the tokens don't fit if a merge across the boundary comes before both of its symbols are taken."""

    def __init__(self, rank):
        self.rank, self.right, self.left, self.known = rank, {}, {}, {}

    def edges(self, t: str) -> None:
        for store, last in ((self.right, True), (self.left, False)):
            edge = store[t] = []
            symbol, at = t, float("inf")
            while True:
                edge.append((symbol, at))
                if len(symbol) == 1:
                    break
                a, b = self.splits[symbol]
                at, symbol = self.rank(a, b), b if last else a
            edge.reverse()

    def learn(self, tokens) -> list[str]:
        """The tokens that merging can reach, with the last merge of each."""
        self.splits, reached = {}, []
        for t in tokens:
            if len(t) > 1:
                steps: list = []
                if merge(list(t), self.rank, steps) != [t]:
                    continue
                self.splits[t] = steps[-1]
            reached.append(t)
        for t in reached:
            self.edges(t)
        return reached

    def __call__(self, a: str, b: str) -> bool:
        got = self.known.get((a, b))
        if got is None:
            if len(self.known) >= CACHE_ENTRIES:
                self.known.clear()
            got = self.known[a, b] = self.remerged(a, b)
        return got

    def remerged(self, a: str, b: str) -> bool:
        xs, ys, i, j = self.right[a], self.left[b], 0, 0
        while True:
            (x, x_at), (y, y_at) = xs[i], ys[j]
            r = self.rank(x, y)
            if r is not None and r < x_at and r <= y_at:  # of equal ranks, the leftmost merge comes first
                return False
            if x_at <= y_at:
                if x_at == float("inf"):
                    return True
                i += 1
            else:
                j += 1


class PrefixCounter:
    """Token counts of every prefix for a byte-level vocabulary file, by dynamic programming."""

    def __init__(self, path: str):
        from tokenizers import Tokenizer

        spec = json.load(open(path, encoding="utf-8"))
        self.path, self.letters = path, byte_letters()
        pairs = [tuple(m.split(" ")) if isinstance(m, str) else tuple(m) for m in spec["model"]["merges"]]
        self.ranks = {p: i for i, p in enumerate(pairs)}
        self.added = [t["content"] for t in spec["added_tokens"]]
        self.cut = re.compile("|".join(map(re.escape, sorted(self.added, key=len, reverse=True)))) if self.added else None
        rank = lambda a, b: self.ranks.get((a, b))
        self.fits = Pairs(rank)
        self.auto = ahocorasick.Automaton()
        for t in self.fits.learn(sorted({*self.letters, *(a + b for a, b in pairs)})):
            self.auto.add_word(t, t)
        self.auto.make_automaton()
        # The pattern that splits text before merging, with white space as the Unicode property.
        w, c, d = map(char_class, ("space", "L", "N"))
        self.pattern = re.compile(rf"'s|'t|'re|'ve|'m|'ll|'d| ?[{c}]+| ?[{d}]+| ?[^{w}{c}{d}]+|[{w}]+(?![^{w}])|[{w}]+")
        self.tokenizer = Tokenizer.from_file(path)
        self.counts = Cache(lambda unit: self.prefixes(unit.encode())[-1])

    def prefixes(self, unit: bytes) -> list[int]:
        """counts[i]: tokens of the first i bytes of one unit, a pretoken."""
        s = "".join(map(self.letters.__getitem__, unit))
        n, fits = len(s), self.fits
        last, counts, done = [""] * (n + 1), [0] * (n + 1), 0
        for end, t in self.auto.iter(s):
            end += 1
            if end == done:
                continue
            at = end - len(t)
            if not at or fits(last[at], t):
                last[end], counts[end], done = t, counts[at] + 1, end
        return counts

    def units(self, text: str) -> list[str]:
        """The pretokens of a text without added tokens."""
        if _OUTSIDE.search(text) is None:
            return self.pattern.findall(text)
        return [text[a:b] for _, (a, b) in self.tokenizer.pre_tokenizer.pre_tokenize_str(text)]

    def parts(self, text: str) -> list[str]:
        return self.cut.split(text) if self.cut is not None and "<" in text else [text]

    def count(self, text: str) -> int:
        parts = self.parts(text)
        total = len(parts) - 1
        get = self.counts.__getitem__
        for p in parts:
            if p:
                total += sum(map(get, self.units(p)))
        return total

    def running(self, text: str) -> list[int]:
        """running[i]: exact token count of text[:i] for every i, in characters.

        Pretokens before the last two of a prefix don't change when the prefix grows, so only the tail of a prefix is
        split again; a prefix inside an added token counts its characters as text."""
        out, total = [0], 0
        for k, part in enumerate(self.parts(text)):
            if k:
                word = next(w for w in self.added if text.startswith(w, len(out) - 1))
                tail = text[max(0, len(out) - 1 - 32) : len(out) - 1]
                base = total - self.count(tail) if tail else total
                for j in range(1, len(word)):
                    out.append(base + self.count(tail + word[:j]) if self.count(tail) + base == total else self.count(text[: len(out)]))
                total += 1
                out.append(total)
            spans, at = [], 0
            for u in self.units(part):
                spans.append((at, u))
                at += len(u)
            for x, (at, u) in enumerate(spans):
                if re.match(r"['\s]", u, re.U) or len(u) > 1 and u[0] == " " and not u[1:].isalnum() or (x and spans[x - 1][1][:1] == "'"):
                    back = max(0, x - 2)
                    lead = total - sum(self.counts[spans[i][1]] for i in range(back, x))
                    for j in range(1, len(u) + 1):
                        out.append(lead + sum(self.counts[v] for v in self.units(part[spans[back][0] : at + j])))
                else:
                    counts = self.prefixes(u.encode())
                    b = 0
                    for c in u:
                        b += len(c.encode())
                        out.append(total + counts[b])
                total += self.counts[u]
        return out


class MergeCodec:
    """Encoder and decoder for a sentence-piece file of merge type with byte fallback and a dummy prefix."""

    SPACE = "▁"

    def __init__(self, path: str):
        import sentencepiece

        lib = sentencepiece.SentencePieceProcessor(model_file=path)
        self.end = lib.eos_id()
        self.ids, self.scores, self.byte_ids = {}, {}, [0] * 256
        for i in range(lib.get_piece_size()):
            p = lib.id_to_piece(i)
            if lib.is_byte(i):
                self.byte_ids[int(p[3:5], 16)] = i
            elif not (lib.is_control(i) or lib.is_unknown(i) or lib.is_unused(i)):
                self.ids[p], self.scores[p] = i, -lib.get_score(i)
        self.bytes_of = {i: p.encode() for p, i in self.ids.items()} | {i: bytes([b]) for b, i in enumerate(self.byte_ids)}
        self.rank = lambda a, b: self.scores.get(a + b)
        self.fits = Pairs(self.rank)
        self.auto = ahocorasick.Automaton()
        reached = set(self.fits.learn(self.ids))
        for p in reached:
            self.auto.add_word(p, p)
        self.auto.make_automaton()
        # The next shorter piece that starts a piece, for stepping back.
        self.shorter = {p: next((p[:k] for k in range(len(p) - 1, 0, -1) if p[:k] in reached), "") for p in reached}
        self.written = {p: f"{i} " for p, i in self.ids.items()}
        # Where no piece has a letter before such a character, nothing merges across: a word and its comma are two units.
        follow = {b for p in self.ids for a, b in zip(p, p[1:]) if a.isalpha()}
        stops = "".join(f"\\u{i:04x}" for i in range(PLAIN) if not chr(i).isalpha() and chr(i) not in follow)
        letters, w = char_class("L"), self.SPACE
        self.unit = re.compile(f"{w}*[{letters}]+(?=[{stops}])|{w}*[^{w}]+|{w}+")
        self.cache = Cache(self._made)

    def pieces(self, unit: str) -> list[str]:
        """Pieces and unknown characters of one unit: longest matches, stepping back from failed positions."""
        if unit.startswith(self.SPACE * 2):
            return merge(list(unit), self.rank)  # runs of spaces have pieces of equal score: merge them outright
        path = [p for _, p in self.auto.iter_long(unit)]
        if "".join(path) == unit and all(map(self.fits.__call__, path, path[1:])):
            return path  # longest matches all the way, and all neighbours fit
        longest: dict[int, str] = {}
        for end, piece in self.auto.iter(unit):
            longest[end - len(piece)] = piece  # of the matches that start here, the longest comes last
        fits, known, n, at, failed = self.fits, self.fits.known, len(unit), 0, 0
        path = []
        piece = longest.get(-1, "")
        while at < n:
            before = path[-1] if path else ""
            while piece:
                if not failed >> (at + len(piece)) & 1:
                    if not before or before not in self.ids:
                        break
                    ok = known.get((before, piece))
                    if fits(before, piece) if ok is None else ok:
                        break
                piece = self.shorter[piece]
            if not piece and at - 1 not in longest:  # a character outside the vocabulary: nothing merges across it
                piece = unit[at]
            if piece:
                path.append(piece)
                at += len(piece)
                piece = longest.get(at - 1, "")
            else:
                failed |= 1 << at
                piece = path.pop()
                at -= len(piece)
                piece = self.shorter[piece]
        return path

    def encode_unit(self, unit: str) -> list[int]:
        out: list[int] = []
        for p in self.pieces(unit):
            i = self.ids.get(p)
            out.extend([i] if i is not None else [self.byte_ids[b] for b in p.encode()])
        return out

    def _made(self, unit: str) -> tuple[int, str, bytes]:
        pieces = self.pieces(unit)
        try:
            ids = list(map(self.ids.__getitem__, pieces))
            return len(ids), "".join(map(self.written.__getitem__, pieces)), b"".join(map(self.bytes_of.__getitem__, ids))
        except KeyError:
            ids = self.encode_unit(unit)
            return len(ids), "".join(f"{i} " for i in ids), b"".join(map(self.bytes_of.__getitem__, ids))

    def units(self, text: str) -> list[str]:
        return self.unit.findall(self.SPACE + text.replace(" ", self.SPACE)) if text else []

    def encode(self, text: str) -> list[int]:
        return [i for u in self.units(text) for i in self.encode_unit(u)] + [self.end]

    def _plain(self, raw: bytes) -> str:
        text = raw.decode("utf-8", "replace")
        return (text[1:] if text.startswith(self.SPACE) else text).replace(self.SPACE, " ")

    def decode(self, ids: list[int]) -> str:
        return self._plain(b"".join(self.bytes_of.get(i, b"") for i in ids))

    def both(self, text: str) -> tuple[int, str, str]:
        """Number of ids, the ids in decimal joined by spaces, and the decoded text."""
        if not text:
            return 1, str(self.end), ""
        counts, ids, raw = zip(*map(self.cache.__getitem__, self.units(text)))
        return sum(counts) + 1, "".join(ids) + str(self.end), self._plain(b"".join(raw))


class WordEncoder:
    """Ids of a lower-casing word vocabulary by the tokenizers library, one call per different word."""

    def __init__(self, path: str):
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_file(path)
        spec = json.load(open(path, encoding="utf-8"))
        self.added = [t["content"] for t in spec["added_tokens"]]
        # The vocabulary's own split pattern.
        w, c, d = map(char_class, ("space", "L", "N"))
        self.pattern = re.compile(rf"'s|'t|'re|'ve|'m|'ll|'d|[{c}]+|[{d}]|[^{w}{c}{d}]+")
        self.ends = np.zeros(65536, bool)
        for t, i in spec["model"]["vocab"].items():
            self.ends[i] = t.endswith("</w>")
        self.cache = Cache(self._made)

    def _made(self, word: str) -> bytes:
        return np.array(self.tokenizer.encode(word, add_special_tokens=False).ids, "<u2").tobytes()

    def _learn(self, words: list[str]) -> None:
        """Encode words that the cache lacks in one call: the last token of each ends a word."""
        if len(self.cache) + len(words) > self.cache.most:
            self.cache.clear()
        ids = np.array(self.tokenizer.encode_batch_fast([" ".join(words)], add_special_tokens=False)[0].ids, "<u2")
        ends = (np.flatnonzero(self.ends[ids]) + 1) * 2
        raw, at = ids.tobytes(), 0
        if len(ends) != len(words):
            for w in words:
                self.cache[w] = self._made(w)
            return
        for w, end in zip(words, ends.tolist()):
            self.cache[w] = raw[at:end]
            at = end

    def _words(self, text: str) -> list[str] | None:
        """The words of a text; None where the classes of the pattern don't hold, before or after lower-casing."""
        low = text.lower()
        if _OUTSIDE.search(text) is not None or _OUTSIDE.search(low) is not None or any(a in text for a in self.added):
            return None
        return self.pattern.findall(low)

    def encode_batch(self, texts: list[str]) -> list[bytes]:
        """Ids of each text as little-endian unsigned 16-bit integers."""
        out: list = []
        for i in range(0, len(texts), 64):
            some = [self._words(t) for t in texts[i : i + 64]]
            if new := [w for w in set().union(*filter(None, some)) if w not in self.cache]:
                self._learn(new)
            get = self.cache.__getitem__
            out += [self._made(t) if words is None else b"".join(map(get, words)) for t, words in zip(texts[i : i + 64], some)]
        return out

    def encode(self, text: str) -> bytes:
        return self.encode_batch([text])[0]


_LOADED: dict = {}


def loaded(kind, path: str):
    """One codec of a kind and file for each worker process."""
    if (kind, path) not in _LOADED:
        _LOADED[kind, path] = kind(path)
    return _LOADED[kind, path]
