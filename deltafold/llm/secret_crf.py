"""Secret scans: fixed patterns, and a linear-chain conditional random field that adds to them.

Every text is cut into tokens (runs of word characters, and runs of other marks between them), and every token is
tagged secret begin, inside or outside from its shape, the words and marks around it and features of the file;
a begin with the insides that follow is a span of kind ``crf``.  Such spans stand beside the patterns' own.

The field is trained here, on windows of a bounded sample of documents.  The patterns' values are its first
examples; as it is to find what they miss, each is also shown with another word in place of the keyword, without
the quotes, and with random values of other alphabets and lengths, so that neither a keyword nor one kind of
value decides alone.

Decoding is exact: a token whose score for outside beats its other scores by more than all transitions can win
back is outside on the best path, so the path is found by Viterbi on the runs between such tokens.

Cases: a null or empty text has no spans; texts and tokens may have any length; rows that repeat are scanned as
often as they occur; without any pattern match in the sample the field adds nothing; an empty table gives an
empty result; other columns are ignored.
"""

from __future__ import annotations

import hashlib
import re
import string
from collections import Counter
from itertools import product

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from deltafold.llm import _common as C

# The base patterns and the least lengths of what they match.
ASSIGN = re.compile(r"""(password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", re.IGNORECASE | re.ASCII)
ACCESS = re.compile(r"AKIA[A-Z0-9]+")
HEX = re.compile(r"[0-9a-f]{24,}")
KINDS = ("assign", "access", "hex", "crf")

#: Documents that the field is trained on at most (about).
SAMPLE_DOCS = 5000
#: Pattern matches and other places that training windows are made around, at most.
SAMPLE_FOUND, SAMPLE_OTHER = 300, 1500
#: Tokens on either side of a window's middle.
REACH = 8
ROUNDS = 80
OUT, BEGIN, INSIDE = range(3)
_TAGS = 3


def base_spans(text: str) -> list[tuple[str, int, int]]:
    """Matches of the fixed patterns, leftmost and not overlapping within a kind."""
    out = [("assign", *m.span()) for m in ASSIGN.finditer(text) if m.end(2) - m.start(2) >= 6]
    out += [("access", *m.span()) for m in ACCESS.finditer(text) if m.end() - m.start() >= 20]
    out += [("hex", *m.span()) for m in HEX.finditer(text)]
    return sorted(out, key=lambda x: (x[1], KINDS.index(x[0])))


def secret_values(text: str) -> list[tuple[int, int]]:
    """The secrets themselves in the patterns' matches, as maximal ranges."""
    found = [m.span(2) for m in ASSIGN.finditer(text) if m.end(2) - m.start(2) >= 6]
    found += [(s, e) for kind, s, e in base_spans(text) if kind != "assign"]
    out: list[tuple[int, int]] = []
    for s, e in sorted(found):
        if out and s < out[-1][1]:
            out[-1] = (out[-1][0], max(e, out[-1][1]))
        else:
            out.append((s, e))
    return out


# ---------------------------------------------------------------- tokens and features

_KIND = np.full(256, 2, np.uint8)  # 0 white space, 1 word characters, 2 other marks
_KIND[[0x20, 0x09, 0x0A, 0x0B, 0x0C, 0x0D]] = 0
for _c in string.ascii_letters + string.digits + "+/_.-":
    _KIND[ord(_c)] = 1
_KIND[0x80:] = 1
_CODE = np.zeros(256, np.uint8)  # 1 digit, 2 upper, 4 lower, 8 sign in a word, 16 hexadecimal
for _set, _bit in ((string.digits, 1), (string.ascii_uppercase, 2), (string.ascii_lowercase, 4), ("+/_.-", 8), (string.hexdigits, 16)):
    for _c in _set:
        _CODE[ord(_c)] |= _bit
_LOWER = np.arange(256, dtype=np.uint8)
_LOWER[ord("A") : ord("Z") + 1] += 32
#: Lengths and shares at which the classes of a shape begin.
_SIZES = np.array([2, 4, 8, 12, 16, 20, 24, 32, 48, 64, 128])
_SHARES = np.array([1e-9, 0.1, 0.25, 0.5, 1.0])
_SHAPE = (3, len(_SIZES) + 1, len(_SHARES) + 1, len(_SHARES) + 1, 3, len(_SHARES) + 1, 2)
_WORDS = 1 << 14
_FILE = 24
#: Rows of the weight table: the shape as a whole and by part, hashed neighbours, file features.
_WIDTHS = (int(np.prod(_SHAPE)), *_SHAPE, _WORDS, _WORDS, _WORDS, _WORDS, _FILE, _FILE)
_BASES = np.r_[0, np.cumsum(_WIDTHS)]
_N_SHAPE = 1 + len(_SHAPE)


class Tokens:
    """Tokens of a slice of texts (bytes, where each text begins) with their features."""

    def __init__(self, raw: np.ndarray, begins: np.ndarray):
        kind = _KIND[raw]
        n, docs = len(raw), len(begins) - 1
        new = np.ones(n + 1, bool)
        new[1:n] = kind[1:] != kind[:-1]
        new[begins] = True
        self.starts = np.flatnonzero(new[:n] & (kind != 0)) if n else np.zeros(0, np.int64)
        edges = np.flatnonzero(new)
        self.ends = edges[np.searchsorted(edges, self.starts, "right")]
        self.doc = np.searchsorted(begins, self.starts, "right") - 1
        self.first = np.searchsorted(self.doc, np.arange(docs + 1))
        self.raw, self.kind = raw, kind[self.starts]
        self._describe(begins)

    def _count(self, flag: np.ndarray) -> np.ndarray:
        run = np.zeros(len(self.raw) + 1, np.int32)
        np.cumsum(flag, out=run[1:])
        return run[self.ends] - run[self.starts]

    def _describe(self, begins: np.ndarray) -> None:
        code, size = _CODE[self.raw], self.ends - self.starts
        digit, upper, sign, base16 = (self._count(code & b != 0) for b in (1, 2, 8, 16))
        group = code & 7
        turn = np.zeros(len(group), bool)
        turn[1:] = group[1:] != group[:-1]
        turns = self._count(turn)
        share = lambda x: np.searchsorted(_SHARES, x / np.maximum(size, 1), "right")
        parts = (self.kind.astype(np.int64), np.searchsorted(_SIZES, size, "right"), share(digit), share(upper), np.minimum(sign, 2), share(turns), (base16 == size).astype(np.int64))
        self.parts = np.stack(parts).astype(np.int32)
        self.shape = np.ravel_multi_index(parts, _SHAPE)
        h = C.word_hashes(_LOWER[self.raw], self.starts, self.ends)
        self.near = [self._hashed(h, *x) for x in self._places()]
        odd = (digit > 0) & (size >= 8)
        log = lambda x: np.minimum(np.log2(x + 1.0).astype(np.int64), _FILE - 1)
        length = np.diff(begins)
        self.file = log(length)[self.doc], log(1000.0 * np.bincount(self.doc[odd], minlength=len(length)) / (length + 1))[self.doc]

    def _places(self):
        """For each token: the word before, the word before that, the marks just before, the word after (-1: none)."""
        n = len(self.starts)
        word = self.kind == 1
        at = np.arange(n)
        before = np.r_[-1, np.maximum.accumulate(np.where(word, at, -1))[:-1]] if n else at
        after = np.r_[np.minimum.accumulate(np.where(word, at, n)[::-1])[::-1][1:], n] if n else at
        again = np.where(before >= 0, before[before], -1) if n else at
        mark = np.where((at > 0) & ~np.r_[True, word[:-1]], at - 1, -1) if n else at
        return [(before, 1), (again, 2), (mark, 3), (np.where(after < n, after, -1), 4)]

    def _hashed(self, h: np.ndarray, place: np.ndarray, seed: int) -> np.ndarray:
        ok = place >= 0
        ok[ok] &= self.doc[place[ok]] == self.doc[ok]
        out = np.zeros(len(place), np.int64)
        out[ok] = (C.mix(h[place[ok]], seed) % np.uint64(_WORDS - 1)).astype(np.int64) + 1
        return out

    def features(self, at: np.ndarray) -> np.ndarray:
        """Rows of the weight table for some tokens: tokens x features."""
        return np.stack([self.shape[at], *self.parts[:, at], *(x[at] for x in self.near), *(x[at] for x in self.file)], axis=1) + _BASES[:-1]


class Field:
    """A linear-chain conditional random field over outside, begin and inside, from outside to outside."""

    def __init__(self, weights: np.ndarray, step: np.ndarray):
        self.weights, self.step = weights.astype(np.float32).astype(float), step
        self.empty = not weights.any()
        grid = np.stack(np.unravel_index(np.arange(_WIDTHS[0]), _SHAPE))
        self.by_shape = self.weights[: _WIDTHS[0]] + sum(self.weights[_BASES[1 + i] + grid[i]] for i in range(len(_SHAPE)))
        # what any tag but outside can win by transitions, whatever stands on both sides
        ways = [step[p, y] + step[y, q] - step[p, OUT] - step[OUT, q] for p, y, q in product(range(_TAGS), (BEGIN, INSIDE), range(_TAGS))]
        self.most = max(ways)

    def scores(self, t: Tokens) -> np.ndarray:
        out = self.by_shape[t.shape]
        for i, x in enumerate((*t.near, *t.file)):
            out = out + self.weights[_BASES[_N_SHAPE + i] + x]
        return out

    def viterbi(self, score: np.ndarray) -> np.ndarray:
        """The best tags of one chain."""
        step, best, back = self.step, score[0] + self.step[OUT], np.zeros((len(score), _TAGS), np.int64)
        for n, x in enumerate(score[1:], 1):
            ways = best[:, None] + step
            back[n] = ways.argmax(axis=0)
            best = ways.max(axis=0) + x
        tags = np.zeros(len(score), np.int64)
        tags[-1] = (best + step[:, OUT]).argmax()
        for n in range(len(score) - 1, 0, -1):
            tags[n - 1] = back[n, tags[n]]
        return tags

    def decode(self, t: Tokens) -> np.ndarray:
        """The best tags of all tokens; every text is a chain."""
        tags = np.zeros(len(t.starts), np.int64)
        if self.empty or not len(tags):
            return tags
        score = self.scores(t)
        open_ = score[:, OUT] - score[:, 1:].max(axis=1) <= self.most
        head = np.zeros(len(tags), bool)
        head[t.first[:-1][t.first[:-1] < len(tags)]] = True
        head[1:] |= open_[1:] != open_[:-1]
        edges = np.r_[np.flatnonzero(head), len(tags)]
        runs = np.flatnonzero(open_[edges[:-1]])
        lone = runs[edges[runs + 1] - edges[runs] == 1]
        one = edges[lone]
        tags[one] = (score[one] + self.step[OUT] + self.step[:, OUT]).argmax(axis=1)
        for r in runs[edges[runs + 1] - edges[runs] > 1].tolist():
            tags[edges[r] : edges[r + 1]] = self.viterbi(score[edges[r] : edges[r + 1]])
        return tags

    @classmethod
    def fit(cls, feats: np.ndarray, tags: np.ndarray, rounds: int = ROUNDS, rate: float = 0.1, ridge: float = 2e-4) -> Field:
        """Maximum likelihood by full gradients (forward-backward over all windows at once, Adam steps).

        ``feats``: windows x tokens x features, -1 in all of a token that pads a short window; ``tags``: windows
        x tokens, outside for padding."""
        used, rows = np.unique(feats, return_inverse=True)
        rows = rows.reshape(feats.shape)
        pad = feats[:, :, 0] < 0
        w, step = np.zeros((len(used), _TAGS)), np.zeros((_TAGS, _TAGS))
        n, length = tags.shape
        one = np.eye(_TAGS)[tags]
        path = np.concatenate([np.zeros((n, 1), np.int64), tags, np.zeros((n, 1), np.int64)], axis=1)
        seen = np.zeros((_TAGS, _TAGS))
        np.add.at(seen, (path[:, :-1].ravel(), path[:, 1:].ravel()), 1)
        state = [np.zeros_like(w), np.zeros_like(w), np.zeros_like(step), np.zeros_like(step)]
        top = lambda x, axis: np.log(np.exp(x - (m := x.max(axis=axis, keepdims=True))).sum(axis=axis)) + m.squeeze(axis)
        for turn in range(1, rounds + 1):
            score = w[rows].sum(axis=2)
            score[pad] = (0.0, -1e6, -1e6)
            ahead, behind = np.zeros((length, n, _TAGS)), np.zeros((length, n, _TAGS))
            ahead[0], behind[-1] = score[:, 0] + step[OUT], step[:, OUT]
            for t in range(1, length):
                ahead[t] = top(ahead[t - 1][:, :, None] + step, 1) + score[:, t]
            for t in range(length - 2, -1, -1):
                behind[t] = top(step + (score[:, t + 1] + behind[t + 1])[:, None, :], 2)
            total = top(ahead[-1] + step[:, OUT], 1)
            mass = np.exp(ahead + behind - total[:, None]).transpose(1, 0, 2)
            error = one - mass
            error[pad] = 0
            flat = np.repeat(error.reshape(-1, _TAGS), feats.shape[2], axis=0)
            grad = np.stack([np.bincount(rows.ravel(), weights=flat[:, y], minlength=len(used)) for y in range(_TAGS)], axis=1)
            move = seen.copy()
            move[OUT] -= mass[:, 0].sum(axis=0)
            move[:, OUT] -= mass[:, -1].sum(axis=0)
            for t in range(1, length):
                move -= np.exp(ahead[t - 1][:, :, None] + step + (score[:, t] + behind[t])[:, None, :] - total[:, None, None]).sum(axis=0)
            for x, g, first, second in ((w, grad / n - ridge * w, 0, 1), (step, move / n - ridge * step, 2, 3)):
                state[first] = 0.9 * state[first] + 0.1 * g
                state[second] = 0.99 * state[second] + 0.01 * g**2
                x += rate * (state[first] / (1 - 0.9**turn)) / (np.sqrt(state[second] / (1 - 0.99**turn)) + 1e-8)
        weights = np.zeros((_BASES[-1], _TAGS))
        weights[used[used >= 0]] = w[used >= 0]
        return cls(weights, step)

    @classmethod
    def nothing(cls) -> Field:
        return cls(np.zeros((_BASES[-1], _TAGS)), np.zeros((_TAGS, _TAGS)))


# ---------------------------------------------------------------- training windows


def variants(text: str, s: int, e: int, rng: np.random.Generator) -> list[tuple[str, int, int]]:
    """Texts like the one with a secret at s..e: as it is; another keyword; no quotes; other values."""
    pick = lambda x: x[int(rng.integers(len(x)))]
    before, value, after = text[:s], text[s:e], text[e:]
    words = re.findall(r"\w+", before) or ["key"]
    key = list(re.finditer(r"\w+", before))[-1:]
    other = before if not key else before[: key[0].start()] + pick(["auth", "credential", "pass", "key", "private_key", "access", "bearer", *words[-20:]]) + before[key[0].end() :]
    bare = re.sub(r"[\"']$", "", before)
    letters = string.ascii_letters + string.digits
    alphabets = (string.hexdigits, letters, letters + "+/", letters + "_-", string.ascii_uppercase + string.digits)
    new = lambda: "".join(pick(x) for x in [pick(alphabets)] for _ in range(int(rng.integers(16, 64))))
    made = [(before, value, after), (other, value, after), (bare, value, re.sub(r"^[\"']", "", after)), (before, new(), after), (other, new(), after), (bare, new(), re.sub(r"^[\"']", "", after))]
    return [(b + v + a, len(b), len(b) + len(v)) for b, v, a in made]


def _cut_out(t: Tokens, tags: np.ndarray, middle: int, doc: int) -> tuple[np.ndarray, np.ndarray]:
    lo, hi = max(t.first[doc], middle - REACH), min(t.first[doc + 1], middle + REACH + 1)
    return np.arange(lo, hi), tags[lo:hi]


def tagged(texts: list[str], values: list[list[tuple[int, int]]]) -> tuple[Tokens, np.ndarray]:
    """Tokens of texts, and the tags that the values (ranges of code points) give them."""
    data = [x.encode("utf-8", "surrogatepass") for x in texts]
    begins = np.cumsum([0, *map(len, data)])
    t = Tokens(np.frombuffer(b"".join(data), np.uint8), begins)
    tags = np.zeros(len(t.starts), np.int64)
    for d, (text, mine) in enumerate(zip(texts, values, strict=True)):
        for s, e in mine:
            lo, hi = (begins[d] + len(text[:x].encode("utf-8", "surrogatepass")) for x in (s, e))
            which = np.flatnonzero((t.starts[t.first[d] : t.first[d + 1]] < hi) & (t.ends[t.first[d] : t.first[d + 1]] > lo)) + t.first[d]
            if len(which):
                tags[which] = INSIDE
                tags[which[0]] = BEGIN
    return t, tags


_WINDOW = "seed long, found boolean, feats array<array<int>>, tags array<int>"
_WINDOW_ARROW = pa.schema([("seed", pa.int64()), ("found", pa.bool_()), ("feats", pa.list_(pa.list_(pa.int32()))), ("tags", pa.list_(pa.int32()))])


def windows(text: str) -> list[tuple[int, bool, np.ndarray, np.ndarray]]:
    """Training windows of a text, each with a number that orders them at random but for all runs alike."""
    out, values = [], secret_values(text)
    seed = int.from_bytes(hashlib.blake2b(text.encode("utf-8", "surrogatepass"), digest_size=7).digest(), "little")
    rng = np.random.default_rng(seed)
    t, tags = tagged([text], [values])

    def put(t: Tokens, tags: np.ndarray, middle: int, doc: int, found: bool) -> None:
        at, mine = _cut_out(t, tags, middle, doc)
        edge = np.flatnonzero(mine)
        if found or not len(edge):
            out.append((int(rng.integers(1 << 62)), found, t.features(at), mine))

    for s, e in values:
        around = text[max(0, s - 300) : e + 300]
        made = variants(around, min(s, 300), min(s, 300) + e - s, rng)
        near = [[*((a, b) for a, b in secret_values(x) if b <= s2 or a >= e2), (s2, e2)] for x, s2, e2 in made]
        t2, tags2 = tagged([x for x, _, _ in made], near)
        for d in range(len(made)):
            mine = np.flatnonzero(tags2[t2.first[d] : t2.first[d + 1]] == BEGIN)
            for m in mine.tolist():
                put(t2, tags2, int(t2.first[d]) + m, d, True)
    odd = np.flatnonzero((tags == OUT) & (t.parts[2] > 0))
    plain = rng.integers(0, len(t.starts), 2) if len(t.starts) else []
    for m in [*(odd[rng.permutation(len(odd))[:4]].tolist()), *plain]:
        put(t, tags, int(m), 0, False)
    return out


def _training(batches):
    for batch in batches:
        rows = [x for text in batch["text"].to_pylist() for x in windows(text)]
        cols = [[r[0] for r in rows], [r[1] for r in rows], [r[2].tolist() for r in rows], [r[3].tolist() for r in rows]]
        yield pa.record_batch([pa.array(c, f.type) for c, f in zip(cols, _WINDOW_ARROW, strict=True)], schema=_WINDOW_ARROW)


def fit_windows(rows: list[tuple[np.ndarray, np.ndarray]]) -> Field:
    """A field of windows (features of each token, tags)."""
    if not any(x.any() for _, x in rows):
        return Field.nothing()
    length = max(len(x) for _, x in rows)
    feats = np.full((len(rows), length, len(_WIDTHS)), -1, np.int64)
    tags = np.zeros((len(rows), length), np.int64)
    for n, (f, x) in enumerate(rows):
        feats[n, : len(x)], tags[n, : len(x)] = f, x
    return Field.fit(feats, tags)


def train(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", sample_docs: int = SAMPLE_DOCS) -> Field:
    """The field of a bounded sample: documents whose id's hash falls in one of enough classes, and of their
    windows those with the smallest random numbers, ``SAMPLE_FOUND`` matches (six variants each) and
    ``SAMPLE_OTHER`` others at most."""
    classes = max(1, docs.count() // max(1, sample_docs))
    sample = docs.where(F.pmod(F.xxhash64(F.col(id_col).cast("long")), F.lit(classes)) == 0).select(F.coalesce(F.col(text_col).cast("string"), F.lit("")).alias("text"))
    rows = sample.mapInArrow(_training, _WINDOW)
    some = [r for found, most in ((True, 6 * SAMPLE_FOUND), (False, SAMPLE_OTHER)) for r in rows.where(F.col("found") == found).orderBy("seed").limit(most).collect()]
    return fit_windows([(np.array(r["feats"], np.int64), np.array(r["tags"], np.int64)) for r in some])


# ---------------------------------------------------------------- scanning


def crf_spans(texts: list[str], field: Field) -> list[list[tuple[str, int, int]]]:
    """Decoded spans of each text, in code points."""
    data = [x.encode("utf-8", "surrogatepass") for x in texts]
    begins = np.cumsum([0, *map(len, data)])
    out: list[list[tuple[str, int, int]]] = [[] for _ in texts]
    for i, j in C.slices(begins):
        raw = np.frombuffer(b"".join(data[i:j]), np.uint8)
        t = Tokens(raw, begins[i : j + 1] - begins[i])
        tags = field.decode(t)
        hit = np.flatnonzero(tags)
        if not len(hit):
            continue
        fresh = (tags[hit] == BEGIN) | np.r_[True, (hit[1:] != hit[:-1] + 1) | (t.doc[hit[1:]] != t.doc[hit[:-1]])]
        head = np.flatnonzero(fresh)
        last = np.r_[head[1:], len(hit)] - 1
        points = np.r_[0, np.cumsum((raw & 0xC0) != 0x80)]
        for a, b in zip(hit[head].tolist(), hit[last].tolist(), strict=True):
            d = int(t.doc[a])
            zero = points[begins[i + d] - begins[i]]
            out[i + d].append(("crf", int(points[t.starts[a]] - zero), int(points[t.ends[b]] - zero)))
    return out


def found_spans(texts: list[str], field: Field) -> list[tuple[list, list]]:
    """For each text the patterns' spans, and these with the field's, by start."""
    out = []
    for text, more in zip(texts, crf_spans(texts, field), strict=True):
        base = base_spans(text)
        out.append((base, sorted(base + more, key=lambda x: (x[1], KINDS.index(x[0])))))
    return out


_OUT = "doc_id long, n_assign long, n_access long, n_hex long, n_crf long, base_sha256 string, spans string, redacted string"
_OUT_ARROW = pa.schema([
    ("doc_id", pa.int64()), ("n_assign", pa.int64()), ("n_access", pa.int64()), ("n_hex", pa.int64()), ("n_crf", pa.int64()),
    ("base_sha256", pa.string()), ("spans", pa.string()), ("redacted", pa.string()),
])


def redact(text: str, spans: list[tuple[str, int, int]], mark: str = "[SECRET]") -> str:
    """The text with each range that spans cover, overlapping ones together, as one mark."""
    out, at = [], 0
    for _, s, e in sorted(spans, key=lambda x: (x[1], -x[2])):
        if e > at:
            if s >= at:
                out += [text[at:s], mark]
            at = e
    return "".join(out) + text[at:]


def _scan(field: Field, with_text: bool):
    def run(batches):
        for batch in batches:
            cols: list[list] = [[] for _ in _OUT_ARROW.names]
            texts = batch["text"].to_pylist()
            for key, text, (base, spans) in zip(batch["id"].to_pylist(), texts, found_spans(texts, field), strict=True):
                count = Counter(k for k, _, _ in spans)
                said = ",".join(f"{k}:{s}:{e}" for k, s, e in base)
                row = (key, *(count[k] for k in KINDS), hashlib.sha256(said.encode()).hexdigest(), ",".join(f"{k}:{s}:{e}" for k, s, e in spans), redact(text, spans) if with_text and spans else None)
                for to, x in zip(cols, row, strict=True):
                    to.append(x)
            yield pa.record_batch(dict(zip(_OUT_ARROW.names, cols, strict=True)), schema=_OUT_ARROW)

    return run


def secret_spans(docs: DataFrame, field: Field | None = None, id_col: str = "doc_id", text_col: str = "text", with_text: bool = True) -> DataFrame:
    """Spans of every text (kind:start:end in code points), their numbers, and the text without them where
    there are any."""
    field = train(docs, id_col, text_col) if field is None else field
    texts = docs.select(F.col(id_col).cast("long").alias("id"), F.coalesce(F.col(text_col).cast("string"), F.lit("")).alias("text"))
    return texts.mapInArrow(_scan(field, with_text), _OUT)


def _redact_texts(field: Field, column: int):
    def run(batches):
        for batch in batches:
            texts = batch.column(column).to_pylist()
            spans = found_spans([x or "" for x in texts], field)
            out = [x and redact(x, found) for x, (_, found) in zip(texts, spans, strict=True)]
            yield batch.set_column(column, batch.schema.field(column), pa.array(out, batch.schema.field(column).type))

    return run


def redacted_documents(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """All rows of ``docs`` with secrets in their texts replaced; a column ``n_chars`` follows the text."""
    out = docs.mapInArrow(_redact_texts(train(docs, id_col, text_col), docs.columns.index(text_col)), docs.schema)
    return out.withColumn("n_chars", F.length(text_col).cast(docs.schema["n_chars"].dataType)) if "n_chars" in docs.columns else out


def op8_secret_scan(spark, sf_dir: str) -> DataFrame:
    """The secret-scan contract on ``documents``."""
    out = secret_spans(spark.read.parquet(f"{sf_dir}/documents.parquet"), with_text=False)
    return out.select("doc_id", "n_assign", "n_access", "n_hex", "base_sha256", "spans", "n_crf")
