"""Substring dedup on words by de Bruijn compaction.

Every run of ``k`` consecutive words of a document is an edge, from its first to its last k-1 words.  Edges
that occur once drop out; of the rest, nonbranching paths are compacted, and their source coordinates
(document, first word, number of words) lead back to the text, where every path is verified.

Steps, all joined through Spark shuffles on chunk, bucket or path (see ``_common``):

1. *edges*: each chunk packs the fingerprints of its distinct edges (44 bits and the bucket's) with counts.
2. *degree*: a bucket answers which edges occur again anywhere, the same document included.
3. *branches*: a chunk sends the edges that do under a second fingerprint, with marks of the words before and
   after; a bucket answers whether the edge is still repeated and whether its paths branch there.
4. *compact*: in each document, repeated edges that follow each other without a branch are one path.  All
   copies of a path have the same extent.
5. *verify*: the words at a path's coordinates are digested (128 bits), and paths are joined on (path, length,
   digest): copies that agree are equal texts.  A path without an equal copy would owe its place to a
   collision of fingerprints or marks; then all repeated edges are digested one by one and those without an
   equal edge are put back.  So a word goes only where its source text was found again.

Cases: a null or empty text has no words and no paths; a text of fewer than ``k`` words has no edges; rows
that repeat a document count as other places, so their words go as well; a null id stays null; an empty table
gives an empty result; other columns of the input are ignored.  Windows are judged on the input, not on what is
left.
"""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from deltafold.llm import _common as C
from deltafold.session import cut

U64 = np.uint64
WINDOW = 35
#: Marks have 48 bits; 0 is the end of a document.
_BRANCH = (1 << 48) - 1
#: Kinds of rows for a chunk that come from no bucket: its own flags of step 2, and edges that step 5 put back.
_MEMO, _BACK = -1, -(1 << 31)
_CHECK = np.dtype([("n", "u1"), ("pre", "<u2"), ("pre_high", "<u4"), ("post", "<u2"), ("post_high", "<u4")])


def _edges(raw: np.ndarray, offsets: np.ndarray, k: int):
    """For slices of documents: (first doc, last doc, word starts, ends, document of each word, word hashes)."""
    for i, j in C.slices(offsets):
        lo, hi = offsets[i], offsets[j]
        begins = offsets[i : j + 1] - lo
        part = raw[lo:hi]
        s, e = C.word_bounds(part, begins[:-1])
        doc = np.searchsorted(begins, s, "right") - 1
        yield i, j, part, s, e, doc, C.word_hashes(part, s, e)


def _whole(doc: np.ndarray, k: int) -> np.ndarray:
    """First words of the windows that stay in one document."""
    return np.flatnonzero(doc[: len(doc) - k + 1] == doc[k - 1 :]) if len(doc) >= k else np.zeros(0, np.int64)


def _first(words: np.ndarray, at: np.ndarray, k: int) -> np.ndarray:
    return C.window_hashes(words, k, 1)[at]


def _second(words: np.ndarray, at: np.ndarray, k: int) -> np.ndarray:
    return C.window_hashes(C.mix(words, 7), k, 2)[at]


def _marks(words: np.ndarray, doc: np.ndarray, at: np.ndarray, shift: int) -> np.ndarray:
    """A mark of the word ``shift`` places from each window's first; 0 where the document has none there."""
    to = at + shift
    ok = (to >= 0) & (to < len(words))
    ok[ok] &= doc[to[ok]] == doc[at[ok]]
    out = np.zeros(len(at), U64)
    out[ok] = (words[to[ok]] >> U64(16)) % U64(_BRANCH - 1) + U64(1)
    return out


def _all_edges(table: pa.Table, lay: C.Layout, k: int) -> np.ndarray:
    raw, offsets = C.text_buffers(table["text"])
    got = [C.place(_first(w, _whole(doc, k), k), lay.buckets) for *_, doc, w in _edges(raw, offsets, k)]
    return np.concatenate(got) if got else np.zeros(0, U64)


def _send_edges(lay: C.Layout, k: int):
    def run(table: pa.Table) -> pa.Table:
        u, n = np.unique(_all_edges(table, lay, k), return_counts=True)
        return C.packed_rows(table["chunk"][0].as_py(), u, C.count_bytes(n))

    return run


def _repeated(texts: pa.Table, answers: pa.Table, lay: C.Layout, k: int) -> np.ndarray:
    """One flag for each edge of the chunk, in document order."""
    u, back = np.unique(_all_edges(texts, lay, k), return_inverse=True)
    return C.replies(answers)[back] > 0


def _meet(values: np.ndarray, sizes: list[int]) -> np.ndarray:
    """For marks sorted by group (sizes): the mark all share, or the branch mark."""
    begin = np.r_[0, np.cumsum(sizes)[:-1]]
    low, high = np.minimum.reduceat(values, begin), np.maximum.reduceat(values, begin)
    return np.where(low == high, low, U64(_BRANCH))


def _put(extra: np.ndarray, name: str, marks: np.ndarray) -> None:
    extra[name], extra[f"{name}_high"] = marks & U64(0xFFFF), marks >> U64(16)


def _got(extra: np.ndarray, name: str) -> np.ndarray:
    return extra[name].astype(U64) | extra[f"{name}_high"].astype(U64) << U64(16)


def _send_checks(lay: C.Layout, k: int):
    def run(texts: pa.Table, answers: pa.Table) -> pa.Table:
        if texts.num_rows == 0:
            return C.PACKED_ARROW.empty_table()
        texts = C.ordered(texts)
        chunk = texts["chunk"][0].as_py()
        again = _repeated(texts, answers, lay, k)
        raw, offsets = C.text_buffers(texts["text"])
        done, keys, before, after = 0, [], [], []
        for *_, doc, words in _edges(raw, offsets, k):
            at = _whole(doc, k)
            mine = again[done : done + len(at)]
            done += len(at)
            if not mine.any():
                continue
            at = at[mine]
            keys.append(C.place(_second(words, at, k), lay.buckets))
            before.append(_marks(words, doc, at, -1))
            after.append(_marks(words, doc, at, k))
        memo = pa.table({"bucket": [_MEMO - chunk], "chunk": [chunk], "width": [0], "vals": [np.packbits(again).tobytes()], "extra": [b""]}, schema=C.PACKED_ARROW)
        if not keys:
            return memo
        key, pre, post = (np.concatenate(x) for x in (keys, before, after))
        order = np.argsort(key, kind="stable")
        u, sizes = np.unique(key, return_counts=True)
        extra = np.zeros(len(u), _CHECK)
        extra["n"] = C.count_bytes(sizes)
        _put(extra, "pre", _meet(pre[order], sizes))
        _put(extra, "post", _meet(post[order], sizes))
        return pa.concat_tables([memo, C.packed_rows(chunk, u, extra)])

    return run


def _confirm(table: pa.Table) -> pa.Table:
    """A bucket's answers: 1 repeated, 2 a path ends after the edge, 4 a path begins with it."""
    bucket = table["bucket"][0].as_py()
    chunks = table["chunk"].to_pylist()
    if bucket <= _MEMO:
        return pa.table({"chunk": chunks, "bucket": [_MEMO] * len(chunks), "reply": table["vals"].to_pylist()}, schema=C.ANSWER_ARROW)
    parts = [C.unpack(w, v) for w, v in zip(table["width"].to_pylist(), table["vals"].to_pylist(), strict=True)]
    extra = np.concatenate([np.frombuffer(x, _CHECK) for x in table["extra"].to_pylist()])
    values = np.concatenate(parts)
    order = np.argsort(values, kind="stable")
    _, group, sizes = np.unique(values, return_inverse=True, return_counts=True)
    total = np.bincount(group, weights=extra["n"].astype(float))
    bits = (total > 1.5) * 1 + (_meet(_got(extra, "post")[order], sizes) == U64(_BRANCH)) * 2 + (_meet(_got(extra, "pre")[order], sizes) == U64(_BRANCH)) * 4
    reply = bits.astype(np.uint8)[group]
    cuts = np.cumsum([0, *map(len, parts)])
    return pa.table({"chunk": chunks, "bucket": [bucket] * len(chunks), "reply": [reply[i:j].tobytes() for i, j in zip(cuts[:-1], cuts[1:], strict=True)]}, schema=C.ANSWER_ARROW)


_OUT = pa.schema([
    ("doc_id", pa.int64()), ("n_words", pa.int64()), ("n_removed", pa.int64()), ("kept_text", pa.string()), ("kept_sha256", pa.string()),
    ("path_starts", pa.list_(pa.int64())), ("path_words", pa.list_(pa.int64())), ("path_ids", pa.list_(pa.int64())), ("path_digests", pa.list_(pa.binary())),
])
_OUT_DDL = "doc_id long, n_words long, n_removed long, kept_text string, kept_sha256 string, path_starts array<long>, path_words array<long>, path_ids array<long>, path_digests array<binary>"


def _digest(data: bytes, starts: np.ndarray, ends: np.ndarray) -> bytes:
    """Of the words at some places of a text, as they stand."""
    return hashlib.blake2b(b" ".join([data[x:y] for x, y in zip(starts.tolist(), ends.tolist(), strict=True)]), digest_size=16).digest()


def _repeated_edges(texts: pa.Table, answers: pa.Table, lay: C.Layout, k: int):
    """For slices of a chunk's documents: (first doc, last doc, bytes, word starts, ends, document of each word,
    first words of the repeated edges, their second fingerprints, branch bits, places among the chunk's)."""
    memo = answers.filter(pa.compute.equal(answers["bucket"], _MEMO))["reply"].to_pylist()
    back_rows = answers.filter(pa.compute.equal(answers["bucket"], _BACK))["reply"].to_pylist()
    reply = C.replies(answers.filter(pa.compute.greater_equal(answers["bucket"], 0)))
    again = np.unpackbits(np.frombuffer(memo[0], np.uint8)).astype(bool) if memo else np.zeros(0, bool)
    raw, offsets = C.text_buffers(texts["text"])
    # the order of the chunk's distinct second fingerprints gives each edge its answer
    done, keys, kept = 0, [], []
    for i, j, part, s, e, doc, words in _edges(raw, offsets, k):
        at = _whole(doc, k)
        mine = again[done : done + len(at)]
        done += len(at)
        at = at[mine]
        keys.append(C.place(_second(words, at, k), lay.buckets) if len(at) else np.zeros(0, U64))
        kept.append((i, j, part, s, e, doc, at))
    key = np.concatenate(keys) if keys else np.zeros(0, U64)
    _, back = np.unique(key, return_inverse=True)
    bits = reply[back] if len(key) else np.zeros(0, np.uint8)
    sure = (bits & 1) > 0
    if back_rows:
        sure[np.concatenate([np.frombuffer(x, "<i8") for x in back_rows])] = False
    done = 0
    for i, j, part, s, e, doc, at in kept:
        mine = np.flatnonzero(sure[done : done + len(at)])
        yield i, j, part, s, e, doc, at[mine], key[done + mine], bits[done + mine], done + mine
        done += len(at)


def _compact(lay: C.Layout, k: int, with_text: bool):
    def run(texts: pa.Table, answers: pa.Table) -> pa.Table:
        if texts.num_rows == 0:
            return _OUT.empty_table()
        texts = C.ordered(texts)
        ids = texts["id"].to_pylist()
        cols: list[list] = [[] for _ in _OUT.names]
        for i, j, part, s, e, doc, at, key, b, _ in _repeated_edges(texts, answers, lay, k):
            path = key.view(np.int64)
            gone = C.covered(len(s), at, k)
            begins = np.ones(len(at), bool)
            begins[1:] = (at[1:] != at[:-1] + 1) | (doc[at[1:]] != doc[at[:-1]]) | ((b[1:] & 4) > 0) | ((b[:-1] & 2) > 0)
            head = np.flatnonzero(begins)
            length = np.diff(np.r_[head, len(at)]) + k - 1
            first_word = np.searchsorted(doc, np.arange(j - i + 1))
            first_path = np.searchsorted(doc[at[head]], np.arange(j - i + 1)) if len(head) else np.zeros(j - i + 1, int)
            data = part.tobytes()
            for d in range(j - i):
                w0, w1 = first_word[d], first_word[d + 1]
                left = np.flatnonzero(~gone[w0:w1]) + w0
                text = b" ".join([data[x:y] for x, y in zip(s[left].tolist(), e[left].tolist(), strict=True)])
                p = slice(first_path[d], first_path[d + 1])
                digests = [_digest(data, s[x : x + n], e[x : x + n]) for x, n in zip(at[head[p]].tolist(), length[p].tolist(), strict=True)]
                row = (ids[i + d], w1 - w0, w1 - w0 - len(left), text.decode() if with_text else None, hashlib.sha256(text).hexdigest(), at[head[p]] - w0, length[p], path[head[p]], digests)
                for to, x in zip(cols, row, strict=True):
                    to.append(x)
        return pa.table(dict(zip(_OUT.names, cols, strict=True)), schema=_OUT)

    return run


_EDGE_ARROW = pa.schema([("chunk", pa.int32()), ("place", pa.int64()), ("key", pa.int64()), ("digest", pa.binary())])


def _digested(lay: C.Layout, k: int):
    """Every repeated edge of a chunk by itself, with the digest of its words."""

    def run(texts: pa.Table, answers: pa.Table) -> pa.Table:
        if texts.num_rows == 0:
            return _EDGE_ARROW.empty_table()
        texts = C.ordered(texts)
        chunk, cols = texts["chunk"][0].as_py(), [[], [], [], []]
        for _, _, part, s, e, _, at, key, _, place in _repeated_edges(texts, answers, lay, k):
            data = part.tobytes()
            row = ([chunk] * len(at), place.tolist(), key.view(np.int64).tolist(), [_digest(data, s[x : x + k], e[x : x + k]) for x in at.tolist()])
            for to, x in zip(cols, row, strict=True):
                to += x
        return pa.table(dict(zip(_EDGE_ARROW.names, cols, strict=True)), schema=_EDGE_ARROW)

    return run


def _put_back(table: pa.Table) -> pa.Table:
    places = np.sort(table["place"].to_numpy()).astype("<i8")
    return pa.table({"chunk": [table["chunk"][0].as_py()], "bucket": [_BACK], "reply": [places.tobytes()]}, schema=C.ANSWER_ARROW)


def repeated_word_spans(docs: DataFrame, k: int = WINDOW, id_col: str = "doc_id", text_col: str = "text", with_text: bool = True) -> DataFrame:
    """For each document: its words, those that lie in a repeated window of ``k`` words, what is left (text and
    SHA-256 of its UTF-8 form), and the compacted paths (first word, number of words, id shared by all copies,
    digest of the words)."""
    lay = C.layout_for(docs, text_col)
    texts = C.by_chunk(docs, lay, id_col, text_col)
    edges = texts.groupBy("chunk").applyInArrow(_send_edges(lay, k), C.PACKED)
    degree = C.exchange(edges, lay).groupBy("bucket").applyInArrow(C.tally, C.ANSWER)
    checks = texts.groupBy("chunk").cogroup(C.exchange(degree, lay, "chunk").groupBy("chunk")).applyInArrow(_send_checks(lay, k), C.PACKED)
    sure = C.exchange(checks, lay).groupBy("bucket").applyInArrow(_confirm, C.ANSWER)
    held = texts.groupBy("chunk")
    found = cut(held.cogroup(C.exchange(sure, lay, "chunk").groupBy("chunk")).applyInArrow(_compact(lay, k, with_text), _OUT_DDL))
    paths = found.select(F.explode(F.arrays_zip("path_ids", "path_words", "path_digests")).alias("p")).select("p.*")
    alone = paths.groupBy("path_ids", "path_words", "path_digests").agg(F.count("*").alias("copies")).where("copies = 1")
    if alone.isEmpty():
        return found
    single = held.cogroup(C.exchange(sure, lay, "chunk").groupBy("chunk")).applyInArrow(_digested(lay, k), "chunk int, place long, key long, digest binary")
    refuted = single.groupBy("key", "digest").agg(F.count("*").alias("copies"), F.first("chunk").alias("chunk"), F.first("place").alias("place")).where("copies = 1")
    back = refuted.groupBy("chunk").applyInArrow(_put_back, C.ANSWER)
    return held.cogroup(C.exchange(sure.unionByName(back), lay, "chunk").groupBy("chunk")).applyInArrow(_compact(lay, k, with_text), _OUT_DDL)


def op2_substring_dedup(spark, sf_dir: str) -> DataFrame:
    """The repeated-window contract on ``documents``."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    return repeated_word_spans(docs, with_text=False).select("doc_id", "n_words", "n_removed", "kept_sha256", F.size("path_starts").cast("long").alias("n_paths"))
