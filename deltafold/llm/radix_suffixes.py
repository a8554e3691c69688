"""Repeated byte strings by a depth-limited radix sort of suffixes.

Suffixes are ordered on their first ``k`` bytes only; those that are equal to that depth are exactly the
repeated strings of ``k`` bytes.  A byte goes if it lies in such a string that also starts in a document with
a smaller id.

Most suffixes repeat nowhere, so they are dealt out by a digit that few of them need: the *anchor* of a
string is the leftmost of its grams of ``k // 2 - 1`` bytes with the smallest hash.  Equal strings have equal
anchors at equal distances, and neighbouring strings mostly share one, so about one suffix in 14 is sent.

1. *first digit*: chunks pack their anchors' fingerprints; buckets answer which occur again.
2. *deal*: for each anchor that does, a chunk sends the bytes around it with the range of strings it stands
   for and the smallest document that holds it (copies within a chunk are merged before they travel).
3. *passes*: a bucket orders the strings at each distance from the anchor by most significant digits of
   eight bytes.  After every pass groups of one drop out, groups equal in all remaining bytes are done, and
   only mixed groups go on to the next digit.  Bytes are compared, never hashes, so nothing is removed by
   chance.
4. *mark*: chunks turn the answers into removed ranges.

Cases: a null or empty text has no bytes; texts shorter than ``k`` keep all; of rows with equal ids none is
smaller than the other, so they do not remove each other; a null id counts as larger than all others; an
empty table gives an empty result; other columns are ignored.
"""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame

from deltafold.llm import _common as C

U64 = np.uint64
DEPTH = 50
_MEMO = -1
_LAST = np.iinfo(np.int64).max
_ENTRY = np.dtype([("low", "u1"), ("high", "u1"), ("doc", "<i8")])
_RUN = np.dtype([("entry", "<u4"), ("low", "u1"), ("high", "u1"), ("doc", "<i8")])


def _shape(k: int) -> tuple[int, int]:
    """Bytes in a gram, and grams in a string of k bytes."""
    gram = max(1, min(k, k // 2 - 1))
    if k - gram + 1 > 255:
        gram = k - 254
    return gram, k - gram + 1


def _sliding_min(x: np.ndarray, w: int) -> np.ndarray:
    size = 1
    while 2 * size <= w:
        x = np.minimum(x[: len(x) - size], x[size:])
        size *= 2
    rest = w - size
    return np.minimum(x[: len(x) - rest], x[rest:]) if rest else x


def _anchors(part: np.ndarray, begins: np.ndarray, k: int, buckets: int):
    """(anchor, first string, last string, placed fingerprint, document) for each group of strings of a slice."""
    gram, w = _shape(k)
    if len(part) < k:
        return (np.zeros(0, np.int64),) * 3 + (np.zeros(0, U64), np.zeros(0, np.int64))
    g = C.mix(C.rolling(part.astype(U64) + U64(1), gram, 0xA0761D6478BD642F))
    least = _sliding_min((g & U64(0xFFFFFFFF00000000)) | np.arange(len(g), dtype=U64), w)
    doc = np.repeat(np.arange(len(begins) - 1, dtype=np.int32), np.diff(begins))
    starts = np.flatnonzero(doc[: len(part) - k + 1] == doc[k - 1 :])
    at = (least[starts] & U64(0xFFFFFFFF)).astype(np.int64)
    if len(at) == 0:
        return (np.zeros(0, np.int64),) * 3 + (np.zeros(0, U64), np.zeros(0, np.int64))
    head = np.flatnonzero(np.r_[True, at[1:] != at[:-1]])
    tail = np.r_[head[1:], len(at)] - 1
    a = at[head]
    return a, starts[head], starts[tail], C.place(C.mix(g[a], 3), buckets), doc[a].astype(np.int64)


def _parts(table: pa.Table, lay: C.Layout, k: int):
    raw, offsets = C.text_buffers(table["text"])
    for i, j in C.slices(offsets, 1 << 19):
        part, begins = raw[offsets[i] : offsets[j]], offsets[i : j + 1] - offsets[i]
        yield i, j, part, begins, _anchors(part, begins, k, lay.buckets)


def _send_anchors(lay: C.Layout, k: int):
    def run(table: pa.Table) -> pa.Table:
        got = [x[3] for *_, x in _parts(table, lay, k)]
        u, n = np.unique(np.concatenate(got), return_counts=True) if got else (np.zeros(0, U64), np.zeros(0, int))
        return C.packed_rows(table["chunk"][0].as_py(), u, C.count_bytes(n))

    return run


def _ids(table: pa.Table) -> np.ndarray:
    return pc.fill_null(table["id"], _LAST).to_numpy()


def _around(part: np.ndarray, a: np.ndarray, first: np.ndarray, last: np.ndarray, k: int) -> np.ndarray:
    """The bytes of all strings of each group, at fixed distances from its anchor, zero outside them."""
    _, w = _shape(k)
    width = w - 1 + k
    padded = np.r_[np.zeros(w - 1, np.uint8), part, np.zeros(k, np.uint8)]
    rows = np.lib.stride_tricks.sliding_window_view(padded, width)[a]
    columns = np.arange(width)
    rows = rows * ((columns >= (first - a + w - 1)[:, None]) & (columns < (last - a + w - 1 + k)[:, None]))
    return rows


def _entries(table: pa.Table, lay: C.Layout, k: int, again: np.ndarray):
    """Merged groups of a chunk in the order they are sent, and each group's place among them."""
    _, w = _shape(k)
    width = w - 1 + k
    ids = _ids(table)
    done, got = 0, []
    for i, _, part, begins, (a, first, last, placed, doc) in _parts(table, lay, k):
        mine = np.flatnonzero(again[done : done + len(a)])
        done += len(a)
        if len(mine):
            a, first, last = a[mine], first[mine], last[mine]
            got.append((_around(part, a, first, last, k), first - a + w - 1, last - a + w - 1, placed[mine], doc[mine] + i, begins[doc[mine]], a))
    if not got:
        return None
    rows, low, high, placed, doc, base, a = (np.concatenate(x) for x in zip(*got, strict=True))
    wide = np.zeros((len(rows), -(-width // 8) * 8), np.uint8)
    wide[:, :width] = rows
    wide = wide.view(U64)
    with np.errstate(over="ignore"):
        look = np.full(len(rows), 1, U64)
        for c in range(wide.shape[1]):
            look = (look ^ wide[:, c]) * U64(0x9FB21C651E98DF25)
            look ^= look >> U64(29)
    order = np.lexsort((high, low, look, placed))
    same = (placed[order][1:] == placed[order][:-1]) & (low[order][1:] == low[order][:-1]) & (high[order][1:] == high[order][:-1])
    same[same] = (wide[order[1:][same]] == wide[order[:-1][same]]).all(axis=1)
    head = np.flatnonzero(np.r_[True, ~same])
    place = np.empty(len(rows), np.int64)
    place[order] = np.cumsum(np.r_[True, ~same]) - 1
    info = np.zeros(len(head), _ENTRY)
    info["low"], info["high"], info["doc"] = low[order[head]], high[order[head]], np.minimum.reduceat(ids[doc][order], head)
    return rows[order[head]], info, placed[order[head]], (place, doc, a - base, order)


def _send_contexts(lay: C.Layout, k: int):
    def run(texts: pa.Table, answers: pa.Table) -> pa.Table:
        if texts.num_rows == 0:
            return C.PACKED_ARROW.empty_table()
        texts = C.ordered(texts)
        chunk = texts["chunk"][0].as_py()
        got = [x[3] for *_, x in _parts(texts, lay, k)]
        _, back = np.unique(np.concatenate(got) if got else np.zeros(0, U64), return_inverse=True)
        again = C.replies(answers)[back] > 0
        cols: list[list] = [[_MEMO - chunk], [chunk], [0], [np.packbits(again).tobytes()], [b""]]
        if (found := _entries(texts, lay, k, again)) is not None:
            rows, info, placed, _ = found
            for b, i, j in zip(*(x.tolist() for x in C.bucket_ranges(placed)), strict=True):
                for to, x in zip(cols, (b, chunk, j - i, rows[i:j].tobytes(), info[i:j].tobytes()), strict=True):
                    to.append(x)
        return pa.table(dict(zip(C.PACKED_ARROW.names, cols, strict=True)), schema=C.PACKED_ARROW)

    return run


def radix_groups(strings: np.ndarray) -> np.ndarray:
    """A label for each row of bytes that equals another row, the same for equal rows; -1 for all others.

    Most significant digits first, eight bytes to a digit; see the module's third step."""
    n, k = strings.shape
    if n == 0:
        return np.zeros(0, np.int64)
    wide = np.zeros((n, -(-k // 8) * 8), np.uint8)
    wide[:, :k] = strings
    digits = wide.view(">u8").astype(U64)
    label, fresh = np.full(n, -1, np.int64), 0
    rows, group = np.arange(n), np.zeros(n, np.int64)
    for d in range(digits.shape[1]):
        key = digits[rows, d]
        order = np.argsort(key, kind="stable") if d == 0 else np.lexsort((key, group))
        rows, key, group = rows[order], key[order], group[order]
        new = np.r_[True, (key[1:] != key[:-1]) | (group[1:] != group[:-1])]
        group = np.cumsum(new) - 1
        keep = np.bincount(group)[group] > 1
        rows, group = rows[keep], group[keep]
        if len(rows) == 0:
            break
        head = np.flatnonzero(np.r_[True, group[1:] != group[:-1]])
        sizes = np.diff(np.r_[head, len(rows)])
        group = np.repeat(np.arange(len(head)), sizes)
        rest = digits[rows, d + 1 :]
        done = np.logical_and.reduceat((rest == np.repeat(rest[head], sizes, axis=0)).all(axis=1), head) if rest.shape[1] else np.ones(len(head), bool)
        settled = done[group]
        label[rows[settled]] = fresh + group[settled]
        fresh += len(head)
        rows, group = rows[~settled], group[~settled]
        if len(rows) == 0:
            break
    return label


def _passes(k: int):
    _, w = _shape(k)
    width = w - 1 + k

    def run(table: pa.Table) -> pa.Table:
        bucket, chunks = table["bucket"][0].as_py(), table["chunk"].to_pylist()
        if bucket <= _MEMO:
            return pa.table({"chunk": chunks, "bucket": [_MEMO] * len(chunks), "reply": table["vals"].to_pylist()}, schema=C.ANSWER_ARROW)
        sizes = table["width"].to_pylist()
        rows = np.concatenate([np.frombuffer(x, np.uint8) for x in table["vals"].to_pylist()]).reshape(-1, width)
        info = np.concatenate([np.frombuffer(x, _ENTRY) for x in table["extra"].to_pylist()])
        runs = []
        open_doc, open_from = np.full(len(rows), _LAST), np.zeros(len(rows), np.uint8)

        def close(which: np.ndarray, at: int) -> None:
            which = which[open_doc[which] < info["doc"][which]]
            run = np.zeros(len(which), _RUN)
            run["entry"], run["low"], run["high"], run["doc"] = which, open_from[which], max(at - 1, 0), open_doc[which]
            runs.append(run)

        for j in range(w + 1):
            least = np.full(len(rows), _LAST)
            if j < w:
                here = np.flatnonzero((info["low"] <= j) & (info["high"] >= j))
                label = radix_groups(rows[here, j : j + k])
                here, label = here[label >= 0], label[label >= 0]
                if len(here):
                    order = np.argsort(label, kind="stable")
                    here, label = here[order], label[order]
                    head = np.flatnonzero(np.r_[True, label[1:] != label[:-1]])
                    least[here] = np.repeat(np.minimum.reduceat(info["doc"][here], head), np.diff(np.r_[head, len(here)]))
            changed = np.flatnonzero(least != open_doc)
            close(changed, j)
            open_doc[changed], open_from[changed] = least[changed], j
        all_runs = np.concatenate(runs)
        cuts = np.cumsum([0, *sizes])
        all_runs = all_runs[np.argsort(all_runs["entry"], kind="stable")]
        where = np.searchsorted(all_runs["entry"], cuts)
        reply = []
        for c, (i, j) in enumerate(zip(where[:-1], where[1:], strict=True)):
            mine = all_runs[i:j].copy()
            mine["entry"] -= U64(cuts[c]).astype(np.uint32)
            reply.append(mine.tobytes())
        return pa.table({"chunk": chunks, "bucket": [bucket] * len(chunks), "reply": reply}, schema=C.ANSWER_ARROW)

    return run


_OUT = pa.schema([
    ("doc_id", pa.int64()), ("n_bytes", pa.int64()), ("n_removed", pa.int64()), ("n_spans", pa.int64()), ("kept_bytes", pa.binary()), ("kept_sha256", pa.string()),
    ("span_starts", pa.list_(pa.int64())), ("span_ends", pa.list_(pa.int64())),
])
_OUT_DDL = "doc_id long, n_bytes long, n_removed long, n_spans long, kept_bytes binary, kept_sha256 string, span_starts array<long>, span_ends array<long>"


def _removed_ranges(texts: pa.Table, answers: pa.Table, lay: C.Layout, k: int):
    """(document of the chunk, first byte, end) of every removed range, overlapping ones too."""
    _, w = _shape(k)
    none = (np.zeros(0, np.int64),) * 3
    memo = answers.filter(pc.equal(answers["bucket"], _MEMO))["reply"].to_pylist()
    if not memo:
        return none
    again = np.unpackbits(np.frombuffer(memo[0], np.uint8)).astype(bool)
    if not again.any() or (found := _entries(texts, lay, k, again)) is None:
        return none
    _, info, placed, (place, doc, at, order) = found
    blobs = dict(zip(answers["bucket"].to_pylist(), answers["reply"].to_pylist(), strict=True))
    runs = []
    for b, i, _ in zip(*(x.tolist() for x in C.bucket_ranges(placed)), strict=True):
        run = np.frombuffer(blobs[b], _RUN).copy()
        run["entry"] += np.uint32(i)
        runs.append(run)
    own = np.zeros(len(info), _RUN)  # within the chunk: all but the smallest document lose what they share
    own["entry"], own["low"], own["high"], own["doc"] = np.arange(len(info)), info["low"], info["high"], info["doc"]
    run = np.concatenate([own, *runs])
    group_start = np.searchsorted(place[order], np.arange(len(info) + 1))
    count = np.diff(group_start)[run["entry"]]
    which = np.repeat(np.arange(len(run)), count)
    nth = np.arange(len(which)) - np.repeat(np.cumsum(count) - count, count)
    occ = order[group_start[run["entry"][which]] + nth]
    later = _ids(texts)[doc[occ]] > run["doc"][which]
    occ, which = occ[later], which[later]
    first = at[occ] - (w - 1) + run["low"][which].astype(np.int64)
    return doc[occ], first, first + k + (run["high"][which].astype(np.int64) - run["low"][which])


def _mark(lay: C.Layout, k: int, with_text: bool):
    def run(texts: pa.Table, answers: pa.Table) -> pa.Table:
        if texts.num_rows == 0:
            return _OUT.empty_table()
        texts = C.ordered(texts)
        doc, first, end = _removed_ranges(texts, answers, lay, k)
        order = np.argsort(doc, kind="stable")
        doc, first, end = doc[order], first[order], end[order]
        where = np.searchsorted(doc, np.arange(texts.num_rows + 1))
        raw, offsets = C.text_buffers(texts["text"])
        cols: list[list] = [[] for _ in _OUT.names]
        for d, name in enumerate(texts["id"].to_pylist()):
            part = raw[offsets[d] : offsets[d + 1]]
            starts = ends = np.zeros(0, np.int64)
            kept = part.tobytes()
            gone = 0
            if where[d] < where[d + 1]:
                step = np.zeros(len(part) + 1, np.int32)
                np.add.at(step, first[where[d] : where[d + 1]], 1)
                np.add.at(step, end[where[d] : where[d + 1]], -1)
                mask = np.cumsum(step[:-1]) > 0
                starts, ends = C.runs_of(mask)
                kept = part[~mask].tobytes()
                gone = int(mask.sum())
            row = (name, len(part), gone, len(starts), kept if with_text else None, hashlib.sha256(kept).hexdigest(), starts, ends)
            for to, x in zip(cols, row, strict=True):
                to.append(x)
        return pa.table(dict(zip(_OUT.names, cols, strict=True)), schema=_OUT)

    return run


def repeated_byte_spans(docs: DataFrame, k: int = DEPTH, id_col: str = "doc_id", text_col: str = "text", with_text: bool = True) -> DataFrame:
    """For each document: its bytes, how many go and in which spans, and what is left (bytes and their SHA-256)."""
    if k < 2:
        raise ValueError("a repeated string has two bytes at least")
    lay = C.layout_for(docs, text_col)
    texts = C.by_chunk(docs, lay, id_col, text_col)
    anchors = texts.groupBy("chunk").applyInArrow(_send_anchors(lay, k), C.PACKED)
    first = C.exchange(anchors, lay).groupBy("bucket").applyInArrow(C.tally, C.ANSWER)
    dealt = texts.groupBy("chunk").cogroup(C.exchange(first, lay, "chunk").groupBy("chunk")).applyInArrow(_send_contexts(lay, k), C.PACKED)
    sorted_ = C.exchange(dealt, lay).groupBy("bucket").applyInArrow(_passes(k), C.ANSWER)
    return texts.groupBy("chunk").cogroup(C.exchange(sorted_, lay, "chunk").groupBy("chunk")).applyInArrow(_mark(lay, k, with_text), _OUT_DDL)


def op4_suffix_dedup(spark, sf_dir: str) -> DataFrame:
    """The repeated-bytes contract on ``documents``."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    return repeated_byte_spans(docs, with_text=False).select("doc_id", "n_bytes", "n_removed", "n_spans", "kept_sha256")
