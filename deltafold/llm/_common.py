"""Numpy and Arrow building blocks that the corpus operators share.

Texts travel in *chunks*: a chunk is the set of documents whose id and text hash to one number, about
``chunk_bytes`` of text.  Fingerprints of a chunk's tokens travel to *buckets* as one packed row for
each (chunk, bucket), never one row for each token, and a bucket answers with one byte for each packed
fingerprint, in the order they were sent.  So no row holds more than a chunk's share of a bucket, a
fingerprint that a third of all documents hold is sent once by each chunk, and nothing is collected.
"""

from __future__ import annotations

import hashlib
import math
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

U64 = np.uint64
#: Low bits of a fingerprint that are sent; its bucket gives the others.
VALUE_BITS = 44


@dataclass(frozen=True)
class Layout:
    """How many chunks, buckets and shuffle partitions a corpus gets."""

    chunks: int
    buckets: int
    partitions: int


def layout_for(docs: DataFrame, text_col: str = "text") -> Layout:
    """Chunk and bucket counts that follow the corpus' bytes (one cheap aggregate over the text column)."""
    total = docs.select(F.sum(F.octet_length(F.col(text_col))).alias("b")).first()["b"] or 0
    spark = docs.sparkSession
    partitions = max(1, int(spark.conf.get("spark.sql.shuffle.partitions")), math.ceil(total / 64e6))
    chunk_bytes = min(32e6, max(1e6, 1e6 * math.sqrt(total / 1e9)))
    return Layout(max(1, math.ceil(total / chunk_bytes)), 3 * partitions, partitions)


def unused(name: str, taken) -> str:
    """A column name like ``name`` that none of the columns ``taken`` has, in any case of letters."""
    have = {c.lower() for c in taken}
    while name.lower() in have:
        name += "_"
    return name


def by_chunk(docs: DataFrame, lay: Layout, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(id, text, chunk) partitioned by chunk.  Null texts become empty.  Chunks follow id and text, so that rows
    without an id, or different texts of one id, are no hot group.  Every later step that uses this frame reads the
    same shuffle (one exchange, reused)."""
    return docs.select(
        F.col(id_col).cast("long").alias("id"),
        F.coalesce(F.col(text_col).cast("string"), F.lit("")).alias("text"),
        F.pmod(F.xxhash64(F.col(id_col).cast("long"), F.xxhash64(F.col(text_col).cast("string"))), F.lit(lay.chunks)).cast("int").alias("chunk"),
    ).repartition(lay.partitions, "chunk")


# ---------------------------------------------------------------- texts as byte arrays


def ordered(table: pa.Table) -> pa.Table:
    """A chunk's documents by id, then text: shuffles deliver rows in any order, and steps that exchange
    answers by position need the same one."""
    return table.take(pc.sort_indices(table, sort_keys=[("id", "ascending"), ("text", "ascending")]))


def text_buffers(column) -> tuple[np.ndarray, np.ndarray]:
    """A string column as (bytes, offsets), without a copy where Arrow allows it."""
    arr = column.combine_chunks() if isinstance(column, pa.ChunkedArray) else column
    if isinstance(arr, pa.ChunkedArray):
        arr = pa.concat_arrays(arr.chunks) if arr.num_chunks else pa.array([], arr.type)
    if len(arr) == 0:
        return np.zeros(0, np.uint8), np.zeros(1, np.int64)
    wide = pa.types.is_large_string(arr.type) or pa.types.is_large_binary(arr.type)
    offsets = np.frombuffer(arr.buffers()[1], np.int64 if wide else np.int32)[arr.offset : arr.offset + len(arr) + 1].astype(np.int64)
    data = arr.buffers()[2]
    raw = np.frombuffer(data, np.uint8) if data is not None else np.zeros(0, np.uint8)
    return raw[offsets[0] : offsets[-1]], offsets - offsets[0]


def slices(offsets: np.ndarray, limit: int = 1 << 20):
    """Ranges of documents of at most ``limit`` bytes together (one document alone may be longer)."""
    i, n = 0, len(offsets) - 1
    while i < n:
        j = max(i + 1, int(np.searchsorted(offsets, offsets[i] + limit, "right")) - 1)
        yield i, j
        i = j


# ---------------------------------------------------------------- hashing


def mix(h: np.ndarray, seed: int = 0) -> np.ndarray:
    """A 64-bit finaliser (multiply and xor-shift), in place on a copy."""
    h = h + U64((0x9E3779B97F4A7C15 * (seed + 1)) & (2**64 - 1))
    h ^= h >> U64(30)
    h *= U64(0xBF58476D1CE4E5B9)
    h ^= h >> U64(27)
    h *= U64(0x94D049BB133111EB)
    h ^= h >> U64(31)
    return h


def rolling(items: np.ndarray, k: int, base: int) -> np.ndarray:
    """Polynomial hash of every k consecutive items, built by doubling."""
    n = len(items)
    if n < k:
        return np.zeros(0, U64)
    with np.errstate(over="ignore"):
        out, out_len, power, length = None, 0, items, 1
        while True:
            if k & length:
                if out is None:
                    out, out_len = power, length
                else:
                    m = n - out_len - length + 1
                    out = out[:m] * U64(pow(base, length, 2**64)) + power[out_len : out_len + m]
                    out_len += length
            if out_len == k:
                return out[: n - k + 1]
            m = n - 2 * length + 1
            power = power[:m] * U64(pow(base, length, 2**64)) + power[length : length + m]
            length *= 2


def _joined(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """One hash for two that follow each other.  Each joint is mixed, so no pattern of equal items cancels out,
    as patterns do in a sum of powers modulo 2**64."""
    h = a * U64(0x9FB21C651E98DF25)
    h += b
    h ^= h >> U64(32)
    h *= U64(0xD6E8FEB86659FD93)
    return h


def window_hashes(items: np.ndarray, k: int, seed: int = 0) -> np.ndarray:
    """64-bit hash of every k consecutive items, built by doubling."""
    n = len(items)
    if n < k:
        return np.zeros(0, U64)
    with np.errstate(over="ignore"):
        out, out_len, power, length = None, 0, items, 1
        while True:
            if k & length:
                if out is None:
                    out, out_len = power, length
                else:
                    m = n - out_len - length + 1
                    out = _joined(out[:m], power[out_len : out_len + m])
                    out_len += length
            if out_len == k:
                return mix(out[: n - k + 1], seed)
            m = n - 2 * length + 1
            power = _joined(power[:m], power[length : length + m])
            length *= 2


_SPACE = np.zeros(256, bool)
_SPACE[[0x20, 0x09, 0x0A, 0x0B, 0x0C, 0x0D]] = True
#: Bytes up to which words are hashed together, eight bytes at a time; longer ones go through a digest.
_LONG = 128
_LOW_BYTES = np.array([(1 << 8 * n) - 1 for n in range(9)], U64)


def word_bounds(raw: np.ndarray, starts_of_docs: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Byte starts and ends of the maximal runs without white space; a document's end ends a word."""
    if len(raw) == 0:
        return np.zeros(0, np.int64), np.zeros(0, np.int64)
    word = ~_SPACE[raw]
    first = word.copy()
    first[1:] &= ~word[:-1]
    last = word.copy()
    last[:-1] &= ~word[1:]
    inner = starts_of_docs[(starts_of_docs > 0) & (starts_of_docs < len(raw))]
    first[inner] = word[inner]
    last[inner - 1] = word[inner - 1]
    return np.flatnonzero(first), np.flatnonzero(last) + 1


def word_hashes(raw: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
    """64-bit hash of each byte range.  Ranges of one length of up to eight bytes never collide."""
    if len(starts) == 0:
        return np.zeros(0, U64)
    padded = np.concatenate([raw, np.zeros(8, np.uint8)])
    eight = np.ndarray((len(raw) + 1,), "<u8", padded, strides=(1,))  # the eight bytes from each place on
    size = ends - starts
    with np.errstate(over="ignore"):
        h = mix(mix(size.astype(U64)) ^ (eight[starts] & _LOW_BYTES[np.minimum(size, 8)]))
        more, done = np.flatnonzero(size > 8), 8
        while len(more) and done < _LONG:
            left = size[more] - done
            h[more] = mix(h[more] ^ (eight[starts[more] + done] & _LOW_BYTES[np.minimum(left, 8)]))
            more, done = more[left > 8], done + 8
    for i in more.tolist():
        h[i] = int.from_bytes(hashlib.blake2b(raw[starts[i] : ends[i]].tobytes(), digest_size=8).digest(), "little")
    return h


# ---------------------------------------------------------------- packed fingerprints


def place(h: np.ndarray, buckets: int, bits: int = VALUE_BITS) -> np.ndarray:
    """bucket << VALUE_BITS | low bits: sorted, it lists the buckets one after the other.  Fewer ``bits`` pack
    shorter, where taking two tokens for one does no harm."""
    bucket = ((h >> U64(VALUE_BITS)) * U64(buckets)) >> U64(64 - VALUE_BITS)
    return (bucket << U64(VALUE_BITS)) | (h & U64((1 << bits) - 1))


def pack(values: np.ndarray) -> tuple[int, bytes]:
    """Sorted values as differences in as few whole bytes as they all fit in."""
    delta = np.diff(values, prepend=U64(0))
    width = max(1, (int(delta.max()).bit_length() + 7) // 8) if len(delta) else 1
    return width, delta.view(np.uint8).reshape(-1, 8)[:, :width].tobytes()


def unpack(width: int, blob: bytes) -> np.ndarray:
    raw = np.frombuffer(blob, np.uint8).reshape(-1, width)
    wide = np.zeros((len(raw), 8), np.uint8)
    wide[:, :width] = raw
    return np.cumsum(wide.reshape(-1).view(U64), dtype=U64)


PACKED = "bucket int, chunk int, width int, vals binary, extra binary"
ANSWER = "chunk int, bucket int, reply binary"
PACKED_ARROW = pa.schema([("bucket", pa.int32()), ("chunk", pa.int32()), ("width", pa.int32()), ("vals", pa.binary()), ("extra", pa.binary())])
ANSWER_ARROW = pa.schema([("chunk", pa.int32()), ("bucket", pa.int32()), ("reply", pa.binary())])


def bucket_ranges(placed: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """For sorted placed fingerprints: the buckets that occur, and where each begins and ends."""
    which = (placed >> U64(VALUE_BITS)).astype(np.int64)
    begin = np.flatnonzero(np.r_[True, which[1:] != which[:-1]]) if len(which) else np.zeros(0, np.int64)
    return which[begin], begin, np.r_[begin[1:], len(which)]


def packed_rows(chunk: int, placed: np.ndarray, extra: np.ndarray | None) -> pa.Table:
    """Sorted distinct fingerprints of a chunk (and bytes that go with each) as one row for each bucket."""
    rows: list[list] = [[], [], [], [], []]
    low = placed & U64((1 << VALUE_BITS) - 1)
    for b, i, j in zip(*(x.tolist() for x in bucket_ranges(placed)), strict=True):
        width, blob = pack(low[i:j])
        for to, x in zip(rows, (b, chunk, width, blob, b"" if extra is None else extra[i:j].tobytes()), strict=True):
            to.append(x)
    return pa.table(dict(zip(PACKED_ARROW.names, rows, strict=True)), schema=PACKED_ARROW)


def count_bytes(counts: np.ndarray) -> np.ndarray:
    return np.minimum(counts, 255).astype(np.uint8)


def tally(table: pa.Table) -> pa.Table:
    """In a bucket: for each fingerprint a byte, 0 where it occurs once in all chunks, else 1 + log2 of its
    other occurrences, rounded down.  Counts within a chunk are capped at 255, which leaves 0 exact."""
    chunks, widths = table["chunk"].to_pylist(), table["width"].to_pylist()
    parts = [unpack(w, v) for w, v in zip(widths, table["vals"].to_pylist(), strict=True)]
    counts = [np.frombuffer(x, np.uint8) for x in table["extra"].to_pylist()]
    sizes = [len(p) for p in parts]
    values = np.concatenate(parts)
    order = np.argsort(values, kind="stable")
    ordered = values[order]
    head = np.r_[True, ordered[1:] != ordered[:-1]]
    group = np.cumsum(head) - 1
    total = np.bincount(group, weights=np.concatenate(counts)[order].astype(np.float64))
    level = np.zeros(len(total), np.uint8)
    many = total > 1.5
    level[many] = 1 + np.floor(np.log2(total[many] - 1)).astype(np.uint8)
    reply = np.empty(len(values), np.uint8)
    reply[order] = level[group]
    cuts = np.cumsum([0, *sizes])
    bucket = table["bucket"][0].as_py()
    return pa.table({"chunk": chunks, "bucket": [bucket] * len(chunks), "reply": [reply[i:j].tobytes() for i, j in zip(cuts[:-1], cuts[1:], strict=True)]}, schema=ANSWER_ARROW)


def replies(table: pa.Table) -> np.ndarray:
    """All answers to a chunk, in the order of its sorted placed fingerprints."""
    if table.num_rows == 0:
        return np.zeros(0, np.uint8)
    order = np.argsort(table["bucket"].to_numpy())
    blobs = table["reply"].to_pylist()
    return np.frombuffer(b"".join(blobs[i] for i in order), np.uint8)


def exchange(rows: DataFrame, lay: Layout, key: str = "bucket") -> DataFrame:
    return rows.repartition(lay.partitions, key)


def runs_of(mask: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Starts and ends of the runs of true."""
    edge = np.diff(np.r_[0, mask.astype(np.int8), 0])
    return np.flatnonzero(edge == 1), np.flatnonzero(edge == -1)


def covered(n: int, starts: np.ndarray, length: int) -> np.ndarray:
    """Which of n places lie in a range of ``length`` from one of ``starts``."""
    step = np.zeros(n + 1, np.int32)
    np.add.at(step, starts, 1)
    np.add.at(step, starts + length, -1)
    return np.cumsum(step[:-1]) > 0


class Memo(dict):
    """compute(key) remembered for short keys.  Two generations bound the memory: when the young one is full,
    it becomes the old one."""

    def __init__(self, compute, limit: int = 200_000, longest: int = 64):
        super().__init__()
        self.compute, self.limit, self.longest, self.old = compute, limit, longest, {}

    def __missing__(self, key):
        got = self.old.get(key)
        if got is None:
            got = self.compute(key)
        if len(key) <= self.longest:
            if len(self) >= self.limit:
                self.old = dict(self)
                self.clear()
            self[key] = got
        return got
