"""Best-fit packing of documents into training sequences, by a tree of partitions.

1. *pieces*: texts become token ids; a document's ids end with a separator; only documents longer than a
   sequence are cut.
2. *leaves*: pieces are dealt in turn over the partitions, so each leaf holds the corpus' mix of lengths
   however the input is laid out.  A leaf packs its pieces, longest first, into the fullest bin that has room.
   Bins that are nearly full leave at once.
3. *tree*: underfull bins of ``FAN_IN`` neighbouring nodes meet as items and are packed again, level by
   level, until one node is left.  Only fills and keys of bins travel; the moves (fewer than there are leaves)
   are carried out at the end.

No bin that could still take another leaves early.  Best fit leaves a node at most one bin that is half full
or less, and two fuller bins never fit together, so ``FAN_IN`` nodes that meet make fewer than ``FAN_IN`` moves.
A node therefore hands on ``FAN_IN`` bins of each fill for each level above it: more can never be asked for.

Cases: a null or empty text is the separator alone (one piece of length 1); rows that repeat a document are
packed as often as they occur; null ids stay null; an empty table gives an empty result; other columns are
ignored.
"""

from __future__ import annotations

import os
import re
import zlib
from functools import lru_cache

import numpy as np
import public_tokenizers
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from deltafold.session import cut

CAPACITY = 2048
SEPARATOR = 0
FAN_IN = 16
#: A bin leaves when its free room is at most this part of a sequence.
NEARLY_FULL = 1 / 128
_ODD = re.compile("[\x1c-\x1f]")
_BETWEEN = "\x01"
_MARKS = ".,;:!?*#$%&|"
_TOGETHER = 400  # texts that are split at once
_PIECE = "doc_id long, piece int, start long, length long, ids_crc32 long, ids binary"
_PIECE_ARROW = pa.schema([("doc_id", pa.int64()), ("piece", pa.int32()), ("start", pa.int64()), ("length", pa.int64()), ("ids_crc32", pa.int64()), ("ids", pa.binary())])


class WordIds:
    """Ids as little-endian 32-bit bytes.  The vocabulary's pattern never crosses white space, so a text's ids
    are those of its white-space-free strings in turn.  Strings not seen of late go to the tokenizers library
    together, with a separator between them that none of them holds.  Two generations bound the memory."""

    def __init__(self, path: str, limit: int = 600_000):
        from tokenizers import Tokenizer

        os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")
        self.tokenizer = Tokenizer.from_file(path)
        self.tokenizer.no_truncation()
        self.tokenizer.no_padding()
        self.limit, self.young, self.old = limit, {}, {}
        self.mark = np.array(self.tokenizer.encode(_BETWEEN, add_special_tokens=False).ids, "<u4")

    def whole(self, text: str) -> bytes:
        return np.array(self.tokenizer.encode(text, add_special_tokens=False).ids, "<u4").tobytes()

    def _together(self, words: list[str]) -> dict[str, bytes]:
        if len(self.mark) != 1:
            return {w: self.whole(w) for w in words}
        apart = [w for w in words if _BETWEEN in w]
        words = [w for w in words if _BETWEEN not in w]
        lots = [words[i : i + 256] for i in range(0, len(words), 256)]
        out = {w: self.whole(w) for w in apart}
        for lot, got in zip(lots, self.tokenizer.encode_batch_fast([f" {_BETWEEN} ".join(x) for x in lots], add_special_tokens=False), strict=True):
            ids = np.array(got.ids, "<u4")
            cuts = np.flatnonzero(ids == self.mark[0])
            begins, ends = [0, *(cuts + 1).tolist()], [*cuts.tolist(), len(ids)]
            out.update((w, ids[i:j].tobytes()) for w, i, j in zip(lot, begins, ends, strict=True))
        return out

    @staticmethod
    def _stem(word: str) -> tuple[str, str]:
        """Letters, and marks that follow them: a pretoken each.  Only letters that the vocabulary's normaliser
        leaves letters are split from their marks: ASCII ones, lower-cased as it does, and those that have no
        upper case to lose."""
        stem = word.rstrip(_MARKS)
        if not stem.isalpha():
            return word, ""
        if stem.isascii():
            return stem.lower(), word[len(stem) :]
        return (stem, word[len(stem) :]) if stem.lower() == stem else (word, "")

    def texts(self, texts: list[str]) -> list[bytes]:
        if len(self.young) > self.limit:
            self.young, self.old = {}, self.young
        get, held, missing = self.young.get, [], {}
        for text in texts:
            if "<|" in text or _ODD.search(text):
                held.append((None, self.whole(text)))  # special tokens, and separators that only Python takes for white space
                continue
            words = text.split()
            got = list(map(get, words))
            if not all(got):  # some are not known (truth is cheaper to test than identity)
                missing.update((w, None) for w, v in zip(words, got, strict=True) if v is None)
            held.append((words, got))
        known, split, new = {}, [], {}
        for w in missing:
            if (v := self.old.get(w)) is not None:
                known[w] = v
            else:
                split.append((w, *self._stem(w)))
                new.update((x, None) for x in split[-1][1:] if x and x not in self.young and x not in self.old)
        new = self._together(list(new))
        look = lambda x: self.young.get(x) or self.old.get(x) or new[x]
        known.update((w, look(stem) + look(tail) if tail else look(stem)) for w, stem, tail in split)
        self.young.update((w, v) for lot in (new, known) for w, v in lot.items() if len(w) <= 64)
        out = []
        for words, got in held:
            if words is not None:
                got = b"".join(got if all(got) else [known[w] if v is None else v for w, v in zip(words, got, strict=True)])
            out.append(got)
        return out


@lru_cache(maxsize=2)
def word_ids(path: str) -> WordIds:
    return WordIds(path)


def _pieces(path: str, capacity: int, with_ids: bool):
    end = np.array([SEPARATOR], "<u4").tobytes()

    def run(batches):
        encode = word_ids(path).texts
        for batch in batches:
            cols: list[list] = [[] for _ in _PIECE_ARROW.names]
            keys, texts = batch["id"].to_pylist(), batch["text"].to_pylist()
            coded = (ids for i in range(0, len(texts), _TOGETHER) for ids in encode(texts[i : i + _TOGETHER]))
            for key, ids in zip(keys, coded, strict=True):
                ids += end
                for n, at in enumerate(range(0, len(ids), 4 * capacity)):
                    part = ids[at : at + 4 * capacity]
                    for to, x in zip(cols, (key, n, at // 4, len(part) // 4, zlib.crc32(part), part if with_ids else None), strict=True):
                        to.append(x)
            yield pa.record_batch(dict(zip(_PIECE_ARROW.names, cols, strict=True)), schema=_PIECE_ARROW)

    return run


def token_pieces(docs: DataFrame, tokenizer_path: str, capacity: int = CAPACITY, id_col: str = "doc_id", text_col: str = "text", with_ids: bool = False) -> DataFrame:
    """Documents' ids and a separator, cut into pieces of ``capacity`` where they are longer."""
    texts = docs.select(F.col(id_col).cast("long").alias("id"), F.coalesce(F.col(text_col).cast("string"), F.lit("")).alias("text"))
    return texts.mapInArrow(_pieces(tokenizer_path, capacity, with_ids), _PIECE)


def best_fit(sizes: list[int], capacity: int) -> list[list[int]]:
    """Places of items by bin: longest first, each into the fullest bin with room.  A bit for each amount of
    free room that some bin has makes the search one shift."""
    rooms: list[list[int]] = [[] for _ in range(capacity + 1)]
    seen, bins = 0, []
    for i in sorted(range(len(sizes)), key=lambda i: -sizes[i]):
        size = sizes[i]
        fits = seen >> size
        if fits:
            room = size + (fits & -fits).bit_length() - 1
            b = rooms[room].pop()
            if not rooms[room]:
                seen &= ~(1 << room)
            bins[b].append(i)
        else:
            room, b = capacity, len(bins)
            bins.append([i])
        room -= size
        if room:
            rooms[room].append(b)
            seen |= 1 << room
    return bins


_ITEM = pa.struct([("doc_id", pa.int64()), ("piece", pa.int32()), ("start", pa.int64()), ("length", pa.int64()), ("ids_crc32", pa.int64()), ("ids", pa.binary()), ("offset", pa.int64())])
_BIN_ARROW = pa.schema([("node", pa.int32()), ("key", pa.int64()), ("fill", pa.int64()), ("items", pa.list_(_ITEM))])
_BIN = "node int, key long, fill long, items array<struct<doc_id:long,piece:int,start:long,length:long,ids_crc32:long,ids:binary,offset:long>>"
#: Bins on their way up, and moves (rows with a ``moved_to``).
_LIGHT_ARROW = pa.schema([("node", pa.int32()), ("key", pa.int64()), ("fill", pa.int64()), ("moved_to", pa.int64())])
_LIGHT = "node int, key long, fill long, moved_to long"


def _in_turn(groups: list[list[dict]]) -> list[dict]:
    """The pieces of bins that share a sequence, one after the other."""
    items, at = [], 0
    for p in (p for g in groups for p in g):
        items.append(p | {"offset": at})
        at += p["length"]
    return items


def levels_above(nodes: int) -> int:
    """How often ``nodes`` nodes meet until one is left."""
    n = 0
    while nodes > 1:
        nodes, n = -(-nodes // FAN_IN), n + 1
    return n


def handed_on(fills: list[int], capacity: int, levels: int) -> list[int]:
    """Places of a packed node's bins that ``levels`` levels above it can have a use for."""
    seen: dict[int, int] = {}
    out = []
    for i, fill in enumerate(fills):
        if fill < capacity * (1 - NEARLY_FULL) and seen.get(fill, 0) < FAN_IN * levels:
            seen[fill] = seen.get(fill, 0) + 1
            out.append(i)
    return out


def meet(keys: list[int], fills: list[int], capacity: int) -> tuple[list[int], list[int], list[tuple[int, int]]]:
    """Bins packed as items: keys and fills of what results, and moves (key, key of the bin it goes into)."""
    bins = best_fit(fills, capacity)
    return [keys[b[0]] for b in bins], [sum(fills[i] for i in b) for b in bins], [(keys[i], keys[b[0]]) for b in bins for i in b[1:]]


def _leaves(capacity: int):
    def run(batches):
        node, pieces = None, []
        for batch in batches:
            if batch.num_rows and node is None:
                node = batch["node"][0].as_py()
            pieces += batch.drop_columns(["node"]).to_pylist()
        if pieces:
            packed = [_in_turn([[pieces[i]] for i in b]) for b in best_fit([p["length"] for p in pieces], capacity)]
            cols = [[node] * len(packed), [(node << 40) + i for i in range(len(packed))], [x[-1]["offset"] + x[-1]["length"] for x in packed], packed]
            yield from pa.table(dict(zip(_BIN_ARROW.names, cols, strict=True)), schema=_BIN_ARROW).to_batches()

    return run


def _onward(capacity: int, levels: int):
    def run(batches):
        rows = [r for b in batches for r in zip(b["node"].to_pylist(), b["key"].to_pylist(), b["fill"].to_pylist(), strict=True)]
        rows = [rows[i] for i in handed_on([r[2] for r in rows], capacity, levels)]
        yield pa.record_batch([pa.array([r[n] for r in rows], _LIGHT_ARROW.field(n).type) for n in range(3)] + [pa.nulls(len(rows), pa.int64())], schema=_LIGHT_ARROW)

    return run


def _meeting(capacity: int, levels: int):
    def run(table: pa.Table) -> pa.Table:
        node = table["node"][0].as_py()
        keys, fills, moves = meet(table["key"].to_pylist(), table["fill"].to_pylist(), capacity)
        stay = handed_on(fills, capacity, levels)
        rows = [(node, keys[i], fills[i], None) for i in stay] + [(node, k, 0, to) for k, to in moves]
        return pa.table({f.name: pa.array([r[n] for r in rows], f.type) for n, f in enumerate(_LIGHT_ARROW)}, schema=_LIGHT_ARROW)

    return run


def _joined(table: pa.Table) -> pa.Table:
    rows = sorted(table.to_pylist(), key=lambda r: (r["key"] != r["target"], r["key"]))
    return pa.table({"items": pa.array([_in_turn([r["items"] for r in rows])], pa.list_(_ITEM))})


def pack_pieces(pieces: DataFrame, capacity: int = CAPACITY) -> DataFrame:
    """``token_pieces`` rows with the sequence each lies in and its offset there."""
    nodes = max(1, pieces.rdd.getNumPartitions())
    dealt = pieces.repartition(nodes).withColumn("node", F.spark_partition_id())
    bins = cut(dealt.mapInArrow(_leaves(capacity), _BIN))
    nodes = max(1, bins.rdd.getNumPartitions())
    going, moves = bins.select("node", "key", "fill").mapInArrow(_onward(capacity, levels_above(nodes)), _LIGHT), {}
    while nodes > 1:
        nodes = -(-nodes // FAN_IN)
        met = cut(going.withColumn("node", F.floor(F.col("node") / FAN_IN).cast("int")).groupBy("node").applyInArrow(_meeting(capacity, levels_above(nodes)), _LIGHT))
        moves |= {r["key"]: r["moved_to"] for r in met.where("moved_to is not null").collect()}  # fewer than leaves, in all levels together
        going = met.where("moved_to is null")
    whole = bins
    if moves:
        ends = {}
        for key in moves:
            to = moves[key]
            while to in moves:
                to = moves[to]
            ends[key] = ends[to] = to
        named = F.broadcast(pieces.sparkSession.createDataFrame(list(ends.items()), "key long, target long"))
        joined = bins.join(named, "key").select("key", "target", "items").groupBy("target").applyInArrow(_joined, f"items {_BIN.split('items ')[1]}")
        whole = bins.join(named, "key", "left_anti").select("items").unionByName(joined)
    return whole.withColumn("sequence_id", F.monotonically_increasing_id()).select("sequence_id", F.inline("items"))


def packed_documents(docs: DataFrame, tokenizer_path: str, capacity: int = CAPACITY, id_col: str = "doc_id", text_col: str = "text", with_ids: bool = True) -> DataFrame:
    """Documents as pieces in sequences, with their ids (little-endian unsigned 32-bit) where asked for."""
    out = pack_pieces(token_pieces(docs, tokenizer_path, capacity, id_col, text_col, with_ids), capacity)
    return out.select("doc_id", "piece", "start", "length", "ids_crc32", *(["ids"] if with_ids else []), "sequence_id", "offset")


def op3_bestfit_packing(spark, sf_dir: str) -> DataFrame:
    """The packing contract on ``documents``."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    return packed_documents(docs, public_tokenizers.path("word_bpe_49k.json"), with_ids=False)
