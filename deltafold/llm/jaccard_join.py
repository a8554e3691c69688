"""Exact n-gram Jaccard join, to connected classes or to pairs, by token-combination prefixes.

1. *document counts*: shingle fingerprints of each chunk go to buckets, which answer with each shingle's
   class of document count (exact where it is 1).
2. *who can link*: a document of n shingles needs ceil(t n) common ones, so one with more unique shingles
   than that leaves has no partner.  Documents with equal sets become one node.
3. *tokens*: shingles that exactly the same nodes hold always come together, so they are one token with a
   weight.  Passages that many documents share become one token each.  Tokens are ordered by their number of
   nodes, rarest first.
4. *leaders*: nodes that share a min-hash are compared with one of them only, the most central (of the most
   common shingles on average).  Then, for ``LEADER_ROUNDS`` rounds, so are nodes that share a prefix token
   but no label yet.  This joins large groups of near copies by about as many comparisons as they have members.
5. *prefixes*: two nodes that link share a token before which each skips at most n - ceil(t n) of weight.  At
   their first common token what is left of both must still make the overlap, so keys whose places do not allow
   it make no pair.  A token of a rare class is a key by itself.  Where a token leaves many pairs between labels
   (a frequent class), prefixes are extended: its combinations with each later token that a linking pair can have
   as its second common one are the keys, if they leave fewer pairs than the token alone.
6. *verify* and contract: all pairs left are checked on whole sets; links and equal sets give components.

Rows of one key meet only across labels: a row of label hash h goes to a group for each leading part of h, and
meets there those whose next bit differs.  So a group's rows of one label never meet each other, each pair of
labels meets once, and no pair is capped or dropped.

Sets are compared by 64-bit fingerprints of shingles: a comparison of two documents of n and m shingles errs only
where two of these n m pairs collide.  Sets are taken for equal by 128-bit digests.

Cases: a null or empty text has no shingles and links with nothing; a text of fewer words than a shingle is
one shingle; null ids link with nothing and get a null component; rows that repeat an id or text fall in one
class; an empty table gives an empty result; other columns are ignored.
"""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from deltafold.llm import _common as C
from deltafold.llm._graph import components
from deltafold.session import cut_and_free

U64 = np.uint64
WORDS, PERCENT = 5, 75
#: A token that leaves more pairs between labels than this many for each of its nodes is of a frequent class.  A pair
#: costs a comparison of sizes and places inside the join (some 20 ns); a combination costs a row that is counted and
#: shuffled, and a node has tens of them.
PAIRS_PER_NODE = 1024
LEADER_KEYS = 4
LEADER_ROUNDS = 3
#: Bits of a fingerprint, besides its bucket's, by which documents are counted.  Two shingles that agree in
#: them get one class, which changes who is looked at further, and no result.
COUNT_BITS = 32
#: An element of a set is a token's hash with its weight in the low bits; heavier tokens are several elements.
WEIGHT_BITS = 12
_HEAVIEST = (1 << WEIGHT_BITS) - 1

_LOWER = np.arange(256, dtype=np.uint8)
_LOWER[ord("A") : ord("Z") + 1] += 32


def _sets(table: pa.Table, k: int):
    """For each document of a chunk: its distinct shingle fingerprints, sorted."""
    raw, offsets = C.text_buffers(table["text"])
    for i, j in C.slices(offsets):
        part, begins = _LOWER[raw[offsets[i] : offsets[j]]], offsets[i : j + 1] - offsets[i]
        s, e = C.word_bounds(part, begins[:-1])
        words = C.word_hashes(part, s, e)
        doc = np.searchsorted(begins, s, "right") - 1
        first = np.searchsorted(doc, np.arange(j - i + 1))
        h = C.window_hashes(words, k, k)
        for a, b in zip(first[:-1].tolist(), first[1:].tolist(), strict=True):
            n = b - a
            if n >= k:
                yield np.unique(h[a : b - k + 1])
            elif n:
                yield C.window_hashes(words[a:b], n, n)
            else:
                yield np.zeros(0, U64)


def _send(lay: C.Layout, k: int):
    def run(table: pa.Table) -> pa.Table:
        got = list(_sets(table, k))
        u, n = np.unique(C.place(np.concatenate(got), lay.buckets, COUNT_BITS), return_counts=True)
        return C.packed_rows(table["chunk"][0].as_py(), u, C.count_bytes(n))

    return run


_ROW = "id long, n long, digest binary, central int, shingles array<long>"
_ROW_ARROW = pa.schema([("id", pa.int64()), ("n", pa.int64()), ("digest", pa.binary()), ("central", pa.int32()), ("shingles", pa.list_(pa.int64()))])


def _needed(n: int, percent: int) -> int:
    return -(-percent * n // 100)


def _rows(lay: C.Layout, k: int, percent: int):
    def run(texts: pa.Table, answers: pa.Table) -> pa.Table:
        if texts.num_rows == 0:
            return _ROW_ARROW.empty_table()
        sets = list(_sets(texts, k))
        _, back = np.unique(C.place(np.concatenate(sets), lay.buckets, COUNT_BITS), return_inverse=True)
        level = C.replies(answers)[back]
        cols: list[list] = [texts["id"].to_pylist(), [len(s) for s in sets], [], [], []]
        at, sent = 0, set()
        for key, s in zip(cols[0], sets, strict=True):
            mine = level[at : at + len(s)]
            at += len(s)
            if len(s) and key is not None and np.count_nonzero(mine) >= _needed(len(s), percent):
                cols[2].append(hashlib.blake2b(s.tobytes(), digest_size=16).digest())
                cols[3].append(int(1000 * mine.mean()))
                cols[4].append(None if cols[2][-1] in sent else s.view(np.int64))
                sent.add(cols[2][-1])  # copies within a chunk send their set once
            else:
                for c in cols[2:]:
                    c.append(None)
        return pa.table(dict(zip(_ROW_ARROW.names, cols, strict=True)), schema=_ROW_ARROW)

    return run


def _documents(docs: DataFrame, k: int, percent: int, id_col: str, text_col: str) -> DataFrame:
    """Steps 1 and 2: a row for each document, with its set where it can link (once for each chunk's copies)."""
    lay = C.layout_for(docs, text_col)
    texts = C.by_chunk(docs, lay, id_col, text_col)
    sent = texts.groupBy("chunk").applyInArrow(_send(lay, k), C.PACKED)
    counts = C.exchange(sent, lay).groupBy("bucket").applyInArrow(C.tally, C.ANSWER)
    return cut_and_free(texts.groupBy("chunk").cogroup(C.exchange(counts, lay, "chunk").groupBy("chunk")).applyInArrow(_rows(lay, k, percent), _ROW))


def _nodes(rows: DataFrame) -> DataFrame:
    """Documents with equal sets as one node, numbered."""
    keys = F.array(*(F.array_min(F.transform("shingles", lambda x, s=s: F.xxhash64(x, F.lit(s)))) for s in range(LEADER_KEYS)))
    sets = rows.where("shingles is not null").select("digest", "n", "central", "shingles").dropDuplicates(["digest"])
    return cut_and_free(sets.select(F.monotonically_increasing_id().alias("node"), "digest", "n", "central", "shingles", keys.alias("looks")))


def _elements(nodes: DataFrame) -> DataFrame:
    """Step 3, a row for each node and token: (node, e, c, w, n, before), where ``before`` is the weight of the
    node's tokens that come earlier; tokens of one node alone weigh, but have no row."""
    spread = nodes.select("node", F.explode("shingles").alias("s"))
    owners = spread.groupBy("s").agg(F.count("*").alias("c"), F.bit_xor(F.xxhash64("node")).alias("x"), F.bit_xor(F.xxhash64("node", F.lit(1))).alias("y"))
    shared = owners.where("c > 1").select("s", "c", F.xxhash64("c", "x", "y").alias("t"))
    tokens = spread.join(shared, "s").groupBy("node", "t").agg(F.first("c").alias("c"), F.count("*").alias("w"))
    parts = tokens.withColumn("j", F.explode(F.sequence(F.lit(0).cast("long"), F.expr(f"(w - 1) div {_HEAVIEST}"))))
    weight = F.least(F.col("w") - F.col("j") * _HEAVIEST, F.lit(_HEAVIEST).cast("long"))
    e = F.shiftleft(F.shiftright(F.xxhash64("t", "j"), WEIGHT_BITS), WEIGHT_BITS).bitwiseOR(weight)
    parts = parts.select("node", e.alias("e"), "c", weight.cast("int").alias("w"))
    mine = Window.partitionBy("node")
    alone = F.col("n") - F.sum("w").over(mine)
    running = F.sum("w").over(mine.orderBy("c", "e").rowsBetween(Window.unboundedPreceding, -1))
    return cut_and_free(parts.join(nodes.select("node", "n"), "node").withColumn("before", alone + F.coalesce(running, F.lit(0))))


def _slack(percent: int):
    """Weight that a node can skip and still have a partner."""
    return F.col("n") - F.ceil(F.col("n") * percent / 100)


def _overlap(a, b, percent: int):
    """Common shingles that sets of sizes a and b need, times 100 + percent."""
    return F.lit(percent) * (a + b)


def _verified(pairs: DataFrame, bags: DataFrame, percent: int) -> DataFrame:
    """The pairs (a, b) whose sets are similar enough, with their common shingles."""
    left = bags.select(F.col("node").alias("a"), F.col("es").alias("ea"), F.col("n").alias("na"))
    right = bags.select(F.col("node").alias("b"), F.col("es").alias("eb"), F.col("n").alias("nb"))
    common = F.aggregate(F.array_intersect("ea", "eb"), F.lit(0).cast("long"), lambda s, x: s + x.bitwiseAND(F.lit(_HEAVIEST).cast("long")))
    both = pairs.join(right, "b").join(left, "a").withColumn("common", common)
    return both.where(F.lit(100 + percent) * F.col("common") >= _overlap(F.col("na"), F.col("nb"), percent)).select("a", "b", "common")


def _across(entries: DataFrame, percent: int) -> DataFrame:
    """Distinct pairs of nodes with a common key and different labels whose sizes and places allow a link.

    ``entries``: (key, label, node, n, left): ``left`` is the most that a node can have in common with another
    if the key is where their common tokens begin."""
    bits = F.xxhash64("label")
    labels = entries.select("key", bits.alias("h")).distinct()
    near = Window.partitionBy("key").orderBy(F.col("h").bitwiseXOR(F.lit(-(1 << 63))))
    # how many leading bits two neighbouring label hashes of a key share: beyond that, groups hold one label
    apart = F.col("h").bitwiseXOR(F.lag("h").over(near))
    same = F.when(apart < 0, 0).otherwise(F.lit(63) - F.floor(F.log2(apart.cast("double"))).cast("int"))
    depth = labels.withColumn("same", same).groupBy("key").agg(F.max("same").alias("depth")).where("depth is not null")
    # log2 of a rounded double may be one too high: one more level does no harm, as no rows meet there
    told = entries.withColumn("h", bits).join(depth, "key").withColumn("i", F.explode(F.expr("sequence(0, least(depth + 1, 63))")))
    told = told.select("node", "n", "left", F.expr("xxhash64(key, i, CASE WHEN i = 0 THEN 0L ELSE shiftrightunsigned(h, 64 - i) END)").alias("g"), F.expr("shiftrightunsigned(h, 63 - i) & 1").alias("bit"))
    a = told.where("bit = 0").select("g", F.col("node").alias("a"), F.col("n").alias("na"), F.col("left").alias("ra"))
    b = told.where("bit = 1").select("g", F.col("node").alias("b"), F.col("n").alias("nb"), F.col("left").alias("rb"))
    enough = (F.lit(100 + percent) * F.least("ra", "rb") >= _overlap(F.col("na"), F.col("nb"), percent)) & (100 * F.least("na", "nb") >= percent * F.greatest("na", "nb"))
    return a.join(b, (a["g"] == b["g"]) & enough).select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).distinct()


def _cross(entries: DataFrame, *keys: str) -> DataFrame:
    """For each key, its nodes and the pairs of them that have different labels."""
    each = entries.groupBy(*keys, "label").agg(F.count("*").alias("k"))
    return each.groupBy(*keys).agg(F.sum("k").alias("m"), ((F.sum("k") * F.sum("k") - F.sum(F.col("k") * F.col("k"))) / 2).alias("cross"))


def _candidates(elements: DataFrame, entries: DataFrame, percent: int) -> DataFrame:
    """Step 5.  ``entries``: prefix tokens (key, label, node, n, w, before) of keys with several labels."""
    counted = cut_and_free(_cross(entries, "key"))
    many = counted.where(F.col("cross") > PAIRS_PER_NODE * F.col("m")).select("key", "cross")
    single = entries.withColumn("left", F.col("n") - F.col("before"))
    if many.isEmpty():
        return _across(single, percent)
    first = entries.join(many.select("key"), "key", "left_semi").select("node", "label", "n", F.col("key").alias("one"), F.col("w").alias("w1"), F.col("before").alias("b1"))
    later = elements.select("node", "e", F.col("w").alias("w2"), F.col("before").alias("b2"))
    two = first.join(later, "node").where((F.col("b2") > F.col("b1")) & (F.col("b2") - F.col("w1") <= _slack(percent)))
    two = two.select("one", F.xxhash64("one", "e").alias("key"), "label", "node", "n", (F.col("w1") + F.col("n") - F.col("b2")).alias("left"))
    # nothing more in common: enough if the token alone is
    alone = first.where(F.col("w1") >= F.ceil(F.col("n") * percent / 100)).select("one", F.xxhash64("one", F.lit("alone")).alias("key"), "label", "node", "n", F.col("w1").cast("long").alias("left"))
    combined = cut_and_free(two.unionByName(alone))
    cost = _cross(combined, "one", "key").groupBy("one").agg(F.sum("cross").alias("after"))
    split = cut_and_free(many.join(cost, many["key"] == cost["one"], "left").where(F.coalesce("after", F.lit(0)) < F.col("cross")).select("key"))
    pairs = _across(single.join(split, "key", "left_anti"), percent)
    return pairs.unionByName(_across(combined.join(split.withColumnRenamed("key", "one"), "one", "left_semi"), percent)).distinct()


def _index(nodes: DataFrame, percent: int) -> tuple[DataFrame, DataFrame, DataFrame]:
    """Elements, nodes with their elements as one array, and prefix tokens."""
    elements = _elements(nodes)
    bags = cut_and_free(elements.groupBy("node").agg(F.first("n").alias("n"), F.collect_list("e").alias("es")))
    prefixes = elements.where(F.col("before") <= _slack(percent)).select("node", F.col("e").alias("key"), "n", "w", "before")
    return elements, bags, cut_and_free(prefixes)


def _mixed(prefixes: DataFrame, labels: DataFrame) -> DataFrame:
    """Prefix tokens with their nodes' labels, of keys with several labels."""
    found = prefixes.join(labels, "node", "left").withColumn("label", F.coalesce("label", "node"))
    several = found.groupBy("key").agg((F.min("label") < F.max("label")).alias("several")).where("several").select("key")
    return cut_and_free(found.join(several, "key", "left_semi"))


def similar_classes(docs: DataFrame, k: int = WORDS, percent: int = PERCENT, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """For each document: the size of its shingle set and the smallest id it is linked with, directly or not."""
    rows = _documents(docs, k, percent, id_col, text_col)
    nodes = _nodes(rows)
    elements, bags, prefixes = _index(nodes, percent)

    # leaders
    looks = nodes.select("node", "central", F.explode("looks").alias("key"))
    leaders = looks.groupBy("key").agg(F.max(F.struct("central", "node"))["node"].alias("a"), F.count("*").alias("c")).where("c > 1").select("key", "a")
    pairs = looks.join(leaders, "key").where("a <> node").select("a", F.col("node").alias("b")).distinct()
    links = cut_and_free(_verified(pairs, bags, percent).select("a", "b"))
    central = nodes.select("node", "central")
    entries = _mixed(prefixes, components(links))
    for turn in range(LEADER_ROUNDS):
        by = F.col("central").cast("long") if turn == 0 else F.xxhash64("label", F.lit(turn))
        left = F.col("n") - F.col("before")
        best = entries.join(central, "node").groupBy("key").agg(F.max(F.struct(by.alias("by"), "central", "node", "label", F.col("n").alias("na"), left.alias("ra"))).alias("top")).select("key", "top.node", "top.label", "top.na", "top.ra").toDF("key", "a", "la", "na", "ra")
        enough = F.lit(100 + percent) * F.least("ra", left) >= _overlap(F.col("na"), F.col("n"), percent)
        found = cut_and_free(_verified(entries.join(best, "key").where((F.col("la") != F.col("label")) & enough).select("a", F.col("node").alias("b")).distinct(), bags, percent).select("a", "b"))
        if found.isEmpty():
            break
        links = cut_and_free(links.unionByName(found))
        entries = _mixed(prefixes, components(links))

    more = cut_and_free(_verified(_candidates(elements, entries, percent), bags, percent).select("a", "b"))
    labels = components(links.unionByName(more))
    members = rows.where("digest is not null").select("id", "digest").join(nodes.select("digest", "node"), "digest")
    classes = members.join(labels, "node", "left").withColumn("label", F.coalesce("label", "node"))
    smallest = classes.groupBy("label").agg(F.min("id").alias("smallest"))
    # an id that stands in several rows belongs to the smallest of their classes
    found = classes.select("id", "label").distinct().join(smallest, "label").groupBy("id").agg(F.min("smallest").alias("smallest"))
    out = rows.select(F.col("id").alias("doc_id"), F.col("n").alias("n_shingles")).join(found.withColumnRenamed("id", "doc_id"), "doc_id", "left")
    return out.select("doc_id", "n_shingles", F.coalesce("smallest", "doc_id").alias("component_id"))


def similar_pairs(docs: DataFrame, k: int = WORDS, percent: int = PERCENT, id_col: str = "doc_id", text_col: str = "text") -> tuple[DataFrame, DataFrame]:
    """All links: (pairs, members).  Pairs (a, b, common) are of documents with different sets, each set standing
    under its smallest id; members (doc_id, representative) say which document has which set.  The pairs are as
    many as there are links between different sets."""
    rows = _documents(docs, k, percent, id_col, text_col)
    nodes = _nodes(rows)
    elements, bags, prefixes = _index(nodes, percent)
    found = _verified(_candidates(elements, _mixed(prefixes, nodes.select("node", F.col("node").alias("label"))), percent), bags, percent)
    members = cut_and_free(rows.where("digest is not null").select("id", "digest").join(nodes.select("digest", "node"), "digest"))
    first = members.groupBy("node").agg(F.min("id").alias("rep"))
    ends = found.join(first.select(F.col("node").alias("a"), F.col("rep").alias("ra")), "a").join(first.select(F.col("node").alias("b"), F.col("rep").alias("rb")), "b")
    pairs = ends.select(F.least("ra", "rb").alias("a"), F.greatest("ra", "rb").alias("b"), "common")
    return pairs, members.join(first, "node").select(F.col("id").alias("doc_id"), F.col("rep").alias("representative"))


def keep_first_of_classes(docs: DataFrame, k: int = WORDS, percent: int = PERCENT, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """The rows of ``docs`` whose id is the smallest of its class (rows that repeat an id stay or go together; rows
    without an id stay)."""
    gone = similar_classes(docs, k, percent, id_col, text_col).where("component_id <> doc_id").select(F.col("doc_id").alias("__gone")).distinct()
    return docs.join(gone, docs[id_col] == gone["__gone"], "left_anti")


def op5_jaccard_join(spark, sf_dir: str) -> DataFrame:
    """The near-duplicate contract on ``documents``."""
    return similar_classes(spark.read.parquet(f"{sf_dir}/documents.parquet"))
