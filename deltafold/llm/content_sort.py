"""Exact dedup by sorting contents.

Normalised texts are range-partitioned by sampled splitters on (first bytes, digest, id) and sorted
externally there: the first bytes order contents, the digest orders those that begin alike (so splitters stay
short however long the texts are), and the id splits a group of copies of any size over partitions.  Equal
texts are then neighbours.  One pass
compares each text with the one before it in full.  A group that crosses partitions is joined up from one
short row for each partition's first and last group, so no partition's rows are ever gathered.

Cases: null counts as the empty text; null ids sort after all others (a group of null ids only keeps one of
them); rows that repeat an id and text are copies of each other and one of them is kept; an empty table gives
an empty result; other columns are ignored.
"""

from __future__ import annotations

import re

import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql.types import BooleanType, IntegerType, StringType, StructField, StructType

from deltafold.llm._common import unused
from deltafold.session import cut

WHITE = r"[\x20\x09-\x0D]+"
_LAST = 2**63 - 1
_SORTED = "doc_id long, part int, run long, nth long, n_run long, at_start boolean, at_end boolean, text_sha256 string"
_SORTED_ARROW = pa.schema([
    ("doc_id", pa.int64()), ("part", pa.int32()), ("run", pa.int64()), ("nth", pa.int64()), ("n_run", pa.int64()),
    ("at_start", pa.bool_()), ("at_end", pa.bool_()), ("text_sha256", pa.string()),
])
#: Characters of a text that splitters hold.
HEAD = 32
#: Rows in a batch of output.
_HOLD = 100_000


def normalised(text):
    """A column with each run of white space as one space; null as empty."""
    return F.regexp_replace(F.coalesce(text.cast("string"), F.lit("")), WHITE, " ")


def _neighbours(batches):
    """Sorted rows in; each with its run (maximal range of equal texts of this partition) out.

    The run's length is known only at its end, so rows go out with ``nth`` as they come and one closing row
    for each run (null ``nth``) carries the length."""
    part, run, text, sha, first_id, n = None, -1, None, None, None, 0
    cols: list[list] = [[] for _ in _SORTED_ARROW.names]

    def put(*row) -> None:
        for to, x in zip(cols, row, strict=True):
            to.append(x)

    def flush():
        nonlocal cols
        out = pa.record_batch(dict(zip(_SORTED_ARROW.names, cols, strict=True)), schema=_SORTED_ARROW)
        cols = [[] for _ in _SORTED_ARROW.names]
        return out

    for batch in batches:
        ids, texts, hashes = batch["id"].to_pylist(), batch["norm"].to_pylist(), batch["sha"].to_pylist()
        for key, t, h in zip(ids, texts, hashes, strict=True):
            if part is None:
                part = batch["part"][0].as_py()
            if run < 0 or h != sha or t != text:  # the hash only saves comparisons of texts that differ
                if run >= 0:
                    put(first_id, part, run, None, n, run == 0, False, sha)
                run, text, sha, first_id, n = run + 1, t, h, key, 0
            put(key, part, run, n, None, run == 0, False, h)
            n += 1
        if len(cols[0]) >= _HOLD:
            yield flush()
    if run >= 0:
        put(first_id, part, run, None, n, run == 0, True, sha)
        yield flush()


def exact_duplicates(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per document: the id that stays of its group, the group's size, whether this row stays, and the
    SHA-256 of the normalised text."""
    spark = docs.sparkSession
    parts = max(int(spark.conf.get("spark.sql.shuffle.partitions")), 1)
    rows = docs.select(F.col(id_col).cast("long").alias("id"), normalised(F.col(text_col)).alias("norm"))
    order = ["head", "sha", "key"]
    dealt = rows.withColumns({"head": F.substring("norm", 1, HEAD), "sha": F.sha2(F.col("norm"), 256), "key": F.coalesce("id", F.lit(_LAST))})
    dealt = dealt.repartitionByRange(parts, *order).sortWithinPartitions(*order)
    # Written once: both uses below must see the same splitters.
    runs = cut(dealt.select("id", "norm", "sha", F.spark_partition_id().alias("part")).mapInArrow(_neighbours, _SORTED))
    closing = runs.where("nth is null").drop("nth")
    # Runs that touch a partition's edge: two rows for each partition at most.
    line = Window.orderBy("part", "run")
    joined = closing.where("at_start or at_end").withColumn("new", F.coalesce(F.lag("text_sha256").over(line) != F.col("text_sha256"), F.lit(True)).cast("int"))
    joined = joined.withColumn("chain", F.sum("new").over(line.rowsBetween(Window.unboundedPreceding, 0)))
    chain = Window.partitionBy("chain").orderBy("part", "run")
    whole = Window.partitionBy("chain")
    fixed = joined.select(
        "part", "run",
        F.first("doc_id").over(chain).alias("edge_keep"),
        F.sum("n_run").over(whole).alias("edge_size"),
        (F.row_number().over(chain) == 1).alias("edge_first"),
    )
    groups = closing.select("part", "run", F.col("doc_id").alias("run_keep"), "n_run").join(F.broadcast(fixed), ["part", "run"], "left").select(
        "part", "run",
        F.when(F.col("edge_size").isNull(), F.col("run_keep")).otherwise(F.col("edge_keep")).alias("keep_id"),
        F.coalesce("edge_size", "n_run").alias("group_size"),
        F.coalesce("edge_first", F.lit(True)).alias("has_first"),
    )
    return (
        runs.where("nth is not null").select("doc_id", "part", "run", "nth", "text_sha256")
        .join(groups, ["part", "run"])
        .select("doc_id", "keep_id", "group_size", (F.col("has_first") & (F.col("nth") == 0)).alias("kept"), "text_sha256")
    )


def _firsts(white: re.Pattern, names: dict[str, str]):
    """Sorted rows in; the first of each run out, with its partition, whether its run begins there and whether
    it is the last.  ``names`` gives the working columns' names."""

    def normal(text: str | None) -> str:
        return white.sub(" ", text or "")

    def run(batches):
        part, sha, text, held, first = None, None, None, None, True

        def tagged(rows: pa.RecordBatch, at_start: list[bool], at_end: list[bool]):
            for name, column in (("part", pa.array([part] * rows.num_rows, pa.int32())), ("at_start", pa.array(at_start, pa.bool_())), ("at_end", pa.array(at_end, pa.bool_()))):
                rows = rows.append_column(names[name], column)
            return rows

        for batch in batches:
            if not batch.num_rows:
                continue
            if part is None:
                part = batch[names["part"]][0].as_py()
            hashes, texts, news = batch[names["sha"]].to_pylist(), batch[names["text"]].to_pylist(), []
            for i, (h, t) in enumerate(zip(hashes, texts, strict=True)):
                if sha is None or h != sha or t != text and normal(t) != normal(text):
                    news.append(i)
                    sha, text = h, t
            if not news:
                continue
            rows = batch.drop_columns([names["part"], names["text"]])
            if held is not None:
                yield tagged(held, [first], [False])
                first = False
            if len(news) > 1:
                n = len(news) - 1
                yield tagged(rows.take(pa.array(news[:-1])), [first] + [False] * (n - 1), [False] * n)
                first = False
            held = rows.take(pa.array(news[-1:]))
        if held is not None:
            yield tagged(held, [first], [True])

    return run


def keep_first_copies(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """The first row (by id, nulls last) of each group of equal normalised texts.  Rows themselves are sorted,
    so ids may repeat or be null: each row stays or goes by its own text."""
    parts = max(int(docs.sparkSession.conf.get("spark.sql.shuffle.partitions")), 1)
    names = {x: unused(f"__{x}", docs.columns) for x in ("head", "sha", "key", "part", "text", "at_start", "at_end", "before")}
    head, sha, key, part, text, at_start, at_end, before = names.values()
    norm = normalised(F.col(text_col))
    dealt = docs.withColumns({head: F.substring(norm, 1, HEAD), sha: F.sha2(norm, 256), key: F.coalesce(F.col(id_col).cast("long"), F.lit(_LAST))})
    dealt = dealt.repartitionByRange(parts, head, sha, key).sortWithinPartitions(head, sha, key)
    rows = dealt.select(*docs.columns, sha, F.spark_partition_id().alias(part), F.col(text_col).cast("string").alias(text))
    schema = StructType([*docs.schema.fields, StructField(sha, StringType()), StructField(part, IntegerType()), StructField(at_start, BooleanType()), StructField(at_end, BooleanType())])
    # Written once: both uses below must see the same splitters.
    firsts = cut(rows.mapInArrow(_firsts(re.compile(WHITE), names), schema))
    # A partition's first run goes on from the one before where that ends with the same text.
    ends = firsts.where(F.col(at_start) | F.col(at_end)).select(part, at_start, at_end, sha)  # two short rows for each partition at most
    line = Window.orderBy(part)
    previous = ends.where(at_end).select(F.lead(part).over(line).alias(part), F.col(sha).alias(before))
    goes_on = ends.where(at_start).join(previous, part).where(F.col(sha) == F.col(before)).select(part, F.lit(True).alias(at_start))
    return firsts.join(F.broadcast(goes_on), [part, at_start], "left_anti").select(*docs.columns)


def op6_exact_dedup(spark, sf_dir: str) -> DataFrame:
    """The exact-copies contract on ``documents``."""
    return exact_duplicates(spark.read.parquet(f"{sf_dir}/documents.parquet"))


OP6_SQL = r"""
WITH n AS (SELECT doc_id, regexp_replace(coalesce(text, ''), '[\x20\x09-\x0D]+', ' ', 'g') AS t FROM documents)
SELECT doc_id, CAST(min(doc_id) OVER (PARTITION BY t) AS BIGINT) AS keep_id,
       CAST(count(*) OVER (PARTITION BY t) AS BIGINT) AS group_size,
       doc_id = min(doc_id) OVER (PARTITION BY t) AS kept, sha256(t) AS text_sha256
FROM n
"""
