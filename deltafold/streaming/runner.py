"""Structured Streaming around incremental queries."""

from __future__ import annotations

import uuid

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupStateTimeout

from deltafold.functions.monoids import SIGN
from deltafold.plans.incremental import IncrementalQuery, appended
from deltafold.session import checkpoint_folder, cut


def dir_stream(spark: SparkSession, path: str, schema, fmt: str = "parquet", files_per_batch: int | None = 1, sign: int | None = None) -> DataFrame:
    """Files of a directory: those there first, then new ones.  A file is read once by its path; one that is
    changed later is not read again.  ``sign`` marks a directory of inserts (1) or of deletions (-1)."""
    reader = spark.readStream.schema(schema).format(fmt)
    if files_per_batch:
        reader = reader.option("maxFilesPerTrigger", files_per_batch)
    df = reader.load(path)
    return df if sign is None else df.withColumn(SIGN, F.lit(sign))


def socket_stream(spark: SparkSession, host: str, port: int, schema: str, fmt: str = "json") -> DataFrame:
    """Lines of a socket parsed as JSON, CSV or XML records."""
    lines = spark.readStream.format("socket").option("host", host).option("port", port).load()
    parse = {"json": lambda: F.from_json("value", schema), "csv": lambda: F.from_csv("value", schema), "xml": lambda: F.from_xml("value", schema)}[fmt]
    return lines.select(parse().alias("r")).select("r.*")


class StreamRunner:
    """One query over one or several streams: they are tagged and stacked, so that a micro-batch holds a batch
    of each and has one id.

    The batch id is the version of the state.  A batch that is replayed after a restart (its offsets were not
    yet committed) is folded only if its version does not count, and its output is written anew to the same
    place, so that both are exact once.  For that the query needs a ``folder``.

    ``emit``: ``complete`` puts out the whole answer after each batch; ``update`` the answer's rows whose group the
    batch touches; ``append`` the batch's own rows, for queries that append (no state is kept or needed)."""

    def __init__(self, query: IncrementalQuery, out: str | None = None, emit: str = "complete"):
        if emit not in ("complete", "update", "append"):
            raise ValueError(emit)
        if emit == "append":
            appended(query.query)
        self.query, self.out, self.emit = query, out, emit

    def _batch(self, df: DataFrame, batch_id: int, schemas: dict[str, list[str]]) -> None:
        df = df.persist()
        tables = {name: df.where(F.col("__stream") == name).select(SIGN, f"r_{name}.*").select(*columns, SIGN) for name, columns in schemas.items()}
        if self.emit == "append":
            rows = self.query.append_only(tables)
        else:
            self.query.step(tables, version=batch_id)
            rows = self.query.touched(tables) if self.emit == "update" else self.query.answer()
        if self.out and (self.emit == "append" or self.query.version == batch_id):
            rows.write.mode("overwrite").parquet(f"{self.out}/batch={batch_id}")
        df.unpersist()

    def run(self, streams: dict[str, DataFrame], checkpoint: str, trigger: dict | None = None) -> None:
        """Runs until all that is available has been read (or ``trigger`` ends it)."""
        stacked, schemas = None, {}
        for name, df in streams.items():
            schemas[name] = [c for c in df.columns if c != SIGN]
            sign = F.col(SIGN) if SIGN in df.columns else F.lit(1)
            one = df.select(F.lit(name).alias("__stream"), sign.cast("int").alias(SIGN), F.struct(*schemas[name]).alias(f"r_{name}"))
            stacked = one if stacked is None else stacked.unionByName(one, allowMissingColumns=True)
        writer = stacked.writeStream.option("checkpointLocation", checkpoint).trigger(**(trigger or {"availableNow": True}))
        writer.foreachBatch(lambda df, i: self._batch(df, i, schemas)).start().awaitTermination()


def as_files(spark: SparkSession, batches: list[DataFrame], columns: list[str]) -> str:
    """Batches as one file each in a fresh directory, in order of arrival (replay of a stream)."""
    folder = f"{checkpoint_folder(spark)}/arrivals-{uuid.uuid4().hex}"
    for b in batches:
        b.select(*columns).coalesce(1).write.mode("append").parquet(folder)
    return folder


def _to_table(stream: DataFrame, spark: SparkSession, mode: str) -> list[DataFrame]:
    """What each micro-batch puts out, written to the shared folder."""
    folder, out = checkpoint_folder(spark), []
    stream.writeStream.outputMode(mode).option("checkpointLocation", f"{folder}/native-{uuid.uuid4().hex}").trigger(availableNow=True).foreachBatch(lambda df, i: out.append(cut(df))).start().awaitTermination()
    return out


def native_aggregate(spark: SparkSession, stream: DataFrame, keys: list[str], aggregates: list) -> DataFrame:
    """Spark's own streaming aggregation, as a comparator: the last complete result."""
    return _to_table(stream.groupBy(*keys).agg(*aggregates), spark, "complete")[-1]


def deduplicated(spark: SparkSession, stream: DataFrame, keys: list[str], ts: str | None = None, delay: str | None = None) -> DataFrame:
    """First row of each key; with a delay, keys older than the watermark are forgotten."""
    once = stream.withWatermark(ts, delay).dropDuplicatesWithinWatermark(keys) if delay else stream.dropDuplicates(keys)
    parts = _to_table(once, spark, "append")
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out


def keyed_average(spark: SparkSession, stream: DataFrame, key: str, value: str) -> DataFrame:
    """In-place state for each key (sum and count), which touches only a batch's keys: the last (key, s, n) of
    each key."""

    def update(k, frames, state):
        s, n = state.get if state.exists else (0, 0)
        for f in frames:
            s, n = s + int(f[value].sum()), n + len(f)
        state.update((s, n))
        yield pd.DataFrame({"key": [k[0]], "s": [s], "n": [n]})

    rows = stream.select(key, value).groupBy(key).applyInPandasWithState(update, "key long, s long, n long", "s long, n long", "update", GroupStateTimeout.NoTimeout)
    parts = _to_table(rows, spark, "update")
    out = None
    for i, p in enumerate(parts):
        p = p.withColumn("version", F.lit(i))
        out = p if out is None else out.unionByName(p)
    return out.groupBy("key").agg(F.max(F.struct("version", "s", "n")).alias("m")).select("key", "m.s", "m.n")
