"""Batch readers, and the deterministic arrival of a table's rows in batches."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import IntegerType, StructField, StructType

from deltafold.session import checkpoint_folder

FORMATS = ("parquet", "orc", "csv", "json", "xml", "text", "binaryFile")
BATCHES = 10


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def read(spark: SparkSession, path: str, fmt: str = "parquet", schema: str | None = None, **options) -> DataFrame:
    """A file or directory in any format Spark reads; a schema avoids inference."""
    reader = spark.read.format(fmt).options(**options)
    return (reader.schema(schema) if schema else reader).load(path)


def arrivals(df: DataFrame, batch, n: int = BATCHES) -> list[DataFrame]:
    """The rows of each batch (a column of numbers below ``n``), written once by batch, so that a batch reads its own
    files and no others."""
    folder = f"{checkpoint_folder(df.sparkSession)}/arrivals-{uuid.uuid4().hex}"
    name = "__batch"
    df.withColumn(name, batch.cast("int")).write.partitionBy(name).parquet(folder)
    there = df.sparkSession.read.schema(StructType([*df.schema.fields, StructField(name, IntegerType())])).parquet(folder)
    return [there.where(F.col(name) == i).drop(name) for i in range(n)]


def arrive_by_key(df: DataFrame, key: str, width: int = 2) -> list[DataFrame]:
    """Batch 0 and nine increments of ``width`` percent of it; rows of one key arrive together."""
    m = 100 + 9 * width
    r = F.pmod(F.col(key), F.lit(m))
    return arrivals(df, F.when(r < 100, 0).otherwise(1 + F.floor((r - 100) / width)))


def arrive_by_time(df: DataFrame, ts: str, bounds: list | None = None) -> list[DataFrame]:
    """Ten batches by time, so that partners in another table arrive apart.  Bounds are approximate deciles; rows
    without a time come first."""
    t = F.unix_micros(F.col(ts).cast("timestamp"))
    if bounds is None:
        bounds = df.select(t.alias("t")).approxQuantile("t", [i / BATCHES for i in range(1, BATCHES)], 0.001)
    batch = F.lit(0)
    for b in bounds:
        batch = batch + F.when(t > b, 1).otherwise(0)
    return arrivals(df, batch)
