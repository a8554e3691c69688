"""Synthetic inputs of the experiments."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def _unit(column, salt: int):
    """A uniform number in [0, 1) that depends on the row and salt only."""
    return F.pmod(F.xxhash64(column, F.lit(salt)), F.lit(1 << 40)) / float(1 << 40)


def random_pairs(spark: SparkSession, rows: int, limit: int = 10_000, seed: int = 0, start: int = 0) -> DataFrame:
    """(id, x, y) with whole x and y below ``limit``."""
    ids = spark.range(start, start + rows)
    return ids.select("id", *(F.floor(_unit(F.col("id"), 2 * seed + s) * limit).cast("long").alias(c) for s, c in enumerate("xy")))


def square_points(spark: SparkSession, rows: int, half_width: float = 1.0, seed: int = 0, start: int = 0) -> DataFrame:
    """(id, x, y) uniform in four squares centred on (3,3), (3,7), (7,3) and (7,7)."""
    ids = spark.range(start, start + rows)
    centre = lambda bit: F.when(F.col("id").bitwiseAND(bit) == 0, 3.0).otherwise(7.0)
    return ids.select("id", (centre(1) + (2 * _unit(F.col("id"), 100 + seed) - 1) * half_width).alias("x"), (centre(2) + (2 * _unit(F.col("id"), 200 + seed) - 1) * half_width).alias("y"))


def rmat_edges(spark: SparkSession, edges: int, nodes: int, a: float = 0.30, b: float = 0.25, c: float = 0.25, seed: int = 0, first_node: int = 0, with_id: bool = False) -> DataFrame:
    """Recursive-matrix edges (src, dst) over ``nodes`` nodes; the fourth quadrant has the rest of the probability."""
    levels = max(1, (nodes - 1).bit_length())
    rows = spark.range(edges)
    src, dst = F.lit(0).cast("long"), F.lit(0).cast("long")
    for level in range(levels):
        u = _unit(F.col("id"), 1000 * (seed + 1) + level)
        src = src * 2 + F.when(u < a + b, 0).otherwise(1)
        dst = dst * 2 + F.when((u < a) | ((u >= a + b) & (u < a + b + c)), 0).otherwise(1)
    return rows.select(*(["id"] if with_id else []), (F.pmod(src, F.lit(nodes)) + first_node).alias("src"), (F.pmod(dst, F.lit(nodes)) + first_node).alias("dst"))
