"""Non-negative matrix factorisation with a pair of matrices as the fixpoint value."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from deltafold.session import cut


def nmf(entries: DataFrame, rank: int = 2, rounds: int = 5, seed: int = 0) -> tuple[DataFrame, DataFrame]:
    """Factors (i, k, w) and (j, k, h) of sparse entries (i, j, v) by multiplicative updates.  Products with
    the sparse matrix are joins on its indices; the small ``rank`` x ``rank`` products are aggregates."""
    start = lambda c: (F.pmod(F.xxhash64(F.col(c), F.col("k"), F.lit(seed)), F.lit(1000)) + 1) / 1000.0
    ks = F.explode(F.sequence(F.lit(0), F.lit(rank - 1))).alias("k")
    w = cut(entries.select("i").distinct().select("i", ks).withColumn("w", start("i")))
    h = cut(entries.select("j").distinct().select("j", ks).withColumn("h", start("j")))

    def gram(df: DataFrame, index: str, value: str) -> DataFrame:
        other = df.select(index, F.col("k").alias("k2"), F.col(value).alias("v2"))
        return df.join(other, index).groupBy("k", "k2").agg(F.sum(F.col(value) * F.col("v2")).alias("g"))

    def update(this: DataFrame, index: str, value: str, other: DataFrame, o_index: str, o_value: str) -> DataFrame:
        top = entries.join(other, o_index).groupBy(index, "k").agg(F.sum(F.col("v") * F.col(o_value)).alias("top"))
        low = this.withColumnRenamed("k", "k2").withColumnRenamed(value, "x").join(F.broadcast(gram(other, o_index, o_value)), "k2").groupBy(index, "k").agg(F.sum(F.col("x") * F.col("g")).alias("low"))  # rank x rank rows
        return cut(this.join(top, [index, "k"]).join(low, [index, "k"]).select(index, "k", (F.col(value) * F.col("top") / (F.col("low") + 1e-9)).alias(value)))

    for _ in range(rounds):
        h = update(h, "j", "h", w, "i", "w")
        w = update(w, "i", "w", h, "j", "h")
    return w, h


def squared_error(entries: DataFrame, w: DataFrame, h: DataFrame) -> float:
    guess = entries.join(w, "i").join(h, ["j", "k"]).groupBy("i", "j", "v").agg(F.sum(F.col("w") * F.col("h")).alias("x"))
    return guess.agg(F.sum((F.col("v") - F.col("x")) ** 2)).first()[0] or 0.0
