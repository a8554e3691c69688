"""A hand-written incremental join aggregate: three delta joins maintain the result."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


class DeltaJoin:
    """Sum and count of v by k over (j, k) joined with (j, v).  Each batch adds new-left with old-right,
    old-left with new-right and new with new, so only affected keys are touched; signs multiply."""

    def __init__(self, spark: SparkSession, partitions: int | None = None, cut_every: int = 8):
        self.spark, self.cut_every, self.batches = spark, cut_every, 0
        self.partitions = partitions or int(spark.conf.get("spark.sql.shuffle.partitions"))
        self.left = self.right = self.result = None

    def step(self, left: DataFrame, right: DataFrame, sign: int = 1) -> None:
        dl = left.groupBy("j", "k").agg((F.count("*") * sign).alias("w")).repartition(self.partitions, "j")
        dr = right.groupBy("j").agg((F.sum("v") * sign).alias("s"), (F.count("*") * sign).alias("n")).repartition(self.partitions, "j")
        pairs = dl.join(dr, "j")
        if self.left is not None:
            pairs = pairs.unionByName(dl.join(self.right, "j")).unionByName(self.left.join(dr, "j"))
        change = pairs.groupBy("k").agg(F.sum(F.col("w") * F.col("s")).alias("s"), F.sum(F.col("w") * F.col("n")).alias("n")).repartition(self.partitions, "k")
        fold = lambda old, new, keys: new if old is None else old.unionByName(new).groupBy(*keys).agg(*(F.sum(c).alias(c) for c in new.columns if c not in keys))
        before = [self.left, self.right, self.result]
        now = [fold(self.left, dl, ["j", "k"]), fold(self.right, dr, ["j"]), fold(self.result, change, ["k"])]
        self.batches += 1
        if self.batches % self.cut_every == 0:
            from deltafold.session import cut

            now = [cut(x).repartition(self.partitions, c) for x, c in zip(now, "jjk", strict=True)]
        self.result, self.left, self.right = now[2].persist(), now[0].persist(), now[1].persist()
        for x in (self.result, self.left, self.right):
            x.count()
        for x in before:
            if x is not None:
                x.unpersist()

    def answer(self) -> DataFrame:
        return self.result.where("n <> 0")

    def close(self) -> None:
        for x in (self.left, self.right, self.result):
            if x is not None:
                x.unpersist()
