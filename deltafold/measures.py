"""Measures of incremental runs."""

from __future__ import annotations

import time
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from deltafold.plans.algebra import Term
from deltafold.plans.incremental import IncrementalQuery, recompute


def timed(f: Callable[[], object]) -> float:
    began = time.perf_counter()
    f()
    return time.perf_counter() - began


def diff_count(a: DataFrame, b: DataFrame) -> int:
    """Rows that one has and the other has not."""
    b = b.select(*a.columns)
    return a.exceptAll(b).count() + b.exceptAll(a).count()


def drift(seconds: list[float]) -> float:
    """Slope of the time of a batch against its number."""
    n = len(seconds)
    mean = (n - 1) / 2
    return sum((i - mean) * s for i, s in enumerate(seconds)) / max(1e-9, sum((i - mean) ** 2 for i in range(n)))


def speedup(incremental: list[float], whole: list[float]) -> float:
    """Median ratio of recomputing to folding in."""
    ratios = sorted(w / i for i, w in zip(incremental, whole, strict=True))
    return ratios[len(ratios) // 2]


def shuffle_bytes(spark: SparkSession) -> int:
    """Bytes that all executors have written to shuffles since the session began."""
    executors = spark.sparkContext._jsc.sc().statusStore().executorList(False)
    return sum(executors.apply(i).totalShuffleWrite() for i in range(executors.size()))


def state_bytes(q: IncrementalQuery) -> int:
    """Catalyst's estimate of the size of all cells' states."""
    return sum(int(c.backend.read()._jdf.queryExecution().optimizedPlan().stats().sizeInBytes()) for c in q.cells)


def compare(spark: SparkSession, query: Term, batches: list[dict[str, DataFrame]], schemas: dict[str, list[str]], static=None, **options) -> dict:
    """Of every batch: seconds and shuffled bytes, incremental and recomputed on all rows so far; rows that differ at
    the end, and the state's rows, answer rows and bytes."""
    q = IncrementalQuery(spark, query, schemas, static, **options)
    rows, so_far = [], {}
    sink = lambda df: df.write.format("noop").mode("overwrite").save()
    for n, b in enumerate(batches):
        before = shuffle_bytes(spark)
        fold = timed(lambda b=b: q.step(b))
        answer = timed(lambda: sink(q.answer()))
        between = shuffle_bytes(spark)
        so_far = {n: df if n not in so_far else so_far[n].unionByName(df) for n, df in b.items()}
        whole = timed(lambda: sink(recompute(query, {**(static or {}), **so_far})))
        rows.append({"batch": n, "fold": fold, "answer": answer, "incremental": fold + answer, "recompute": whole, "shuffled": between - before, "shuffled_recompute": shuffle_bytes(spark) - between})
    folded, whole = [r["incremental"] for r in rows], [r["recompute"] for r in rows]
    last = recompute(query, {**(static or {}), **so_far})
    out = {"batches": rows, "incremental": folded, "recompute": whole, "speedup": speedup(folded[1:], whole[1:]), "drift": drift(folded[1:]), "differing_rows": diff_count(q.answer(), last), "state_rows": q.state_stats(), "answer_rows": last.count(), "state_bytes": state_bytes(q)}
    q.close()
    return out


def sweep(run: Callable[[int], dict], sizes: list[int]) -> list[dict]:
    """One run from an empty state for each increment size: seconds of each batch, speed-up and drift."""
    out = []
    for size in sizes:
        r = run(size)
        out.append({"increment": size, **{k: r[k] for k in ("incremental", "recompute", "speedup", "drift", "differing_rows") if k in r}})
    return out


def persisted(spark: SparkSession) -> int:
    """Frames and tables held in executors now (for leaks over batches)."""
    return spark.sparkContext._jsc.getPersistentRDDs().size()


def exchanges(df: DataFrame) -> int:
    """Shuffles that a plan does, without those that made what it finds in memory, and reused ones."""
    n, hidden = 0, None
    for line in df._jdf.queryExecution().executedPlan().toString().splitlines():
        depth = len(line) - len(line.lstrip(" :+-*()0123456789"))
        if hidden is not None and depth > hidden:
            continue
        hidden = depth if "InMemoryRelation" in line else None
        n += "Exchange " in line and "Reused" not in line and "Broadcast" not in line
    return n


def purity(rows: DataFrame, cluster: str, label: str) -> float:
    """Share of rows whose label is the most common one of their cluster."""
    counts = rows.groupBy(cluster, label).count().groupBy(cluster).agg(F.max("count").alias("top"), F.sum("count").alias("n"))
    return counts.agg(F.sum("top") / F.sum("n")).first()[0]


def rank_gap(a: DataFrame, b: DataFrame) -> float:
    """Summed difference of ranks, relative to their sum."""
    both = a.withColumnRenamed("rank", "ra").join(b.withColumnRenamed("rank", "rb"), "node", "full_outer")
    r = both.agg(F.sum(F.abs(F.coalesce("ra", F.lit(0.0)) - F.coalesce("rb", F.lit(0.0)))).alias("d"), F.sum("ra").alias("s")).first()
    return r["d"] / r["s"]
