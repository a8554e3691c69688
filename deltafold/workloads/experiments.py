"""The reference's evaluation: four queries, an initial input and nine increments of each of four sizes, every batch
beside recomputing on all data so far.  Each run begins with an empty state."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from deltafold.functions import monoids as m
from deltafold.measures import compare, drift, speedup, sweep, timed
from deltafold.operators.kmeans import IncrementalKMeans, kmeans
from deltafold.operators.pagerank import IncrementalPageRank, pagerank
from deltafold.plans.algebra import stream
from deltafold.session import cut
from deltafold.sources.generators import random_pairs, square_points

INCREMENTS = 9
#: Sizes of the increments (tuples), and of the graph's (edges for 100 new nodes).
SIZES, EDGES = (10_000, 20_000, 30_000, 40_000), (100, 200, 300, 400)


def _parts(df: DataFrame, key: str, initial: int, increment: int) -> list[DataFrame]:
    cuts = [0, *(initial + n * increment for n in range(INCREMENTS + 1))]
    return [df.where(f"{key} >= {a} AND {key} < {b}") for a, b in zip(cuts[:-1], cuts[1:], strict=True)]


def group_by(spark: SparkSession, increment: int, initial: int = 1_000_000) -> dict:
    """Average by key over random pairs."""
    rows = cut(random_pairs(spark, initial + INCREMENTS * increment))
    batches = [{"s": p.select("x", "y")} for p in _parts(rows, "id", initial, increment)]
    return compare(spark, stream("s").group_by("x").agg(mean=m.avg("y"), n=m.count()), batches, {"s": ["x", "y"]})


def join_group_by(spark: SparkSession, increment: int, initial: int = 100_000) -> dict:
    """Average over a join of two streams of random pairs (several partners on both sides; both sides are kept)."""
    a = cut(random_pairs(spark, initial + INCREMENTS * increment, seed=1)).selectExpr("id", "x AS a", "y AS b")
    b = cut(random_pairs(spark, initial + INCREMENTS * increment, seed=2)).selectExpr("id", "x AS c", "y AS d")
    batches = [{"l": x.select("a", "b"), "r": y.select("c", "d")} for x, y in zip(_parts(a, "id", initial, increment), _parts(b, "id", initial, increment), strict=True)]
    return compare(spark, stream("l").join(stream("r"), {"b": "c"}).group_by("a").agg(mean=m.avg("d"), n=m.count()), batches, {"l": ["a", "b"], "r": ["c", "d"]})


def pairs_found(spark: SparkSession, initial: int = 100_000, increment: int = 10_000) -> tuple[int, int]:
    """Join pairs of ``join_group_by``'s input that come together in one batch, and all pairs."""
    a = cut(random_pairs(spark, initial + INCREMENTS * increment, seed=1)).selectExpr("id", "y AS b")
    b = cut(random_pairs(spark, initial + INCREMENTS * increment, seed=2)).selectExpr("id", "x AS c")
    batch = f"IF(id < {initial}, 0, 1 + (id - {initial}) div {increment})"
    return tuple(count_pairs(a.selectExpr("b AS k", f"{batch} AS n"), b.selectExpr("c AS k", f"{batch} AS n")).first())


def count_pairs(left: DataFrame, right: DataFrame) -> DataFrame:
    """One row (batchwise, exact): the pairs of rows (k, n) with equal keys k that have one batch n, and all such pairs."""
    count = lambda df, *keys: df.groupBy(*keys).agg(F.count("*").alias("c"))

    def pairs(name, *keys):
        met = count(left, *keys).withColumnRenamed("c", "a").join(count(right, *keys).withColumnRenamed("c", "b"), list(keys))
        return met.agg(F.coalesce(F.sum(F.col("a") * F.col("b")), F.lit(0)).alias(name))

    return pairs("batchwise", "k", "n").crossJoin(pairs("exact", "k"))


def clusters(spark: SparkSession, increment: int, initial: int = 1_000_000, rounds: int = 10) -> dict:
    """K-means in four squares."""
    whole = cut(square_points(spark, initial + INCREMENTS * increment))
    init = [(2.0, 2.0), (2.0, 8.0), (8.0, 2.0), (8.0, 8.0)]
    q, folded, again = IncrementalKMeans(spark, ["x", "y"], init, rounds), [], []
    for n, part in enumerate(_parts(whole, "id", initial, increment)):
        folded.append(timed(lambda part=part: q.step(part)))
        again.append(timed(lambda n=n: kmeans(whole.where(f"id < {initial + n * increment}"), ["x", "y"], init, rounds)))
    return {"incremental": folded, "recompute": again, "speedup": speedup(folded[1:], again[1:]), "drift": drift(folded[1:])}


def ranks(spark: SparkSession, edges: int, initial: int = 50_000, nodes: int = 5_000, rounds: int = 10) -> dict:
    """PageRank of a recursive-matrix graph."""
    from deltafold.workloads.iterative import grown_graph

    q, folded, again, whole = IncrementalPageRank(spark, rounds), [], [], None
    for new in grown_graph(spark, initial, nodes, [(100, edges)] * INCREMENTS):
        folded.append(timed(lambda new=new: q.step(new)))
        whole = new if whole is None else whole.unionByName(new)
        again.append(timed(lambda: pagerank(whole, rounds)))
    return {"incremental": folded, "recompute": again, "speedup": speedup(folded[1:], again[1:]), "drift": drift(folded[1:])}


def evaluation(spark: SparkSession) -> dict[str, list[dict]]:
    """All curves."""
    return {f.__name__: sweep(lambda size, f=f: f(spark, size), list(sizes)) for f, sizes in ((group_by, SIZES), (join_group_by, SIZES), (clusters, SIZES), (ranks, EDGES))}


def backends(spark: SparkSession, increment: int = 10_000, initial: int = 200_000) -> dict[str, dict]:
    """The same group-by on every state backend, and each batch's seconds."""
    rows = cut(random_pairs(spark, initial + INCREMENTS * increment))
    batches = [{"s": p.select("x", "y")} for p in _parts(rows, "id", initial, increment)]
    query = stream("s").group_by("x").agg(mean=m.avg("y"), n=m.count())
    return {b: compare(spark, query, batches, {"s": ["x", "y"]}, backend=b) for b in ("memory", "layered", "bucketed", "keyed")}


__all__ = ["backends", "clusters", "count_pairs", "evaluation", "group_by", "join_group_by", "pairs_found", "ranks"]
