"""PageRank: batch, and incremental by a frontier of nodes whose in-neighbours moved."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from deltafold.operators.merge import merge_states
from deltafold.functions.monoids import ADD
from deltafold.session import cut

#: Out-links that one row may hold where a round is a single group-by; graphs with larger hubs use joins.
MOST_LINKS = 100_000


def _nodes(edges: DataFrame) -> DataFrame:
    return edges.select(F.col("src").alias("node")).union(edges.select("dst")).distinct()


def pagerank(edges: DataFrame, rounds: int = 10, damping: float = 0.85, cut_every: int = 4, how: str = "auto", dangling: str = "drop") -> DataFrame:
    """(node, rank) after a number of rounds from rank 1 for every node.

    ``how="group"``: a node's row carries its out-links, and a round is one group-by in which it receives shares and
    keeps its links, in place of a join of ranks with edges.  ``"join"``: links stay put and ranks are joined to them,
    for graphs with hubs of more than ``MOST_LINKS`` out-links; ``auto`` looks at the largest.  Rank of nodes without
    out-links is dropped, or with ``dangling="redistribute"`` shared by all."""
    edges = edges.select("src", "dst").persist()
    degree = edges.groupBy("src").agg(F.count("*").alias("deg"))
    if how == "auto":
        how = "group" if (degree.agg(F.max("deg")).first()[0] or 0) <= MOST_LINKS else "join"
    run = _by_group if how == "group" else _by_join
    ranks = cut(run(edges, degree, rounds, damping, cut_every, dangling))
    edges.unpersist()
    return ranks


def _lost(rows: DataFrame, nothing, dangling: str) -> float:
    """Rank for each node from nodes without out-links."""
    if dangling != "redistribute":
        return 0.0
    r = rows.agg(F.sum(F.when(nothing, F.col("rank")).otherwise(0.0)).alias("lost"), F.count("*").alias("n")).first()
    return (r["lost"] or 0.0) / max(1, r["n"])


def _by_group(edges: DataFrame, degree: DataFrame, rounds: int, damping: float, cut_every: int, dangling: str) -> DataFrame:
    links = edges.groupBy("src").agg(F.collect_list("dst").alias("to"))
    empty = F.array().cast(links.schema["to"].dataType)
    rows = cut(_nodes(edges).join(links, F.col("node") == F.col("src"), "left").select("node", F.coalesce("to", empty).alias("to"), F.lit(1.0).alias("rank")))
    for i in range(rounds):
        more = _lost(rows, F.size("to") == 0, dangling)
        share = (F.col("rank") / F.size("to")).alias("got")
        given = rows.select(F.explode("to").alias("node"), share).select("node", "got", empty.alias("to"))
        both = given.unionByName(rows.select("node", F.lit(0.0).alias("got"), "to"))
        rows = both.groupBy("node").agg(F.flatten(F.collect_list("to")).alias("to"), F.sum("got").alias("got")).select("node", "to", ((1 - damping) + damping * (F.col("got") + more)).alias("rank"))
        if (i + 1) % cut_every == 0 and i + 1 < rounds:
            rows = cut(rows)
    return rows.select("node", "rank")


def _by_join(edges: DataFrame, degree: DataFrame, rounds: int, damping: float, cut_every: int, dangling: str) -> DataFrame:
    links = edges.join(degree, "src").persist()
    nodes = _nodes(edges).join(degree.select(F.col("src").alias("node"), F.lit(True).alias("has")), "node", "left").persist()
    ranks = nodes.withColumn("rank", F.lit(1.0))
    for i in range(rounds):
        more = _lost(ranks, F.col("has").isNull(), dangling)
        shares = links.join(ranks, links["src"] == ranks["node"]).groupBy("dst").agg(F.sum(F.col("rank") / F.col("deg")).alias("got"))
        ranks = nodes.join(shares, nodes["node"] == shares["dst"], "left").select("node", "has", ((1 - damping) + damping * (F.coalesce("got", F.lit(0.0)) + more)).alias("rank"))
        if (i + 1) % cut_every == 0:
            ranks = cut(ranks)
    out = cut(ranks.select("node", "rank"))
    links.unpersist()
    nodes.unpersist()
    return out


def pagerank_fixed_point(edges: DataFrame, rounds: int = 3, scale: int = 10**9) -> DataFrame:
    """Ranks as whole numbers (damping 0.85), so that no order of summation matters: (node, rank)."""
    edges = edges.select("src", "dst").persist()
    links = edges.join(edges.groupBy("src").agg(F.count("*").alias("deg")), "src").persist()
    nodes = _nodes(edges).persist()
    ranks = nodes.withColumn("rank", F.lit(scale).cast("long"))
    for _ in range(rounds):
        shares = links.join(ranks, links["src"] == ranks["node"]).groupBy("dst").agg(F.sum(F.expr("rank div deg")).alias("got"))
        ranks = nodes.join(shares, nodes["node"] == shares["dst"], "left").select("node", F.expr(f"CAST({scale}L * 15 div 100 + coalesce(got, 0) * 85 div 100 AS BIGINT)").alias("rank"))
    out = cut(ranks)
    for x in (edges, links, nodes):
        x.unpersist()
    return out


class IncrementalPageRank:
    """Keeps edges, out-degrees and ranks.  A batch of edges touches their ends; every round the ranks of the
    frontier's nodes are computed anew from all their in-links (pull), and the next frontier are the targets of
    those that moved.  Ranks of nodes that no round touches stay as they were, which is the approximation.

    Edges are kept as layers, one for each batch and put together every ``compact_every`` batches; a round writes
    ranks once."""

    def __init__(self, spark, rounds: int = 10, damping: float = 0.85, tolerance: float = 0.0, compact_every: int = 8):
        self.spark, self.rounds, self.damping, self.tolerance, self.compact_every = spark, rounds, damping, tolerance, compact_every
        self.layers: list[DataFrame] = []
        self.degree = self.ranks = None
        self.touched: list[float] = []

    @property
    def edges(self) -> DataFrame:
        out = self.layers[0]
        for x in self.layers[1:]:
            out = out.unionByName(x)
        return out

    def step(self, new: DataFrame) -> DataFrame:
        new = cut(new.select("src", "dst"))
        counted = new.groupBy("src").agg(F.count("*").alias("deg"))
        if not self.layers:
            self.layers, self.degree = [new], cut(counted)
            self.ranks = pagerank(new, self.rounds, self.damping)
            return self.ranks
        self.layers.append(new)
        if len(self.layers) > self.compact_every:
            self.layers = [cut(self.edges)]
        self.degree = cut(merge_states(self.degree, counted, ["src"], {"deg": ADD}))
        edges, degree = self.edges, self.degree
        ends = _nodes(new)
        # the new links' targets, and as a source's new degree changes what all its targets get, these too
        sources = new.select(F.col("src").alias("moved")).distinct()
        frontier = edges.join(sources, edges["src"] == sources["moved"], "left_semi").select(F.col("dst").alias("node")).union(ends).distinct()
        state = self.ranks.withColumn("known", F.lit(True)).join(ends, "node", "full_outer").select("node", F.coalesce("rank", F.lit(1.0)).alias("rank"), F.lit(False).alias("moved"))
        state = cut(state)
        total = state.count()
        for i in range(self.rounds):
            links = edges.join(frontier, edges["dst"] == frontier["node"], "left_semi").join(degree, "src")
            got = links.join(state.select(F.col("node").alias("src"), "rank"), "src").groupBy(F.col("dst").alias("node")).agg(F.sum(F.col("rank") / F.col("deg")).alias("got"))
            fresh = frontier.join(got, "node", "left").select("node", ((1 - self.damping) + self.damping * F.coalesce("got", F.lit(0.0))).alias("fresh"))
            state = state.drop("moved").join(fresh, "node", "left")
            state = cut(state.select("node", F.coalesce("fresh", "rank").alias("rank"), F.coalesce(F.abs(F.col("fresh") - F.col("rank")) > self.tolerance, F.lit(False)).alias("moved"), F.col("fresh").isNotNull().alias("touched")))
            r = state.agg(F.count_if("touched").alias("t"), F.count_if("moved").alias("m")).first()
            self.touched.append(r["t"] / max(1, total))
            state = state.drop("touched")
            if not r["m"]:
                break
            moved = state.where("moved").select(F.col("node").alias("moved"))
            frontier = edges.join(moved, edges["src"] == moved["moved"], "left_semi").select(F.col("dst").alias("node")).distinct()
        self.ranks = state.select("node", "rank")
        return self.ranks
