"""Connected components by rounds of star contraction."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from deltafold.session import cut_and_free


def components(links: DataFrame) -> DataFrame:
    """(node, label) for every node of the undirected links (a, b); the label is the component's smallest node.

    Large stars point each node's larger neighbours at the smallest node it knows, small stars the node and
    its smaller ones; the rounds needed grow with the logarithm of the longest path.  Every shuffle
    pre-aggregates, edges stay a table, and only their count and a checksum reach the driver.  Null ends and
    loops are ignored; no links give an empty result."""
    edges = cut_and_free(links.where("a <> b").select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")).distinct())
    state = _sum(edges)
    while state[0]:
        both = edges.unionByName(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
        least = both.groupBy("u").agg(F.min("v").alias("m"))
        large = both.join(least, "u").where("v > u").select(F.col("v").alias("u"), F.least("u", "m").alias("v")).where("u <> v").distinct()
        low = large.groupBy("u").agg(F.min("v").alias("m"))
        small = large.join(low, "u").where("v <> m").select(F.col("v").alias("u"), F.col("m").alias("v"))
        edges = cut_and_free(small.unionByName(low.select("u", F.col("m").alias("v"))).distinct())
        before, state = state, _sum(edges)
        if before == state:
            break
    return edges.select(F.col("u").alias("node"), F.col("v").alias("label")).unionByName(edges.select(F.col("v").alias("node"), F.col("v").alias("label")).distinct())


def _sum(edges: DataFrame) -> tuple:
    return tuple(edges.agg(F.count("*"), F.bit_xor(F.xxhash64("u", "v")), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first())
