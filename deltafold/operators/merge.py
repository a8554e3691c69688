"""Operators on keyed collections: merging, diminishing, diffusion, replacement, and near keys.

A keyed frame has unique key columns; ``kinds`` names the merge kind of each value column."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from deltafold.functions.monoids import ADD, SUPPORT, Kind


def _binary(kind: Kind, a: Column, b: Column) -> Column:
    known = {"add": lambda: a + b, "least": lambda: F.least(a, b), "greatest": lambda: F.greatest(a, b), "times": lambda: a * b, "xor": lambda: a.bitwiseXOR(b), "any": lambda: a | b, "all": lambda: a & b, "bag": lambda: F.concat(a, b), "replace": lambda: F.greatest(a, b)}
    return F.when(a.isNull(), b).when(b.isNull(), a).otherwise(known[kind.name]())


def merge_states(x: DataFrame, y: DataFrame, keys: list[str], kinds: dict[str, Kind], how: str = "union") -> DataFrame:
    """Matched keys merged, the others kept.  ``union``: one aggregation over both, which leaves a partitioned
    ``x`` where it is; ``join``: a full outer join (null keys do not match there, so it is an ablation)."""
    if how == "union":
        return x.select(*keys, *kinds).unionByName(y.select(*keys, *kinds)).groupBy(*keys).agg(*(k.agg(F.col(c)).alias(c) for c, k in kinds.items()))
    a, b = x.select(*keys, *kinds), y.select(*keys, *(F.col(c).alias(f"__y_{c}") for c in kinds))
    return a.join(b, keys, "full_outer").select(*keys, *(_binary(k, F.col(c), F.col(f"__y_{c}")).alias(c) for c, k in kinds.items()))


def diminish(x: DataFrame, y: DataFrame, keys: list[str], kinds: dict[str, Kind]) -> DataFrame:
    """``x`` without what ``y`` merged into it.  A row goes when its support count is zero, never because its
    values are; ``kinds`` has the support count among its columns."""
    for c, k in kinds.items():
        if k.undo is None:
            raise ValueError(f"{c}: {k.name} cannot be undone")
    b = y.select(*(F.col(k).alias(f"__b_{k}") for k in keys), *(F.col(c).alias(f"__y_{c}") for c in kinds))
    same = reduce(lambda p, q: p & q, [F.col(k).eqNullSafe(F.col(f"__b_{k}")) for k in keys])
    joined = x.select(*keys, *kinds).join(b, same, "left")
    out = joined.select(*keys, *(F.when(F.col(f"__y_{c}").isNull(), F.col(c)).otherwise(k.undo(F.col(c), F.col(f"__y_{c}"))).alias(c) for c, k in kinds.items()))
    return out.where(F.col(SUPPORT) != 0) if SUPPORT in kinds else out


def diffuse(t: DataFrame, d: DataFrame, keys: list[str], kinds: dict[str, Kind]) -> DataFrame:
    """The keys of ``d`` only, their values merged with those in ``t``: what a small change touches."""
    b = t.select(*keys, *(F.col(c).alias(f"__t_{c}") for c in kinds))
    return d.select(*keys, *kinds).join(b, keys, "left").select(*keys, *(_binary(k, F.col(c), F.col(f"__t_{c}")).alias(c) for c, k in kinds.items()))


def replace(t: DataFrame, d: DataFrame, keys: list[str]) -> DataFrame:
    """``t`` with the rows of ``d`` in place of those with the same keys."""
    return t.join(d.select(*keys), keys, "left_anti").unionByName(d.select(*t.columns))


def near_join(t: DataFrame, d: DataFrame, dims: list[str], eps: float, t_id: str = "t_id", d_id: str = "d_id") -> DataFrame:
    """Pairs (d_id, t_id) that are each other's nearest within ``eps``: approximate equality of points is not
    transitive, so only mutual nearest pairs match.  Cells of width eps and their neighbours make it an equi-join."""
    cell = lambda c: F.floor(F.col(c) / eps).cast("long")
    left = d.select(F.col(d_id).alias("d_id"), *(F.col(c).alias(f"d_{c}") for c in dims), *(cell(c).alias(f"c_{c}") for c in dims))
    for c in dims:
        left = left.withColumn(f"c_{c}", F.explode(F.array(*(F.col(f"c_{c}") + o for o in (-1, 0, 1)))))
    right = t.select(F.col(t_id).alias("t_id"), *(F.col(c).alias(f"t_{c}") for c in dims), *(cell(c).alias(f"c_{c}") for c in dims))
    dist = F.sqrt(reduce(lambda a, b: a + b, [(F.col(f"d_{c}") - F.col(f"t_{c}")) ** 2 for c in dims]))
    near = left.join(right, [f"c_{c}" for c in dims]).withColumn("dist", dist).where(F.col("dist") <= eps).select("d_id", "t_id", "dist")
    of_d = near.groupBy("d_id").agg(F.min(F.struct("dist", "t_id")).alias("m")).select("d_id", F.col("m.t_id").alias("t_id"))
    of_t = near.groupBy("t_id").agg(F.min(F.struct("dist", "d_id")).alias("m")).select(F.col("m.d_id").alias("d_id"), "t_id")
    return of_d.intersect(of_t)


def co_group(left: DataFrame, right: DataFrame, keys: list[str]) -> DataFrame:
    """For each key of either side, both bags as arrays (empty where a side has none).  For keys of bounded
    groups; joins do not build bags."""
    bag = lambda df, name: df.groupBy(*keys).agg(F.collect_list(F.struct(*[c for c in df.columns if c not in keys])).alias(name))
    out = bag(left, "left_bag").join(bag(right, "right_bag"), keys, "full_outer")
    return out.select(*keys, *(F.coalesce(c, F.array()).alias(c) for c in ("left_bag", "right_bag")))


def ungroup(grouped: DataFrame, keys: list[str], bag: str) -> DataFrame:
    return grouped.select(*keys, F.inline(bag))


__all__ = ["ADD", "co_group", "diffuse", "diminish", "merge_states", "near_join", "replace", "ungroup"]
