"""Partial results, their merging, and finishing: the physical side of one aggregate.

A state is a frame with lineage columns ``__k0, __k1, ...``, one column ``p<i>_<part>`` for each part, and the
number of rows that support it, ``__n``.  A state of value multiplicities has the value as its last lineage
column, ``__value``, and only ``__n``.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from deltafold.functions.monoids import ADD, SIGN, SUPPORT, Kind, Monoid, leaves, outer

VALUE = "__value"


@dataclass(frozen=True)
class Group:
    """Monoids that share one state; a monoid over values has a state of its own."""

    monoids: tuple[tuple[int, Monoid], ...]  # place among the aggregate's subterms, monoid
    plain: tuple[tuple[str, Kind], ...] = ()  # further columns that merge by themselves

    @property
    def values(self) -> str | None:
        return self.monoids[0][1].values if self.monoids else None

    def parts(self) -> list[tuple[str, Kind]]:
        return [(f"p{i}_{name}", kind) for i, m in self.monoids for name, kind, _ in m.parts] + [*self.plain, (SUPPORT, ADD)]


def state_groups(aggregate, deletes: bool = False) -> list[Group]:
    """The states an aggregate needs.  With deletions, what cannot be undone is kept as multiplicities."""
    monoids = [m for _, ex in aggregate.aggregates for m in leaves(ex)]
    if deletes:
        monoids = [m.deletable_as() if not m.invertible and m.deletable_as else m for m in monoids]
        for m in monoids:
            if not m.invertible:
                raise ValueError(f"{m.label} cannot be undone")
    plain = tuple((i, m) for i, m in enumerate(monoids) if m.values is None)
    return [Group(plain)] + [Group(((i, m),)) for i, m in enumerate(monoids) if m.values is not None]


def lineage_columns(df_columns: list[str]) -> list[str]:
    return [c for c in df_columns if c.startswith("__k") or c == VALUE]


def partial(df: DataFrame, n_keys: int, group: Group) -> DataFrame:
    """Signed rows with lineage columns to a state.  Values that are null are no values."""
    keys = [c for c in df.columns if c.startswith("__k") and c[3:].isdigit()]
    if group.values is not None:
        df = df.withColumn(VALUE, F.expr(group.values)).where(F.col(VALUE).isNotNull())
        return df.groupBy(*keys, VALUE).agg(F.sum(F.col(SIGN).cast("long")).alias(SUPPORT))
    columns = [kind.agg(lift()).alias(f"p{i}_{name}") for i, m in group.monoids for name, kind, lift in m.parts]
    return df.groupBy(*keys).agg(*columns, F.sum(F.col(SIGN).cast("long")).alias(SUPPORT))


def merged(state: DataFrame, group: Group) -> DataFrame:
    """Rows of one lineage as one row (the merge of any number of states after their union)."""
    keys = lineage_columns(state.columns)
    return state.groupBy(*keys).agg(*(kind.agg(F.col(c)).alias(c) for c, kind in group.parts()))


def reduced(state: DataFrame, n_keys: int, group: Group) -> DataFrame:
    """A state of longer lineage summed up to its first ``n_keys`` keys (and value)."""
    keys = [f"__k{i}" for i in range(n_keys)] + ([VALUE] if group.values is not None else [])
    return state.groupBy(*keys).agg(*(kind.agg(F.col(c)).alias(c) for c, kind in group.parts()))


def finish(states: list[DataFrame], aggregate, groups: list[Group] | None = None) -> DataFrame:
    """The aggregate's result from its states, which are merged and have its keys as lineage."""
    groups = groups or state_groups(aggregate)
    keys = [f"__k{i}" for i in range(len(aggregate.keys))]
    base, results = states[0], {}
    if keys:
        base = base.where(F.col(SUPPORT) > 0)
    else:
        base = base.withColumn(SUPPORT, F.coalesce(F.col(SUPPORT), F.lit(0)))
        base = base.withColumns({c: F.coalesce(F.col(c), F.lit(0)) for c, k in groups[0].parts() if k is ADD})
    for i, m in groups[0].monoids:
        results[i] = m.finish({name: F.col(f"p{i}_{name}") for name, _, _ in m.parts})
    for state, group in zip(states[1:], groups[1:], strict=True):
        i, m = group.monoids[0]
        there = state.where(F.col(SUPPORT) > 0)
        one = there.groupBy(*keys).agg(m.over_values(F.col(VALUE), F.col(SUPPORT)).alias(f"r{i}"))
        if keys:
            one = one.select(*(F.col(k).alias(f"{k}_r{i}") for k in keys), f"r{i}")
            same = F.lit(True)
            for k in keys:
                same = same & F.col(k).eqNullSafe(F.col(f"{k}_r{i}"))
            base = base.join(one, same, "left").drop(*(f"{k}_r{i}" for k in keys))
        else:
            base = base.crossJoin(F.broadcast(one))  # one row each
        results[i] = F.coalesce(F.col(f"r{i}"), F.lit(0)) if m.label == "count_distinct" else F.col(f"r{i}")
    left = [results[i] for i in sorted(results)]
    columns = [F.col(k).alias(name) for k, (name, _) in zip(keys, aggregate.keys, strict=True)]
    for name, ex in aggregate.aggregates:
        columns.append(outer(ex, left).alias(name))
    return base.select(*columns)
