"""Terms of the query algebra, and their direct (batch) evaluation.

A term is declared once; ``evaluate`` runs it on whole tables (the baseline), ``plans.compiler`` turns the same
term into state and answer.
"""

from __future__ import annotations

import re
from collections.abc import Callable
from dataclasses import dataclass, field, replace

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from deltafold.functions.monoids import SIGN, Ex, as_ex, leaves, outer

#: Functions whose value changes when a batch is replayed, and those among them that need no brackets.
_UNSTABLE = re.compile(r"\b(?:(?:rand|randn|random|uuid|now|curdate|monotonically_increasing_id|spark_partition_id|input_file_name|shuffle)\s*\(|(?:current_timestamp|current_date|current_time|localtimestamp|current_user)\b)", re.IGNORECASE)
_QUOTED = re.compile(r"'(?:[^'\\]|\\.|'')*'|\"(?:[^\"\\]|\\.)*\"|`[^`]*`")


class Unsupported(ValueError):
    """A term outside the supported class; the message says why."""


class Term:
    """Base of all terms, with the builder methods."""

    def flat_map(self, where: str | None = None, explode: tuple[str, str] | None = None, **columns: str) -> Term:
        return FlatMap(self, where, explode, tuple(columns.items()))

    def where(self, condition: str) -> Term:
        return FlatMap(self, condition, None, ())

    def select(self, **columns: str) -> Term:
        return FlatMap(self, None, None, tuple(columns.items()))

    def join(self, other: Term, on: dict[str, str], kind: str = "inner", mode: str | None = None) -> Term:
        return Join(self, other, tuple(on.items()), kind, mode)

    def group_by(self, *names: str, **keys: str) -> Grouped:
        return Grouped(self, tuple((n, n) for n in names) + tuple(keys.items()))

    def agg(self, **aggregates) -> Term:
        return Aggregate(self, (), tuple((k, as_ex(v)) for k, v in aggregates.items()))

    def distinct(self) -> Term:
        return Distinct(self)

    def order_by(self, *order: str, limit: int | None = None) -> Term:
        return OrderBy(self, order, limit)

    def union(self, other: Term) -> Term:
        return Union((self, other))

    def co_group(self, other: Term, on: dict[str, str]) -> Term:
        return CoGroup(self, other, tuple(on.items()))

    def then(self, f: Callable[[DataFrame], DataFrame], columns: list[str], label: str = "then") -> Term:
        """A frame function of the whole result (windows, pivots, ...), which stays in the answer."""
        return Then(self, f, tuple(columns), label)

    def nested(self, sub: Term, on: dict[str, str], kind: str = "exists", condition: str | None = None, **value) -> Term:
        """Rows for which a correlated subquery holds: ``exists``, ``not_exists``, or ``scalar`` with an aggregate
        of the subquery's rows under a name that ``condition`` uses.  ``on``: own column -> subquery's."""
        (name, aggregate), = value.items() or [(None, None)]
        return Nested(self, sub, tuple(on.items()), kind, condition, name, None if aggregate is None else as_ex(aggregate))

    def grouping_sets(self, sets: list[list[str]], columns: list[str], gid: str = "gid") -> Term:
        """Each row once for every grouping set, with the columns that a set leaves out as null and a number that
        tells the sets apart (a bit for each column, set where it is left out)."""
        cells = []
        for kept in sets:
            number = sum(1 << (len(columns) - 1 - i) for i, c in enumerate(columns) if c not in kept)
            parts = ", ".join(f"'{c}', {c if c in kept else f'IF(false, {c}, NULL)'}" for c in columns)
            cells.append(f"named_struct('{gid}', CAST({number} AS BIGINT), {parts})")
        return FlatMap(self, None, ("__set", f"array({', '.join(cells)})"), tuple((c, f"__set.{c}") for c in (*columns, gid)))

    @property
    def children(self) -> tuple[Term, ...]:
        return ()


@dataclass(frozen=True)
class Source(Term):
    """A named table: a stream, or invariant data."""

    name: str
    streaming: bool = True


@dataclass(frozen=True)
class Values(Term):
    """Literal rows (a bag of records); no rows need a schema."""

    rows: tuple
    schema: str


@dataclass(frozen=True)
class FlatMap(Term):
    """Filter, unnest one array, and project: one pass without a shuffle."""

    src: Term
    condition: str | None
    explode: tuple[str, str] | None
    columns: tuple[tuple[str, str], ...]

    @property
    def children(self):
        return (self.src,)


@dataclass(frozen=True)
class Join(Term):
    """Equi-join, i.e. a co-group whose groups are consumed pairwise."""

    left: Term
    right: Term
    on: tuple[tuple[str, str], ...]
    kind: str = "inner"
    mode: str | None = None  # invariant, co_arrival or retained; None: invariant if one side is, else retained

    @property
    def children(self):
        return (self.left, self.right)


@dataclass(frozen=True)
class CoGroup(Term):
    """For each key of either side both bags, as arrays ``left_bag`` and ``right_bag``; for groups of bounded size."""

    left: Term
    right: Term
    on: tuple[tuple[str, str], ...]

    @property
    def children(self):
        return (self.left, self.right)


@dataclass(frozen=True)
class Then(Term):
    src: Term
    f: Callable[[DataFrame], DataFrame] = field(compare=False)
    columns: tuple[str, ...]
    label: str = "then"

    @property
    def children(self):
        return (self.src,)


@dataclass(frozen=True)
class Nested(Term):
    """A correlated subquery in a filter; ``plans.unnest`` turns it into joins."""

    src: Term
    sub: Term
    on: tuple[tuple[str, str], ...]
    kind: str
    condition: str | None
    name: str | None
    value: Ex | None
    #: What an empty group's sum is: zero (True), SQL's null (False), or as the way of unnesting has it.
    zero: bool | None = None

    @property
    def children(self):
        return (self.src, self.sub)


@dataclass(frozen=True)
class Grouped:
    src: Term
    keys: tuple[tuple[str, str], ...]

    def agg(self, **aggregates) -> Aggregate:
        return Aggregate(self.src, self.keys, tuple((k, as_ex(v)) for k, v in aggregates.items()))


@dataclass(frozen=True)
class Aggregate(Term):
    """Group-by with aggregates; without keys a total aggregation."""

    src: Term
    keys: tuple[tuple[str, str], ...]
    aggregates: tuple[tuple[str, Ex], ...]

    @property
    def children(self):
        return (self.src,)


@dataclass(frozen=True)
class Distinct(Term):
    src: Term

    @property
    def children(self):
        return (self.src,)


@dataclass(frozen=True)
class OrderBy(Term):
    src: Term
    order: tuple[str, ...]
    limit: int | None = None

    @property
    def children(self):
        return (self.src,)


@dataclass(frozen=True)
class Union(Term):
    parts: tuple[Term, ...]

    @property
    def children(self):
        return self.parts


@dataclass(frozen=True)
class Cell(Term):
    """A reference to a state; stands where a subterm was cut out."""

    number: int
    of: Term = field(compare=False)


def stream(name: str) -> Source:
    return Source(name, True)


def static(name: str) -> Source:
    return Source(name, False)


def values(rows, schema: str) -> Values:
    return Values(tuple(tuple(r) for r in rows), schema)


def empty(schema: str) -> Values:
    return Values((), schema)


def walk(t: Term):
    yield t
    for c in t.children:
        yield from walk(c)


def sources(t: Term) -> list[Source]:
    return [x for x in walk(t) if isinstance(x, Source)]


def is_streaming(t: Term) -> bool:
    return any(s.streaming for s in sources(t))


def rebuild(t: Term, children: list[Term]) -> Term:
    if isinstance(t, (Join, CoGroup)):
        return replace(t, left=children[0], right=children[1])
    if isinstance(t, Nested):
        return replace(t, src=children[0], sub=children[1])
    if isinstance(t, Union):
        return replace(t, parts=tuple(children))
    return replace(t, src=children[0]) if children else t


def check_term(t: Term) -> None:
    """Refuses what cannot be made incremental: joins of two streams without equal keys, and functions whose
    value changes when a batch is replayed."""
    for x in walk(t):
        if isinstance(x, Join):
            if not x.on and is_streaming(x.left) and is_streaming(x.right):
                raise Unsupported("a join of two streams needs equal keys")
            if x.mode == "invariant" and is_streaming(x.left) and is_streaming(x.right):
                raise Unsupported("mode invariant needs a side that is no stream")
        texts = [x.condition, *(e for _, e in x.columns), (x.explode or (None, None))[1]] if isinstance(x, FlatMap) else [e for _, e in x.keys] + [r for _, ex in x.aggregates for m in leaves(ex) for r in m.reads] if isinstance(x, Aggregate) else [x.condition] if isinstance(x, Nested) else []
        for text in texts:
            if text and _UNSTABLE.search(_QUOTED.sub("''", text)):
                raise Unsupported(f"not the same on replay: {text}")


def explain_support(t: Term) -> tuple[bool, str]:
    try:
        check_term(t)
    except Unsupported as why:
        return False, str(why)
    return True, "supported"


# ------------------------------------------------------------------ batch evaluation


def expanded(df: DataFrame) -> DataFrame:
    """Rows that carry a multiplicity as that many rows; a heavy row in steps, so that no array is long."""
    if SIGN not in df.columns:
        return df
    step = 10_000
    lots = df.where(F.col(SIGN) > 0).withColumn("__lot", F.explode(F.expr(f"sequence(0L, (CAST({SIGN} AS BIGINT) - 1) div {step})")))
    size = F.least(F.lit(step).cast("long"), F.col(SIGN) - F.col("__lot") * step).cast("int")
    return lots.withColumn("__copy", F.explode(F.array_repeat(F.lit(0), size))).drop("__lot", "__copy", SIGN)


def apply_flat_map(df: DataFrame, t: FlatMap) -> DataFrame:
    """One flat-map on a frame; the sign column passes through."""
    if t.condition:
        df = df.where(t.condition)
    if t.explode:
        name, array = t.explode
        df = df.withColumn(name, F.explode(F.expr(array)))
    if t.columns:
        keep = [SIGN] if SIGN in df.columns else []
        df = df.select(*(F.expr(e).alias(n) for n, e in t.columns), *keep)
    return df


def apply_join(left: DataFrame, right: DataFrame, t: Join) -> DataFrame:
    """The join; the signs of two signed sides multiply.  Where partners arrive and leave together, two deleted rows
    are a deleted pair, and a row that comes has nothing to do with one that goes in the same batch."""
    signed = [SIGN in left.columns, SIGN in right.columns]
    left = left.withColumnRenamed(SIGN, "__sl") if signed[0] else left
    right = right.withColumnRenamed(SIGN, "__sr") if signed[1] else right
    condition = F.lit(True)
    for a, b in t.on:
        condition = condition & (left[a] == right[b])
    out = left.crossJoin(right) if not t.on else left.join(right, condition, t.kind)
    if t.kind in ("left_semi", "left_anti"):
        return out.withColumnRenamed("__sl", SIGN) if signed[0] else out
    if any(signed):
        sign = F.lit(1)
        for name, there in zip(("__sl", "__sr"), signed, strict=True):
            sign = sign * F.coalesce(F.col(name), F.lit(1)) if there else sign
        if all(signed) and t.mode == "co_arrival":
            out = out.where("__sl * __sr > 0")
            sign = F.abs(sign) * F.signum("__sl")
        out = out.withColumn(SIGN, sign.cast("long")).drop("__sl", "__sr")
    return out


def apply_aggregate(df: DataFrame, t: Aggregate) -> DataFrame:
    """Group and finish in one step, for rows with or without signs."""
    from deltafold.plans.partial import finish, partial

    df = df if SIGN in df.columns else df.withColumn(SIGN, F.lit(1))
    df = df.select("*", *(F.expr(e).alias(f"__k{i}") for i, (_, e) in enumerate(t.keys)))
    return finish([partial(df, len(t.keys), m) for m in _cells(t)], t)


def _cells(t: Aggregate):
    from deltafold.plans.partial import state_groups

    return state_groups(t)


def evaluate(t: Term, tables: dict[str, DataFrame], cells: dict[int, DataFrame] | None = None) -> DataFrame:
    """The term on whole tables (and on the frames that stand for its cells)."""
    go = lambda x: evaluate(x, tables, cells)
    if isinstance(t, Source):
        return tables[t.name]
    if isinstance(t, Cell):
        return cells[t.number]
    if isinstance(t, Values):
        spark = next(iter({**tables, **(cells or {})}.values())).sparkSession
        return spark.createDataFrame(list(t.rows), t.schema)
    if isinstance(t, FlatMap):
        return apply_flat_map(go(t.src), t)
    if isinstance(t, Join):
        return apply_join(go(t.left), go(t.right), t)
    if isinstance(t, Aggregate):
        return apply_aggregate(go(t.src), t)
    if isinstance(t, Distinct):
        return go(t.src).drop(SIGN).distinct()
    if isinstance(t, Union):
        parts = [go(p) for p in t.parts]
        if any(SIGN in p.columns for p in parts):
            parts = [p if SIGN in p.columns else p.withColumn(SIGN, F.lit(1)) for p in parts]
        out = parts[0]
        for p in parts[1:]:
            out = out.unionByName(p)
        return out
    if isinstance(t, Then):
        return t.f(expanded(go(t.src)))
    if isinstance(t, CoGroup):
        from deltafold.operators.merge import co_group

        right = expanded(go(t.right))
        for a, b in t.on:
            right = right.withColumnRenamed(b, a)
        return co_group(expanded(go(t.left)), right, [a for a, _ in t.on])
    if isinstance(t, Nested):
        from deltafold.plans.unnest import unnest

        return go(unnest(t))
    if isinstance(t, OrderBy):
        out = expanded(go(t.src)).orderBy(*(F.expr(o[:-5]).desc() if o.lower().endswith(" desc") else F.expr(o).asc() for o in t.order))
        return out.limit(t.limit) if t.limit is not None else out
    raise Unsupported(type(t).__name__)


__all__ = ["Aggregate", "Cell", "CoGroup", "Distinct", "Nested", "Then", "expanded", "FlatMap", "Join", "OrderBy", "Source", "Term", "Union", "Unsupported", "Values", "apply_aggregate", "apply_flat_map", "apply_join", "check_term", "empty", "evaluate", "explain_support", "is_streaming", "leaves", "outer", "rebuild", "sources", "static", "stream", "values", "walk"]
