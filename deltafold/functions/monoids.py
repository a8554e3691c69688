"""Merge operations of states, as column sets.

An aggregate keeps *parts*; a part has a value for one row (``lift``) and a *kind* that both sums up rows and
merges states, so one ``groupBy().agg()`` does either.  Rows carry a sign (+1 inserted, -1 deleted); parts of
an invertible kind are lifted times the sign, so a deletion is one more merge.
"""

from __future__ import annotations

import functools
import inspect
from collections.abc import Callable
from dataclasses import dataclass, field, replace

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

SIGN, SUPPORT = "__sign", "__n"


@dataclass(frozen=True)
class Kind:
    """A commutative monoid on one column."""

    name: str
    agg: Callable[[Column], Column]
    invertible: bool = False
    idempotent: bool = False
    undo: Callable[[Column, Column], Column] | None = None


ADD = Kind("add", F.sum, invertible=True, undo=lambda a, b: a - b)
LEAST = Kind("least", F.min, idempotent=True)
GREATEST = Kind("greatest", F.max, idempotent=True)
TIMES = Kind("times", F.product)
XOR = Kind("xor", F.bit_xor, invertible=True, undo=lambda a, b: a.bitwiseXOR(b))
ANY = Kind("any", F.bool_or, idempotent=True)
ALL = Kind("all", F.bool_and, idempotent=True)
BIT_OR = Kind("bit_or", F.bit_or, idempotent=True)
BIT_AND = Kind("bit_and", F.bit_and, idempotent=True)
BAG = Kind("bag", lambda c: F.flatten(F.collect_list(c)))
SKETCH = Kind("sketch", lambda c: F.hll_union_agg(c), idempotent=True)
#: Equal in state and batch, or an error: the one side of a one-to-many join.
SAME = Kind("same", lambda c: F.when(F.min(c) == F.max(c), F.min(c)).when(F.count(c) == 0, F.lit(None)).otherwise(F.raise_error(F.lit("invariant part differs between state and batch"))), idempotent=True)
#: The newest value wins; values are structs that begin with a version.
REPLACE = Kind("replace", F.max, idempotent=True)
KINDS = {k.name: k for k in (ADD, LEAST, GREATEST, TIMES, XOR, ANY, ALL, BIT_OR, BIT_AND, BAG, SKETCH, SAME, REPLACE)}


def _signed(value: Column) -> Column:
    return value * F.col(SIGN)


@dataclass(frozen=True)
class Monoid:
    """An aggregate: its parts by name (kind, lifted value) and how to finish them."""

    label: str
    parts: tuple[tuple[str, Kind, Callable[[], Column]], ...]
    finish: Callable[[dict[str, Column]], Column]
    #: Aggregates over the multiplicities of values; such a state has the value in its lineage.
    values: str | None = None
    over_values: Callable[[Column, Column], Column] | None = field(default=None)
    deletable_as: Callable[[], Monoid] | None = field(default=None)
    #: The expressions that ``lift`` reads, as text.
    reads: tuple[str, ...] = ()

    @property
    def invertible(self) -> bool:
        return self.values is not None or all(k.invertible for _, k, _ in self.parts)

    @property
    def idempotent(self) -> bool:
        return bool(self.parts) and all(k.idempotent for _, k, _ in self.parts)

    def describe(self) -> str:
        return f"multiplicities of {self.values}" if self.values else " x ".join(k.name for _, k, _ in self.parts)


def product(*monoids: Monoid) -> str:
    """The component-wise merge of several aggregates, as text."""
    return " x ".join(m.describe() for m in monoids)


def _reading(*names: str):
    """Notes which of a constructor's arguments are expressions."""

    def deco(make):
        order = list(inspect.signature(make).parameters)

        @functools.wraps(make)
        def made(*args, **options):
            given = dict(zip(order, args, strict=False)) | options
            texts = tuple(given[n] for n in names if given.get(n) is not None)
            out = make(*args, **options)
            again = out.deletable_as and (lambda: replace(out.deletable_as(), reads=texts))
            return replace(out, reads=texts, deletable_as=again)

        return made

    return deco


def _present(x: str) -> Callable[[], Column]:
    return lambda: F.when(F.expr(x).isNotNull(), F.col(SIGN)).otherwise(F.lit(0)).cast("long")


@_reading("x")
def count(x: str | None = None) -> Monoid:
    lift = _present(x) if x else lambda: F.col(SIGN).cast("long")
    return Monoid("count", (("n", ADD, lift),), lambda p: p["n"])


@_reading("condition")
def count_if(condition: str) -> Monoid:
    return Monoid("count_if", (("n", ADD, lambda: F.when(F.expr(condition), F.col(SIGN)).otherwise(F.lit(0)).cast("long")),), lambda p: p["n"])


@_reading("x")
def sum_(x: str, empty_zero: bool = False) -> Monoid:
    parts = (("s", ADD, lambda: _signed(F.coalesce(F.expr(x), F.lit(0)))), ("n", ADD, _present(x)))
    return Monoid("sum", parts, lambda p: F.coalesce(p["s"], F.lit(0)) if empty_zero else F.when(p["n"] != 0, p["s"]))


@_reading("x")
def avg(x: str) -> Monoid:
    parts = (("s", ADD, lambda: _signed(F.coalesce(F.expr(x), F.lit(0)))), ("n", ADD, _present(x)))
    return Monoid("avg", parts, lambda p: F.when(p["n"] != 0, p["s"].cast("double") / p["n"]))


@_reading("x")
def product_(x: str) -> Monoid:
    """Zeros are counted apart, so the others' product keeps its value (and logs need no care)."""
    parts = (("p", TIMES, lambda: F.when(F.expr(x) != 0, F.pow(F.expr(x).cast("double"), F.col(SIGN))).otherwise(F.lit(1.0))), ("z", ADD, lambda: F.when(F.expr(x) == 0, F.col(SIGN)).otherwise(F.lit(0)).cast("long")))
    return Monoid("product", parts, lambda p: F.when(p["z"] > 0, F.lit(0.0)).otherwise(p["p"]))


@_reading("x")
def min_(x: str) -> Monoid:
    return Monoid("min", (("v", LEAST, lambda: F.expr(x)),), lambda p: p["v"], deletable_as=lambda: over_values("min", x, lambda v, n: F.min(v)))


@_reading("x")
def max_(x: str) -> Monoid:
    return Monoid("max", (("v", GREATEST, lambda: F.expr(x)),), lambda p: p["v"], deletable_as=lambda: over_values("max", x, lambda v, n: F.max(v)))


def _flags(x: str) -> tuple:
    yes = lambda: F.when(F.expr(x), F.col(SIGN)).otherwise(F.lit(0)).cast("long")
    no = lambda: F.when(~F.expr(x), F.col(SIGN)).otherwise(F.lit(0)).cast("long")
    return (("t", ADD, yes), ("f", ADD, no))


@_reading("x")
def every(x: str) -> Monoid:
    return Monoid("every", _flags(x), lambda p: F.when(p["t"] + p["f"] > 0, p["f"] == 0))


@_reading("x")
def some(x: str) -> Monoid:
    return Monoid("some", _flags(x), lambda p: F.when(p["t"] + p["f"] > 0, p["t"] > 0))


def _moments(*pairs: tuple[str, str]) -> tuple:
    """Exact sums of products in decimals; rows with a null factor are left out."""
    both = " AND ".join(sorted({f"({x}) IS NOT NULL" for p in pairs for x in p}))
    part = lambda a, b: lambda: F.when(F.expr(both), F.expr(f"CAST(({a}) AS DECIMAL(18,0)) * CAST(({b}) AS DECIMAL(18,0))") * F.col(SIGN)).otherwise(F.lit(0)).cast("decimal(38,0)")
    return (*((f"m{i}", ADD, part(a, b)) for i, (a, b) in enumerate(pairs)), ("n", ADD, lambda: F.when(F.expr(both), F.col(SIGN)).otherwise(F.lit(0)).cast("long")))


@_reading("x")
def variance(x: str, population: bool = False, root: bool = False) -> Monoid:
    """Of whole numbers: n, sum and sum of squares are exact, so merging and deleting are."""

    def finish(p):
        n, s, ss = p["n"].cast("double"), p["m0"].cast("double"), p["m1"].cast("double")
        v = F.when(p["n"] > (0 if population else 1), (ss - s * s / n) / (n if population else n - 1))
        return F.sqrt(v) if root else v

    return Monoid("variance", _moments((x, "1"), (x, x)), finish)


@_reading("x", "y")
def covariance(x: str, y: str, what: str = "covar_samp") -> Monoid:
    """Sample or population covariance, correlation, or the slope of y on x."""

    def finish(p):
        n, sx, sy, sxy, sxx, syy = (p[c].cast("double") for c in ("n", "m0", "m1", "m2", "m3", "m4"))
        c, vx, vy = sxy - sx * sy / n, sxx - sx * sx / n, syy - sy * sy / n
        return {"covar_samp": F.when(p["n"] > 1, c / (n - 1)), "covar_pop": F.when(p["n"] > 0, c / n), "corr": F.when((vx > 0) & (vy > 0), c / F.sqrt(vx * vy)), "slope": F.when(vx > 0, c / vx)}[what]

    return Monoid(what, _moments((x, "1"), (y, "1"), (x, y), (x, x), (y, y)), finish)


@_reading("x")
def bit_xor(x: str) -> Monoid:
    return Monoid("bit_xor", (("x", XOR, lambda: F.when(F.col(SIGN) % 2 != 0, F.coalesce(F.expr(x), F.lit(0))).otherwise(F.lit(0)).cast("long")),), lambda p: p["x"])


@_reading("x")
def bits(x: str, want: str) -> Monoid:
    """bit_and or bit_or of all 64 bits; with deletions, from counts of set bits."""
    kind = {"and": BIT_AND, "or": BIT_OR}[want]
    return Monoid(f"bit_{want}", (("v", kind, lambda: F.expr(f"CAST(({x}) AS BIGINT)")),), lambda p: p["v"], deletable_as=lambda: _bit_counts(x, want))


def _bit_counts(x: str, want: str) -> Monoid:
    bit = lambda i: F.coalesce(F.expr(f"(CAST(({x}) AS BIGINT) >> {i}) & 1"), F.lit(0)).cast("long")
    parts = tuple((f"b{i}", ADD, lambda i=i: _signed(bit(i))) for i in range(64))
    full = lambda p, i: p[f"b{i}"] == p["n"] if want == "and" else p[f"b{i}"] > 0

    def finish(p):
        out = F.lit(0).cast("long")
        for i in range(64):
            out = out.bitwiseOR(F.when(full(p, i), F.lit(1 << i if i < 63 else -(1 << 63))).otherwise(F.lit(0)).cast("long"))
        return F.when(p["n"] > 0, out)

    return Monoid(f"bit_{want}", (*parts, ("n", ADD, _present(x))), finish)


@_reading("value", "order")
def by_order(value: str, order: str, newest: bool = True) -> Monoid:
    """The value at the greatest (or least) order; ties go to the greater (less) value."""
    kind = GREATEST if newest else LEAST
    pick = F.max if newest else F.min
    again = lambda: over_values("by_order", f"struct(({order}) AS o, ({value}) AS v)", lambda v, n: pick(v)["v"])
    return Monoid("by_order", (("v", kind, lambda: F.expr(f"struct(({order}) AS o, ({value}) AS v)")),), lambda p: p["v"]["v"], deletable_as=again)


@_reading("x")
def top_k(x: str, k: int) -> Monoid:
    """The k greatest values, as a bounded list."""
    trim = Kind(f"top{k}", lambda c: F.slice(F.sort_array(F.flatten(F.collect_list(c)), asc=False), 1, k))
    return Monoid("top_k", (("v", trim, lambda: F.expr(f"filter(array_repeat({x}, CAST(least({SIGN}, {k}) AS INT)), e -> e IS NOT NULL)")),), lambda p: p["v"], deletable_as=lambda: over_values("top_k", x, lambda v, n: F.slice(F.sort_array(F.flatten(F.collect_list(F.expr("array_repeat(__value, CAST(__n AS INT))"))), asc=False), 1, k)))


@_reading("x")
def bag(x: str) -> Monoid:
    """All values, in order of value (the order of arrival is no part of a bag)."""
    return over_values("bag", x, lambda v, n: F.sort_array(F.flatten(F.collect_list(F.expr("array_repeat(__value, CAST(__n AS INT))")))))


@_reading("x", "order")
def string_agg(x: str, order: str, separator: str = ",") -> Monoid:
    """Strings joined in order; the append monoid, kept as a bag and ordered in the answer."""
    rows = F.expr("array_repeat(__value, CAST(__n AS INT))")
    return over_values("string_agg", f"struct(({order}) AS o, ({x}) AS v)", lambda v, n: F.array_join(F.transform(F.sort_array(F.flatten(F.collect_list(rows))), lambda e: e["v"].cast("string")), separator))


@_reading("x")
def approx_distinct(x: str) -> Monoid:
    """An estimate by a sketch; opt-in, not exact, inserts only."""
    return Monoid("approx_distinct", (("h", Kind("sketch_of_values", F.hll_union_agg), lambda: F.expr(x)),), lambda p: F.hll_sketch_estimate(p["h"]))


def over_values(label: str, value: str, aggregate: Callable[[Column, Column], Column]) -> Monoid:
    """An aggregate of a multiset, whose state maps each value to its multiplicity."""
    return Monoid(label, (), lambda p: p["r"], values=value, over_values=aggregate)


@_reading("x")
def count_distinct(x: str) -> Monoid:
    return over_values("count_distinct", x, lambda v, n: F.count(v))


@_reading("x")
def sum_distinct(x: str) -> Monoid:
    return over_values("sum_distinct", x, lambda v, n: F.sum(v))


@_reading("x")
def collect_set(x: str) -> Monoid:
    return over_values("collect_set", x, lambda v, n: F.sort_array(F.collect_set(v)))


@_reading("x")
def mode(x: str) -> Monoid:
    """The most frequent value; the least of several."""
    return over_values("mode", x, lambda v, n: F.min(F.struct(-n, v))["__value"])


@_reading("x")
def percentile(x: str, at: float) -> Monoid:
    """The discrete percentile: the least value with at least that share of the rows at or below it."""
    walk = f"""
      aggregate(array_sort(collect_list(struct(__value AS v, __n AS n))),
        named_struct('left', CAST(ceil({at} * sum(__n)) AS BIGINT), 'got', CAST(NULL AS DOUBLE)),
        (a, e) -> named_struct('left', a.left - e.n, 'got', CASE WHEN a.got IS NULL AND a.left - e.n <= 0 THEN CAST(e.v AS DOUBLE) ELSE a.got END),
        a -> a.got)"""
    return over_values("percentile", x, lambda v, n: F.expr(walk))


@_reading("x")
def histogram(x: str, low: float, high: float, buckets: int) -> Monoid:
    """Rows in each of equal buckets from ``low`` to ``high``, the first and last of which are open to the outside;
    an array."""
    width = (high - low) / buckets
    at = f"CAST(greatest(0, least({buckets - 1}, floor((({x}) - {low}) / {width}))) AS INT)"
    parts = tuple((f"b{i}", ADD, lambda i=i: F.when(F.expr(at) == i, F.col(SIGN)).otherwise(F.lit(0)).cast("long")) for i in range(buckets))
    return Monoid("histogram", parts, lambda p: F.array(*(p[f"b{i}"] for i in range(buckets))))


@_reading("x")
def invariant(x: str) -> Monoid:
    """A value that is the same in all rows of a group, in state and batch, or an error."""
    return Monoid("invariant", (("v", SAME, lambda: F.expr(x)),), lambda p: p["v"], deletable_as=lambda: over_values("invariant", x, lambda v, n: SAME.agg(v)))


# ------------------------------------------------------------------ expressions over aggregates


class Ex:
    """An expression over aggregates, e.g. ``Agg(sum_("x")) / Agg(count())``."""

    def _two(self, other, op):
        return Op(op, (self, other if isinstance(other, Ex) else Const(other)))

    def __add__(self, o):
        return self._two(o, "+")

    def __sub__(self, o):
        return self._two(o, "-")

    def __mul__(self, o):
        return self._two(o, "*")

    def __truediv__(self, o):
        return self._two(o, "/")


@dataclass(frozen=True)
class Agg(Ex):
    monoid: Monoid


@dataclass(frozen=True)
class Const(Ex):
    value: object


@dataclass(frozen=True)
class Op(Ex):
    op: str
    args: tuple


def as_ex(x) -> Ex:
    return x if isinstance(x, Ex) else Agg(x)


def leaves(ex: Ex) -> list[Monoid]:
    """The largest subterms that merge, left to right."""
    if isinstance(ex, Agg):
        return [ex.monoid]
    return [m for a in ex.args for m in leaves(a)] if isinstance(ex, Op) else []


def outer(ex: Ex, results: list[Column]) -> Column:
    """The rest of the expression, over the subterms' results (consumed left to right)."""
    if isinstance(ex, Agg):
        return results.pop(0)
    if isinstance(ex, Const):
        return F.lit(ex.value)
    a, b = (outer(x, results) for x in ex.args)
    return {"+": lambda: a + b, "-": lambda: a - b, "*": lambda: a * b, "/": lambda: a / b}[ex.op]()


def check_monoid(rows: DataFrame, monoid: Monoid, split_by: str) -> bool:
    """Whether merging the states of two halves gives the state of the whole, on given rows."""
    rows = rows.withColumn(SIGN, F.lit(1))
    names = [f"p{i}" for i in range(len(monoid.parts))]
    state = lambda df: df.agg(*(k.agg(lift()).alias(c) for c, (_, k, lift) in zip(names, monoid.parts, strict=True)))
    merged = state(rows.where(split_by)).unionByName(state(rows.where(f"NOT ({split_by})"))).agg(*(k.agg(F.col(c)).alias(c) for c, (_, k, _) in zip(names, monoid.parts, strict=True)))
    done = lambda df: df.select(monoid.finish({p: F.col(c) for c, (p, _, _) in zip(names, monoid.parts, strict=True)})).first()[0]
    return done(merged) == done(state(rows))
