"""Running compiled queries batch by batch."""

from __future__ import annotations

import time
from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from deltafold.functions.monoids import ADD, SIGN, SUPPORT
from deltafold.plans.algebra import Aggregate, Join, Term, Unsupported, evaluate, is_streaming, sources, walk
from deltafold.plans.compiler import compile_query, signed_rows
from deltafold.plans.infer import infer
from deltafold.plans.partial import Group
from deltafold.streaming.state import BACKENDS, Files, Pointers, StateCell


@dataclass
class BatchMetrics:
    """Of one batch."""

    batch: int
    seconds: float
    state_rows: int | None = None
    answer_rows: int | None = None


#: Guard states: rows of either side of a join by key.
_SIDES = Group((), ((f"left_{SUPPORT}", ADD), (f"right_{SUPPORT}", ADD)))


class IncrementalQuery:
    """A query over streams and invariant tables: ``step`` folds a batch in, ``answer`` gives the exact result
    on everything so far.

    With a ``folder`` the state outlives the process: every cell has a folder of its own there, a batch counts
    once one pointer for all cells is written, and a query that is made with the same folder goes on after the
    last batch that counts.  A batch with a ``version`` that counts already is not folded again."""

    def __init__(self, spark: SparkSession, query: Term, schemas: dict[str, list[str]], static: dict[str, DataFrame] | None = None, *, backend: str | None = None, lineage: str = "full", deletes: bool = False, split_policy: str = "homomorphic", guard: bool = True, check_subset: bool = True, folder: str | None = None, **options):
        self.spark, self.query, self.static = spark, query, static or {}
        self.plan = compile_query(query, schemas, lineage, deletes, split_policy)
        backend = backend or ("layered" if folder else "memory")
        if folder and not BACKENDS[backend].durable:
            raise Unsupported(f"the state of backend {backend} does not outlive the process")
        self.guards = [j for j in walk(query) if isinstance(j, Join) and j.mode == "co_arrival"] if guard else []
        make = lambda name, group: BACKENDS[backend](spark, group, **options, **({"folder": f"{folder}/{name}"} if folder else {}))
        self.cells = [StateCell(c.number, make(f"cell-{c.number}", c.group)) for c in self.plan.cells]
        self.seen = [StateCell(n, make(f"guard-{n}", _SIDES)) for n in range(len(self.guards))]
        self.deletes, self.check_subset, self.version = deletes, check_subset, -1
        self.pointers = Pointers(Files(spark, folder), "committed") if folder else None
        self.metrics: list[BatchMetrics] = []
        if self.pointers:
            self.version = max(self.pointers.versions(), default=-1)
            for cell in (*self.cells, *self.seen):
                cell.backend.restore(self.version)

    @property
    def batches(self) -> int:
        return self.version + 1

    def _signed(self, insert: dict[str, DataFrame], delete: dict[str, DataFrame] | None) -> dict[str, DataFrame]:
        out = {}
        for name, df in insert.items():
            out[name] = df if SIGN in df.columns else df.withColumn(SIGN, F.lit(1))
        for name, df in (delete or {}).items():
            gone = df.withColumn(SIGN, F.lit(-1))
            out[name] = out[name].unionByName(gone) if name in out else gone
        return out

    def step(self, insert: dict[str, DataFrame], delete: dict[str, DataFrame] | None = None, version: int | None = None) -> bool:
        """Folds one batch of every stream; rows inserted and deleted in one batch cancel.  Returns whether it was
        folded: a ``version`` (a stream's batch id) that counts already is not."""
        if delete and not self.deletes:
            raise Unsupported("compile with deletes=True to delete rows")
        version = self.version + 1 if version is None else version
        if version <= self.version:
            return False
        began = time.perf_counter()
        tables = {**self.static, **self._signed(insert, delete)}
        self._guard(tables, version)
        for plan, cell in zip(self.plan.cells, self.cells, strict=True):
            cell.step(plan.partial(tables), version)
            if delete and self.check_subset:
                cell.check_support()
        if self.pointers:
            self.pointers.write(version, {"cells": len(self.cells)})
            for old in self.pointers.versions()[:-2]:
                self.pointers.drop(old)
        self.version = version
        self.metrics.append(BatchMetrics(version, time.perf_counter() - began))
        return True

    def _guard(self, tables: dict[str, DataFrame], version: int) -> None:
        """Co-arrival holds while all rows of a key come in one batch, and go in one batch; else matches would be
        lost.  The keys seen so far are a state like any other."""
        sides = (f"left_{SUPPORT}", f"right_{SUPPORT}")
        for cell, join in zip(self.seen, self.guards, strict=True):
            both = None
            for n, (side, cols) in enumerate(((join.left, [a for a, _ in join.on]), (join.right, [b for _, b in join.on]))):
                rows = signed_rows(side, tables).select(*(F.col(c).alias(f"__k{i}") for i, c in enumerate(cols)), *(F.col(SIGN).cast("long").alias(x) if i == n else F.lit(0).cast("long").alias(x) for i, x in enumerate(sides)), F.col(SIGN).alias("sign"))
                both = rows if both is None else both.unionByName(rows)
            keys = [c for c in both.columns if c.startswith("__k")]
            delta = both.where(" AND ".join(f"{k} IS NOT NULL" for k in keys)).groupBy(*keys).agg(*(F.sum(x).alias(x) for x in sides), F.count_if(F.col("sign") > 0).alias("come"), F.count_if(F.col("sign") < 0).alias("go")).persist()
            met = delta
            if cell.backend.version >= 0:
                met = met.join(cell.backend.read().select(*keys, *(F.col(x).alias(f"old_{x}") for x in sides), F.lit(True).alias("known")), keys, "left")
            else:
                met = met.withColumns({**{f"old_{x}": F.lit(0).cast("long") for x in sides}, "known": F.lit(None).cast("boolean")})
            after = [F.coalesce(F.col(f"old_{x}"), F.lit(0)) + F.col(x) for x in sides]
            alive = F.coalesce(F.col(f"old_{sides[0]}") + F.col(f"old_{sides[1]}") > 0, F.lit(False))
            wrong = met.agg(F.bool_or((F.col("come") > 0) & alive).alias("again"), F.bool_or(after[0] > 1).alias("several"), F.bool_or((F.col("go") > 0) & ((after[0] != 0) | (after[1] != 0))).alias("part")).first()
            if any(wrong):
                delta.unpersist()
                raise Unsupported("co-arrival: " + ("a key of this batch came before; use mode='retained'" if wrong["again"] else "the one side has several rows of one key" if wrong["several"] else "only a part of a key's rows is deleted; use mode='retained'"))
            cell.step(delta.select(*keys, *sides, F.lit(0).cast("long").alias(SUPPORT)), version)
            delta.unpersist()

    def answer(self) -> DataFrame:
        return self.plan.answer([c.backend.read() for c in self.cells], self.static)

    def touched(self, insert: dict[str, DataFrame], delete: dict[str, DataFrame] | None = None) -> DataFrame:
        """The answer's rows whose group a batch touches (update output).  Groups are those of the topmost
        aggregate; a join of streams below it touches the groups of all rows that share a key with the batch."""
        top = next((x for x in walk(self.plan.query) if isinstance(x, Aggregate)), None)
        if top is None or not top.keys:
            return self.answer()
        changed = {n for n, d in self._signed(insert, delete).items()}
        tables = {**self.static, **self._signed(insert, delete)}
        join = next((x for x in walk(top.src) if isinstance(x, Join) and is_streaming(x.left) and is_streaming(x.right) and x.mode != "co_arrival"), None)
        if join is None and all(s.name in changed for s in sources(top.src) if s.streaming) and not any(isinstance(x, Aggregate) for x in walk(top.src)):
            keys = signed_rows(top.src, tables).select(*(F.expr(e).alias(n) for n, e in top.keys)).distinct()
            return self.answer().join(keys, keys.columns, "left_semi")
        pushed = self.plan.pushed_sides.get(top)
        if pushed is None:
            return self.answer()  # groups cannot be told from the batch alone
        left, right = pushed
        nk, names = len(join.on), [n for n, _ in top.keys]
        near = signed_rows(join.right, tables).select(*(F.col(b).alias(f"__k{i}") for i, (_, b) in enumerate(join.on))).distinct()
        known = self.cells[left].backend.read()
        groups = known.join(near, [f"__k{i}" for i in range(nk)], "left_semi").select(*(F.col(f"__k{nk + i}").alias(n) for i, n in enumerate(names)))
        own = self.plan.cells[left].partial(tables).select(*(F.col(f"__k{nk + i}").alias(n) for i, n in enumerate(names)))
        keys = groups.unionByName(own).distinct()
        return self.answer().join(keys, names, "left_semi")

    def append_only(self, insert: dict[str, DataFrame]) -> DataFrame:
        """The batch's own rows of a query that appends; no state."""
        return evaluate(self.query, {**self.static, **{n: d.drop(SIGN) for n, d in insert.items()}})

    def state_stats(self) -> list[tuple[int, int]]:
        return [(c.number, c.backend.read().count()) for c in self.cells]

    def explain(self) -> str:
        return self.plan.explain()

    def close(self) -> None:
        for c in (*self.cells, *self.seen):
            c.backend.close()


def recompute(query: Term, tables: dict[str, DataFrame]) -> DataFrame:
    """The baseline: the whole query on all data."""
    return evaluate(query, tables)


def window_only(query: Term, batches: list[dict[str, DataFrame]], static: dict[str, DataFrame] | None = None) -> DataFrame:
    """The baseline without state: each batch alone, with its number in ``batch``."""
    out = None
    for i, b in enumerate(batches):
        one = evaluate(query, {**(static or {}), **b}).withColumn("batch", F.lit(i).cast("long"))
        out = one if out is None else out.unionByName(one)
    return out


def run_in_batches(spark: SparkSession, query: Term, batches, schemas: dict[str, list[str]], static=None, **options) -> IncrementalQuery:
    """Folds any number of batches (e.g. parts of an input larger than memory) and returns the running query."""
    q = IncrementalQuery(spark, query, schemas, static, **options)
    for b in batches:
        q.step(b)
    return q


def appended(query: Term) -> None:
    """Refuses append output for queries whose old rows can change."""
    merge = infer(query)
    if merge is None or merge.kind != "bag":
        raise Unsupported("append output needs a query whose rows only ever add up")
