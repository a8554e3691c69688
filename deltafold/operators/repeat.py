"""Repetition of a step: on all data, exactly on increments where the step merges, and approximately where not."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from deltafold.functions.monoids import Kind
from deltafold.operators.merge import diffuse, merge_states, near_join
from deltafold.operators.merge import replace as replaced
from deltafold.plans.algebra import Term, Unsupported, evaluate
from deltafold.plans.infer import infer
from deltafold.session import cut


def repeat(step: Callable[[DataFrame], DataFrame], times: int, start: DataFrame, cut_every: int = 4) -> DataFrame:
    """``step`` applied ``times`` times; the plan is cut so that it does not grow with the rounds."""
    x = start
    for i in range(times):
        x = step(x)
        if (i + 1) % cut_every == 0:
            x = cut(x)
    return x


def is_homomorphic_step(step: Term) -> bool:
    """Whether a step, as a term over its value and the streams, merges: then increments can be run alone and
    merged exactly."""
    merge = infer(step)
    return merge is not None and merge.kind in ("bag", "keyed")


class ExactRepeat:
    """The ideal case: a step whose value on old and new data is the bag of both values, so every batch is run
    through all rounds alone and its result added."""

    def __init__(self, step: Term, source: str, times: int, static: dict[str, DataFrame] | None = None):
        merge = infer(step)
        if merge is None or merge.kind != "bag":
            raise Unsupported("the step does not merge; use IncrementalRepeat, which approximates")
        self.term, self.source, self.times, self.static, self.result = step, source, times, static or {}, None

    def step(self, batch: DataFrame) -> DataFrame:
        new = cut(repeat(lambda x: evaluate(self.term, {**self.static, self.source: x}), self.times, batch))
        self.result = new if self.result is None else self.result.unionByName(new)
        return self.result


class IncrementalRepeat:
    """The approximate loop.  ``partial(x, batch)`` is the keyed state of a batch under the fixpoint value x, and
    ``answer(state)`` the next value.  A batch runs all rounds alone: in each, what it adds is merged with the old
    state's rows of the same keys only (diffusion; without it, with all rows), and the answer of that is the next
    value.  After the loop the touched rows take the place of the old ones (``fold="replace"``); ``"as_printed"``
    merges them once more, which counts old data twice.

    ``near=(dims, eps)``: keys are points that hardly ever repeat exactly; a new key takes the place of the old one
    that is its mutual nearest within eps.  ``dims`` are columns of the state made by ``place(state)``."""

    def __init__(self, spark: SparkSession, partial: Callable, answer: Callable, keys: list[str], kinds: dict[str, Kind], init, times: int, fold: str = "replace", start: str = "state", diffusion: bool = True, near: tuple[list[str], float] | None = None, place: Callable | None = None):
        self.spark, self.partial, self.answer_of, self.keys, self.kinds, self.init, self.times = spark, partial, answer, keys, kinds, init, times
        self.fold, self.start, self.diffusion, self.near, self.place = fold, start, diffusion, near, place
        self.state: DataFrame | None = None
        self.touched: list[float] = []

    def _rekeyed(self, new: DataFrame) -> DataFrame:
        if not self.near:
            return new
        (key,), (dims, eps) = self.keys, self.near
        pairs = near_join(self.place(self.state).withColumnRenamed(key, "t_id"), self.place(new).withColumnRenamed(key, "d_id"), dims, eps)
        found = new.join(pairs.withColumnRenamed("d_id", key), key, "left")
        return found.withColumn(key, F.coalesce("t_id", key)).drop("t_id")

    def step(self, batch: DataFrame):
        batch = batch.persist()
        if self.state is None:
            x = self.init
            for _ in range(self.times):
                state = cut(self.partial(x, batch))
                x = self.answer_of(state)
            self.state = state
        else:
            x, rows = (self.init if self.start == "init" else self.answer_of(self.state)), self.state.count()
            for _ in range(self.times):
                new = self._rekeyed(self.partial(x, batch))
                delta = cut(diffuse(self.state, new, self.keys, self.kinds) if self.diffusion else merge_states(self.state, new, self.keys, self.kinds))
                self.touched.append(delta.count() / max(1, rows))
                x = self.answer_of(delta)
            self.state = cut(replaced(self.state, delta, self.keys) if self.fold == "replace" else merge_states(self.state, delta, self.keys, self.kinds))
        batch.unpersist()
        return self.answer()

    def answer(self):
        return self.answer_of(self.state)
