"""K-means: batch, and approximate incremental with a state of one row for each cluster."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

Centres = list[tuple[float, ...]]
#: Of each cluster: the sums of its points' coordinates, and their number.
State = dict[int, tuple[float, ...]]


def nearest(dims: list[str], centres: Centres) -> Column:
    """The number of the nearest centre as a column expression (ties: the lowest).  Centres are few and known
    when the plan is made, so there is no join."""
    far = lambda c: reduce(lambda a, b: a + b, [(F.col(d).cast("double") - F.lit(float(x))) * (F.col(d).cast("double") - F.lit(float(x))) for d, x in zip(dims, c, strict=True)])
    if len(dims) > 8:  # a sum over arrays: written out, so many terms are more code than a method may have
        point = F.array(*(F.col(d).cast("double") for d in dims))
        far = lambda c: F.aggregate(F.zip_with(point, F.array(*(F.lit(float(x)) for x in c)), lambda a, b: (a - b) * (a - b)), F.lit(0.0), lambda s, x: s + x)
    if len(centres) == 1:
        return F.lit(0)
    return F.least(*(F.struct(far(c).alias("d"), F.lit(i).alias("i")) for i, c in enumerate(centres)))["i"]


def sums(points: DataFrame, dims: list[str], centres: Centres) -> DataFrame:
    """The state of points: (cid, s_<dim>..., c)."""
    return points.select(nearest(dims, centres).alias("cid"), *dims).groupBy("cid").agg(*(F.sum(d).cast("double").alias(f"s_{d}") for d in dims), F.count("*").alias("c"))


def state_of(points: DataFrame, dims: list[str], centres: Centres) -> State:
    """The state of points on the driver: k rows, one job."""
    return {r["cid"]: (*(r[f"s_{d}"] for d in dims), r["c"]) for r in sums(points, dims, centres).collect()}


def merged_states(a: State, b: State) -> State:
    """Clusters of both, added up."""
    return {i: tuple(x + y for x, y in zip(a[i], b[i], strict=True)) if i in a and i in b else a.get(i, b.get(i)) for i in a | b}


def centres_of(state: State, before: Centres) -> Centres:
    """Means by cluster; a cluster without points stays where it was."""
    return [tuple(x / state[i][-1] for x in state[i][:-1]) if i in state and state[i][-1] else c for i, c in enumerate(before)]


def kmeans(points: DataFrame, dims: list[str], init: Centres, rounds: int = 10) -> tuple[Centres, State]:
    """Batch k-means: a fixed number of rounds over all points, one job each.  The centres and the last state."""
    centres, state = list(init), {}
    for _ in range(rounds):
        state = state_of(points, dims, centres)
        centres = centres_of(state, centres)
    return centres, state


def initial_centres(points: DataFrame, dims: list[str], k: int, seed: int = 0) -> Centres:
    """k points chosen by a seeded hash."""
    rows = points.select(*dims, F.xxhash64(*dims, F.lit(seed)).alias("h")).distinct().orderBy("h", *dims).limit(k).collect()
    return [tuple(float(r[d]) for d in dims) for r in rows]


def near_pairs(new: Centres, old: Centres, eps: float) -> dict[int, int]:
    """New centre -> old centre for those that are each other's nearest within ``eps`` (k rows on either side)."""
    far = lambda a, b: sum((x - y) ** 2 for x, y in zip(a, b, strict=True)) ** 0.5
    best_old = [min(range(len(old)), key=lambda j: (far(a, old[j]), j)) for a in new]
    best_new = [min(range(len(new)), key=lambda i: (far(new[i], b), i)) for b in old]
    return {i: j for i, j in enumerate(best_old) if best_new[j] == i and far(new[i], old[j]) <= eps}


class IncrementalKMeans:
    """Each batch runs all rounds over the batch alone, against the state: what the batch's points add to the
    clusters they fall in is merged with the state of those clusters only (diffusion).

    ``fold="replace"`` puts the touched clusters' merged rows in place of the old ones; ``"as_printed"`` merges
    them once more, which counts the old points twice (kept to show that).  ``key="id"`` knows clusters by a
    number; ``"near"`` by their centres, equal within ``eps``.  A round is one job over the batch; the state has k rows
    and stays on the driver."""

    def __init__(self, spark, dims: list[str], init: Centres, rounds: int = 10, fold: str = "replace", start: str = "state", diffusion: bool = True, key: str = "id", eps: float = 0.5):
        self.spark, self.dims, self.init, self.rounds, self.fold, self.start, self.diffusion = spark, dims, list(init), rounds, fold, start, diffusion
        self.key, self.eps = key, eps
        self.state: State = {}
        self.centres, self.touched = list(init), []

    def _keyed(self, new: State, centres: Centres) -> State:
        """The batch's clusters under the state's keys."""
        if self.key == "id":
            return new
        there = sorted(self.state)
        pairs = near_pairs(centres, [self.centres[i] for i in there], self.eps)
        fresh = iter(range(len(self.init), 10**9))
        return {there[pairs[i]] if i in pairs else i if i not in self.state else next(fresh): v for i, v in new.items()}

    def step(self, points: DataFrame) -> Centres:
        points = points.select(*self.dims).persist()
        if not self.state:
            self.centres, self.state = kmeans(points, self.dims, self.init, self.rounds)
        else:
            centres, delta = (list(self.init) if self.start == "init" else list(self.centres)), {}
            for _ in range(self.rounds):
                new = self._keyed(state_of(points, self.dims, centres), centres)
                delta = {i: merged_states({i: self.state[i]}, {i: v})[i] if i in self.state else v for i, v in new.items()} if self.diffusion else merged_states(self.state, new)
                self.touched.append(len(delta) / max(1, len(self.state)))
                centres = centres_of(delta, centres)
            self.state = self.state | delta if self.fold == "replace" else merged_states(self.state, delta)
            self.centres = centres_of(self.state, self.centres)
        points.unpersist()
        return self.centres

    @property
    def points(self) -> int:
        """What the state takes for the number of points."""
        return sum(v[-1] for v in self.state.values())
