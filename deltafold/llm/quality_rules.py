"""Quality classifier: a sparse ensemble of rules over text statistics.

1. *statistics*: about twenty column expressions over the whole text (no Python on the rows).
2. *rules*: boosted shallow trees are grown on a bounded sample of labelled documents; every path from a root
   to a node below it is a rule, a conjunction of bounds on statistics.
3. *weights*: logistic regression on the rules with a lasso penalty; most weights become zero.
4. *compile*: the rules left are one Spark column, so scoring is a scan and a projection.

Labels, language, source and id are no inputs of the score.

Cases: a null or empty text has statistics of zero and is scored as such; labels that are null or repeat with
both values count as they stand or not at all; no label in the sample gives 0.5 for every document (one value
only gives that value's share, smoothed); rows that repeat are scored as often as they occur; an empty table
gives an empty result; other columns are ignored.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from deltafold.llm._common import unused

#: Labelled documents that the fit reads at most (about).
SAMPLE_ROWS = 20_000
TREES, DEPTH, BINS, LEAST = 24, 3, 32, 20
PENALTY, ROUNDS = 1e-3, 400

_UPPER = "ABCDEFGHIJKLMNOPQRSTUVWXYZÀÁÂÄÆÇÈÉÊËÍÎÏÑÓÔÖÙÚÛÜ"


def _without(text: Column, chars: str) -> Column:
    return F.length(F.translate(text, chars, ""))


def statistics(text: Column, words: Column) -> dict[str, Column]:
    """Statistics of a text and of its words (an array), all null-free doubles."""
    n = F.greatest(F.length(text), F.lit(1))
    n_words = F.greatest(F.size(words), F.lit(1))
    share = lambda chars: (F.length(text) - _without(text, chars)) / n
    pairs = F.zip_with(F.slice(words, F.lit(1), F.greatest(F.size(words) - 1, F.lit(0))), F.slice(words, F.lit(2), F.greatest(F.size(words) - 1, F.lit(0))), lambda a, b: a == b)
    lines = F.size(F.split(text, "\n"))
    return {
        "length": F.log1p(F.length(text).cast("double")),
        "words": F.log1p(F.size(words).cast("double")),
        "word_length": F.length(text) / n_words,
        "distinct": F.size(F.array_distinct(words)) / n_words,
        "repeated": F.size(F.filter(pairs, lambda x: x)) / n_words,
        "long_words": F.size(F.filter(words, lambda w: F.length(w) >= 16)) / n_words,
        "short_words": F.size(F.filter(words, lambda w: F.length(w) <= 2)) / n_words,
        "upper": share(_UPPER),
        "digits": share("0123456789"),
        "marks": share("#$%&*@^~+=<>"),
        "bars": share("|/\\_"),
        "calls": share("!?"),
        "stops": share("."),
        "commas": share(",;:"),
        "brackets": share("()[]{}\"'"),
        "line_length": F.log1p(n / lines),
    }


@dataclass(frozen=True)
class Rule:
    """All bounds hold: (statistic, threshold, True where it is to be above)."""

    bounds: tuple[tuple[str, float, bool], ...]

    def rows(self, x: dict[str, np.ndarray]) -> np.ndarray:
        return np.logical_and.reduce([(x[s] > t) == above for s, t, above in self.bounds])

    def column(self, of: dict[str, Column]) -> Column:
        out = None
        for s, t, above in self.bounds:
            one = of[s] > F.lit(t) if above else of[s] <= F.lit(t)
            out = one if out is None else out & one
        return out


def _tree_rules(x: np.ndarray, names: list[str], cuts: list[np.ndarray], bins: np.ndarray, grad: np.ndarray, rows: np.ndarray) -> tuple[list[Rule], np.ndarray]:
    """Rules of one tree's nodes, and the tree's output on all rows."""
    rules, out = [], np.zeros(len(x))
    least = max(2, min(LEAST, len(rows) // 10))  # of small samples a tenth

    def grow(bounds: tuple, mine: np.ndarray, everyone: np.ndarray) -> None:
        best = (1e-9, None, None)
        if len(bounds) < DEPTH:
            for f in range(len(names)):
                if len(cuts[f]) == 0:
                    continue
                size = np.bincount(bins[mine, f], minlength=len(cuts[f]) + 1)[:-1].cumsum()
                total = np.bincount(bins[mine, f], weights=grad[mine], minlength=len(cuts[f]) + 1)
                left, whole = total[:-1].cumsum(), total.sum()
                ok = (size >= least) & (len(mine) - size >= least)
                if not ok.any():
                    continue
                gain = np.where(ok, left**2 / np.maximum(size, 1) + (whole - left) ** 2 / np.maximum(len(mine) - size, 1) - whole**2 / len(mine), 0)
                if gain.max() > best[0]:
                    best = (gain.max(), f, int(gain.argmax()))
        if bounds:
            rules.append(Rule(bounds))
        if best[1] is None:
            out[everyone] = grad[mine].mean() if len(mine) else 0
            return
        _, f, c = best
        for above in (False, True):
            side = lambda r: r[(bins[r, f] > c) == above]  # noqa: B023, E731
            grow((*bounds, (names[f], float(cuts[f][c]), above)), side(mine), side(everyone))

    grow((), rows, np.arange(len(x)))
    return rules, out


def extract_rules(stats: dict[str, np.ndarray], y: np.ndarray) -> list[Rule]:
    """Distinct rules of boosted trees, each grown on a random half of the rows."""
    names = sorted(stats)
    x = np.stack([stats[s] for s in names], axis=1)
    cuts = [np.unique(np.quantile(x[:, f], np.linspace(0, 1, BINS + 1)[1:-1])) for f in range(len(names))]
    bins = np.stack([np.searchsorted(cuts[f], x[:, f], "left") for f in range(len(names))], axis=1)
    rng, raw, found = np.random.default_rng(0), np.full(len(y), np.log((y.mean() + 1e-3) / (1 - y.mean() + 1e-3))), {}
    for _ in range(TREES):
        grad = y - 1 / (1 + np.exp(-raw))
        rules, step = _tree_rules(x, names, cuts, bins, grad, np.sort(rng.permutation(len(y))[: max(1, len(y) // 2)]))
        raw = raw + 2 * step
        found |= dict.fromkeys(rules)
    return list(found)


def lasso(z: np.ndarray, y: np.ndarray, penalty: float = PENALTY, rounds: int = ROUNDS) -> tuple[np.ndarray, float]:
    """Weights and bias of a logistic regression with an absolute penalty (accelerated proximal steps)."""
    n, p = z.shape
    mean = z.mean(0)
    c = z - mean
    step = 4 / max(np.linalg.norm(c, 2) ** 2 / n, 1e-9) if p else 1.0
    w, b = np.zeros(p), float(np.log((y.mean() + 1e-3) / (1 - y.mean() + 1e-3)))
    ahead, momentum = w, 1.0
    for _ in range(rounds):
        error = 1 / (1 + np.exp(-(c @ ahead + b))) - y
        new = ahead - step * (c.T @ error) / n
        new = np.sign(new) * np.maximum(np.abs(new) - step * penalty, 0)
        b -= 2 * error.mean()
        after = (1 + np.sqrt(1 + 4 * momentum**2)) / 2
        ahead, w, momentum = new + (momentum - 1) / after * (new - w), new, after
    return w, b - float(mean @ w)


@dataclass(frozen=True)
class RuleEnsemble:
    rules: tuple[Rule, ...]
    weights: tuple[float, ...]
    bias: float

    def score(self, of: dict[str, Column]) -> Column:
        total = F.lit(self.bias)
        for rule, w in zip(self.rules, self.weights, strict=True):
            total = total + F.when(rule.column(of), F.lit(w)).otherwise(F.lit(0.0))
        return 1 / (1 + F.exp(-total))


def with_statistics(docs: DataFrame, keep: list[Column], text_col: str = "text") -> DataFrame:
    """The kept columns and, last, a struct of the statistics under a name that none of them has."""
    kept = docs.select(*keep).columns
    text, words, found = (unused(x, kept) for x in ("__text", "__words", "__stats"))
    staged = docs.select(*keep, F.coalesce(F.col(text_col).cast("string"), F.lit("")).alias(text))
    staged = staged.withColumn(words, F.filter(F.split(text, r"[\x20\x09-\x0D]+"), lambda w: w != ""))
    stats = statistics(F.col(text), F.col(words))
    return staged.withColumn(found, F.struct(*(c.cast("double").alias(s) for s, c in stats.items()))).drop(text, words)


def train(docs: DataFrame, labels: DataFrame, id_col: str = "doc_id", text_col: str = "text", label_col: str = "quality", sample_rows: int = SAMPLE_ROWS) -> RuleEnsemble:
    """An ensemble of ``labels`` (id and 0/1) for their documents, on about ``sample_rows`` of them."""
    told = labels.where(F.col(label_col).isin(0, 1) & F.col(id_col).isNotNull()).groupBy(F.col(id_col).cast("long").alias("__id")).agg(F.min(label_col).alias("__low"), F.max(label_col).alias("__high"))
    told = told.where("__low = __high").select("__id", F.col("__low").cast("double").alias("__y"))
    classes = max(1, told.count() // sample_rows)
    some = F.broadcast(told.where(F.pmod(F.xxhash64("__id"), F.lit(classes)) == 0))  # about sample_rows rows, whatever the table's size
    texts = docs.select(F.col(id_col).cast("long").alias("__id"), F.col(text_col).alias("__t"))
    rows = with_statistics(texts.join(some, "__id"), [F.col("__y")], "__t").limit(2 * sample_rows).collect()
    if not rows:
        return RuleEnsemble((), (), 0.0)
    y = np.array([r["__y"] for r in rows])
    stats = {s: np.array([r["__stats"][s] for r in rows]) for s in rows[0]["__stats"].asDict()}
    rules = extract_rules(stats, y) if 0 < y.mean() < 1 else []
    z = np.stack([r.rows(stats) for r in rules], axis=1).astype(float) if rules else np.zeros((len(y), 0))
    w, b = lasso(z, y)
    left = [i for i in range(len(rules)) if abs(w[i]) > 1e-6]
    return RuleEnsemble(tuple(rules[i] for i in left), tuple(float(w[i]) for i in left), b)


def scored(docs: DataFrame, model: RuleEnsemble, keep: list[Column], text_col: str = "text", name: str = "score") -> DataFrame:
    """The kept columns and a double ``name``."""
    staged = with_statistics(docs, keep, text_col)
    found = staged.columns[-1]
    of = {s: F.col(f"{found}.{s}") for s in staged.schema[found].dataType.names}
    return staged.withColumn(name, model.score(of)).drop(found)


def held_out(key: Column) -> Column:
    """Rows that no label is taken from."""
    return F.coalesce(F.crc32(key.cast("string").cast("binary")) % 3 == 1, F.lit(False))


def train_for(spark, docs: DataFrame, sf_dir: str) -> RuleEnsemble:
    labels = spark.read.parquet(f"{sf_dir}/labels.parquet").where(~held_out(F.col("doc_id")))
    return train(docs, labels.select("doc_id", "quality"))


def op1_quality_classifier(spark, sf_dir: str) -> DataFrame:
    """The quality contract on ``documents``."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    out = scored(docs, train_for(spark, docs, sf_dir), [F.col("doc_id"), held_out(F.col("doc_id")).alias("held_out")])
    return out.select("doc_id", "held_out", "score", F.when(F.col("score") >= 0.5, 1).otherwise(0).alias("predicted"))
