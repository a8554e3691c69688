"""Language identification of web pages by Bayesian fusion of evidence.

For each page the log-posterior over languages adds up

* *text*: a naive Bayes likelihood of hashed character trigrams of the visible text, tempered because
  neighbouring trigrams are not independent; fitted on a bounded sample of documents of known language;
* *markup*: P(declared language | language), declared by the first <html> tag outside comments and scripts,
  wherever in the page it is;
* *address*: P(address suffix | language), the suffix being a language segment of the path, else the last
  label of the host;
* *host*: a prior smoothed hierarchically: a host's counts lean on its domain's, and these on the corpus'.

The last three are estimated from all pages by grouped aggregation of the text posteriors (soft counts), so
they need no labels.  Priors of hosts with many pages are salted when they are joined back.

Cases: null or empty html has no text evidence (equal likelihoods), so markup, address and host decide; a
null address has the empty host and suffix; rows that repeat count as often as they occur; an empty table
gives an empty result; other columns are ignored.
"""

from __future__ import annotations

import html as markup
import re
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from deltafold.session import cut

SAMPLE_DOCS = 4000
BINS = 1 << 14
TEMPER = 0.2
LEAN = 4.0  # pages' worth of a smoother prior
SALT_AT = 50_000
_HIDDEN = re.compile(r"<(script|style)\b.*?</\1\s*>|<!--.*?-->", re.IGNORECASE | re.DOTALL)
_TAG = re.compile(r"<[^>]*>")


def visible_text(page: str) -> str:
    return markup.unescape(_TAG.sub(" ", _HIDDEN.sub(" ", page)))


def trigrams(text: str) -> np.ndarray:
    """Hashed character trigrams of the lower-cased text."""
    codes = np.frombuffer(re.sub(r"[\W\d_]+", " ", text.lower()).encode("utf-32-le", "surrogatepass"), np.uint32).astype(np.uint64)
    if len(codes) < 3:
        return np.zeros(0, np.int64)
    mixed = (codes[:-2] * np.uint64(0x9E3779B1) + codes[1:-1]) * np.uint64(0x85EBCA77) + codes[2:]
    mixed ^= mixed >> np.uint64(17)
    return ((mixed * np.uint64(0xC2B2AE3D27D4EB4F)) >> np.uint64(50)).astype(np.int64) & (BINS - 1)


def fit_text(docs: DataFrame, text_col: str = "text", lang_col: str = "lang", id_col: str = "doc_id", sample_docs: int = SAMPLE_DOCS) -> tuple[list[str], np.ndarray]:
    """Languages, and the log-probability of each trigram bin in each, from about ``sample_docs`` documents."""
    told = docs.where(F.col(lang_col).isNotNull() & F.col(text_col).isNotNull())
    classes = max(1, told.count() // sample_docs)

    def counted(batches):
        for batch in batches:
            total: dict[str, np.ndarray] = {}
            for lang, text in zip(batch["lang"].to_pylist(), batch["text"].to_pylist(), strict=True):
                total[lang] = total.get(lang, 0) + np.bincount(trigrams(text), minlength=BINS)
            yield pa.record_batch([pa.array(list(total), pa.string()), pa.array([v.astype("<i8").tobytes() for v in total.values()], pa.binary())], names=["lang", "counts"])

    sample = told.where(F.pmod(F.xxhash64(F.col(id_col)), F.lit(classes)) == 0).select(F.col(lang_col).alias("lang"), F.col(text_col).cast("string").alias("text"))
    rows = sample.mapInArrow(counted, "lang string, counts binary").collect()  # a few rows of fixed size for each batch of the sample
    langs = sorted({r["lang"] for r in rows})
    table = np.ones((BINS, max(1, len(langs)))) * 0.5
    for r in rows:
        table[:, langs.index(r["lang"])] += np.frombuffer(r["counts"], "<i8")
    return langs, np.log(table / table.sum(0))


def _read(table: np.ndarray, n_langs: int):
    root = re.compile(r"<html\b[^>]*", re.IGNORECASE)
    declared = re.compile(r"\blang\s*=\s*[\"']?([A-Za-z]+)", re.IGNORECASE)
    address = re.compile(r"^[a-z][a-z0-9+.-]*://([^/?#:]*)[^/?#]*(?:/([a-z]{2})(?=[/?#]|$))?", re.IGNORECASE)

    def run(batches):
        for batch in batches:
            cols: list[list] = [[], [], [], [], [], []]
            for key, url, page in zip(batch["id"].to_pylist(), batch["url"].to_pylist(), batch["html"].to_pylist(), strict=True):
                grams = trigrams(visible_text(page))
                like = table[grams].sum(0) * TEMPER if len(grams) else np.zeros(n_langs)
                like = like - like.max() if n_langs else like
                m, tag = address.match(url), root.search(_HIDDEN.sub(" ", page))
                d = declared.search(tag[0]) if tag else None
                host = (m[1] if m else "").lower()
                labels = host.split(".")
                row = (key, host, ".".join(labels[-2:]), (m[2] or labels[-1] if m else "").lower(), d[1].lower() if d else "", like.tolist())
                for to, x in zip(cols, row, strict=True):
                    to.append(x)
            yield pa.record_batch([pa.array(cols[0], pa.int64()), *(pa.array(c, pa.string()) for c in cols[1:5]), pa.array(cols[5], pa.list_(pa.float64()))], names=["id", "host", "domain", "suffix", "declared", "like"])

    return run


def _array(make, n: int):
    return F.array(*(make(i) for i in range(n)))


def identify(pages: DataFrame, langs: list[str], table: np.ndarray, id_col: str = "page_id", url_col: str = "url", html_col: str = "html") -> DataFrame:
    """For each page: host, declared language, address suffix, the most likely language, its posterior, and the
    language of the text alone."""
    n = len(langs)
    text = lambda c: F.coalesce(F.col(c).cast("string"), F.lit(""))
    rows = pages.select(F.col(id_col).cast("long").alias("id"), text(url_col).alias("url"), text(html_col).alias("html"))
    rows = rows.mapInArrow(_read(table, n), "id long, host string, domain string, suffix string, declared string, like array<double>")
    if n == 0:
        none = F.lit(None)
        return rows.select(F.col("id").alias("page_id"), "host", "declared", "suffix", none.cast("string").alias("lang"), none.cast("double").alias("posterior"), none.cast("string").alias("text_lang"))
    weights = _array(lambda i: F.exp(F.col("like")[i]), n)
    rows = cut(rows.withColumn("w", weights).withColumn("w", F.transform("w", lambda x: x / F.aggregate("w", F.lit(0.0), lambda a, b: a + b))))

    def soft(*keys):
        return rows.groupBy(*keys).agg(F.count("*").alias("pages"), _array(lambda i: F.sum(F.col("w")[i]), n).alias("c"))

    total = soft().first()
    share = [((x or 0.0) + 1.0) / ((total["pages"] or 0) + n) for x in total["c"] or [0.0] * n]
    domains = soft("domain").select("domain", _array(lambda i: (F.col("c")[i] + LEAN * share[i]) / (F.col("pages") + LEAN), n).alias("p"))
    hosts = soft("host", "domain").join(domains, "domain")
    hosts = hosts.select("host", F.ceil(F.col("pages") / SALT_AT).cast("int").alias("salts"), _array(lambda i: F.log((F.col("c")[i] + LEAN * F.col("p")[i]) / (F.col("pages") + LEAN)), n).alias("host_log"))

    def given(key: str):
        """log P(value | language) of a bounded or sparse attribute, smoothed by its share of all pages."""
        each = soft(key)
        return each.select(key, _array(lambda i: F.log((F.col("c")[i] + LEAN * F.col("pages") / (total["pages"] or 1)) / ((total["c"] or [0.0] * n)[i] + LEAN)), n).alias(f"{key}_log"))

    salted = rows.join(hosts.select("host", "salts"), "host").withColumn("salt", F.pmod(F.xxhash64("id"), F.col("salts")).cast("int")).drop("salts")
    priors = hosts.withColumn("salt", F.explode(F.sequence(F.lit(0), F.col("salts") - 1))).drop("salts")
    known = salted.join(priors, ["host", "salt"]).join(given("declared"), "declared").join(given("suffix"), "suffix")
    parts = ["like", "host_log", "declared_log", "suffix_log"]
    known = known.withColumn("s", _array(lambda i: reduce(lambda a, b: a + b, [F.col(c)[i] for c in parts]), n))
    known = known.withColumn("best", F.array_max("s"))
    mass = F.aggregate(F.transform("s", lambda x: F.exp(x - F.col("best"))), F.lit(0.0), lambda a, b: a + b)
    name = lambda c: F.array(*map(F.lit, langs))[F.array_position(c, F.array_max(c)).cast("int") - 1]
    return known.select(F.col("id").alias("page_id"), "host", "declared", "suffix", name(F.col("s")).alias("lang"), (1 / mass).alias("posterior"), name(F.col("like")).alias("text_lang"))


def op7_language_id(spark, sf_dir: str) -> DataFrame:
    """The language of every page of ``pages``; the text model is fitted on ``documents``."""
    langs, table = fit_text(spark.read.parquet(f"{sf_dir}/documents.parquet"))
    return identify(spark.read.parquet(f"{sf_dir}/pages.parquet"), langs, table)
