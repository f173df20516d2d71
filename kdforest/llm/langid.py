"""Language identification by fusing text likelihoods with declared language, address suffix and host priors.

Trigram likelihoods come from a bounded sample of labelled documents. One pass over the rows keeps, in place of the
text, its log likelihood in each language. Grouped aggregation of the text-only guesses gives counts by host and by address
suffix; a host's prior is smoothed towards its suffix's, and that towards all rows'. The posterior multiplies text
likelihood, prior and the chance of the declared language.
"""

from __future__ import annotations

import math
import re
from collections.abc import Iterator
from dataclasses import dataclass
from html import unescape

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from kdforest.llm.common import hash_sample, maybe_broadcast, table, unused, written

BUCKETS = 1 << 15
FIT_ROWS = 6_000
#: Trigrams that count at most, for neighbouring ones aren't independent.
MOST_TRIGRAMS = 60
#: Log likelihood of a trigram in no known language.
OTHER = -math.log(BUCKETS) - 0.5
#: Chance that a declared language is right, and pseudo-counts of the parent prior.
DECLARED_RIGHT, SMOOTHING = 0.9, 20.0
#: Largest share of a language's likelihood spread over all trigrams: with it one never seen is less likely than in no known language.
MOST_SPREAD = 0.5
SALTS = 64
_TAGS = re.compile(r"<!--.*?-->|<(script|style|head)\b.*?</\1\s*>|<[^>]*>", re.S | re.I)
_LETTER = np.array([chr(i).isalpha() for i in range(0x3000)])


def trigrams(text: str | None) -> np.ndarray:
    """Buckets of the trigrams of a text's letters in lower case; other characters are one space between words."""
    c = np.frombuffer((text or "").lower().encode("utf-32-le", "replace"), dtype="<u4")
    letter = _LETTER[np.minimum(c, 0x2FFF)] | (c >= 0x3040)
    keep = letter | np.concatenate([[False], letter[:-1]]) if len(c) else letter
    c = np.where(letter, c, 32)[keep]
    if not letter.any():
        return np.zeros(0, dtype=np.int64)
    c = np.concatenate([[32], c, [32]]).astype(np.uint32)
    h = (c[:-2] * np.uint32(0x9E3779B1) + c[1:-1]) * np.uint32(0x85EBCA6B) + c[2:]
    h = (h ^ (h >> np.uint32(15))) * np.uint32(0x2C1B3C6D)
    return ((h ^ (h >> np.uint32(12))) & np.uint32(BUCKETS - 1)).astype(np.int64)


@dataclass
class Likelihood:
    """Log likelihood of each bucket in each language."""

    languages: list[str]
    log: np.ndarray

    def of(self, text: str | None) -> tuple[list[float], int]:
        """Tempered log likelihoods, the last that of no known language, and the trigrams."""
        g = trigrams(text)
        if not len(g):
            return [0.0] * (len(self.languages) + 1), 0
        mean = [*self.log[:, g].mean(axis=1).tolist(), OTHER]
        return [m * min(len(g), MOST_TRIGRAMS) for m in mean], len(g)


def smoothed(counts: np.ndarray, floor: float = 0.5) -> np.ndarray:
    """Log likelihoods from ``counts`` with ``floor`` added to each, but at most ``MOST_SPREAD`` of the whole."""
    n = max(1, int(counts.sum()))
    spread = min(floor * BUCKETS / (n + floor * BUCKETS), MOST_SPREAD)
    return np.log((1 - spread) * counts / n + spread / BUCKETS)


def trained(docs: DataFrame, rows: int = FIT_ROWS, most_languages: int = 200, floor: float = 0.5) -> Likelihood:
    """Fit on about ``rows`` labelled documents (doc_id, text, lang); rows without a label don't count.

    Of more than ``most_languages`` languages those with the most trigrams in the sample are kept, which bounds the model;
    texts in another one are then "und" or taken for a kept one. Null and empty texts count no trigrams.
    """
    some = hash_sample(docs.where("lang IS NOT NULL AND lang <> '' AND doc_id IS NOT NULL").select("doc_id", "text", "lang"), "doc_id", rows)

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        counts: dict[str, np.ndarray] = {}
        for b in batches:
            for text, lang in zip(b.column(0), b.column(1).to_pylist(), strict=True):
                counts.setdefault(lang, np.zeros(BUCKETS, dtype=np.int64))
                counts[lang] += np.bincount(trigrams(text.as_py()), minlength=BUCKETS)
        yield pa.RecordBatch.from_pylist([{"lang": k, "n": v.tobytes()} for k, v in counts.items()], pa.schema([("lang", pa.string()), ("n", pa.binary())]))

    total: dict[str, np.ndarray] = {}
    for r in some.select("text", "lang").repartition(8).mapInArrow(work, "lang string, n binary").toLocalIterator():
        total[r.lang] = total.get(r.lang, 0) + np.frombuffer(r.n, dtype=np.int64)
    kept = sorted(sorted(total, key=lambda k: -total[k].sum())[:most_languages])
    return Likelihood(kept, np.array([smoothed(total[k], floor) for k in kept]).reshape(-1, BUCKETS))


def visible(page: str | None) -> str:
    return unescape(_TAGS.sub(" ", page or ""))


def with_likelihoods(rows: DataFrame, model: Likelihood, markup: bool) -> DataFrame:
    """``rows`` with ``body`` replaced by ll (one per language and one for none) and trigrams."""
    keep = [c for c in rows.columns if c != "body"]

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            got = [model.of(visible(t.as_py()) if markup else t.as_py()) for t in b.column("body")]
            cols = [*(b.column(c) for c in keep), pa.array([g[0] for g in got], pa.list_(pa.float64())), pa.array([g[1] for g in got], pa.int64())]
            yield pa.RecordBatch.from_arrays(cols, [*keep, "ll", "trigrams"])

    schema = rows.select(*keep).withColumns({"ll": F.array(F.lit(0.0)), "trigrams": F.lit(0).cast("long")}).schema
    return rows.select(*keep, "body").mapInArrow(work, schema)


def _guess(ll: Column, n: int) -> Column:
    """Position of the largest value, from 1."""
    return F.array_position(F.slice(ll, 1, n), F.array_max(F.slice(ll, 1, n))).cast("int")


def host_priors(marked: DataFrame, n: int, smoothing: float = SMOOTHING) -> DataFrame:
    """(host, suffix, prior): log priors of the ``n`` classes from grouped counts of text-only guesses."""
    known = marked.where("trigrams > 0").select("host", "suffix", _guess(F.col("ll"), n).alias("g"))
    tally = [F.sum(F.when(F.col("g") == i + 1, 1.0).otherwise(0.0)).alias(f"n{i}") for i in range(n)]
    hosts = written(known.groupBy("host", "suffix").agg(*tally), "hosts")
    sums = [F.sum(f"n{i}").alias(f"n{i}") for i in range(n)]
    row = hosts.agg(*sums).first()
    world = [float(row[i] or 0) + 1.0 for i in range(n)]
    world = [x / sum(world) for x in world]
    suffixes = hosts.groupBy("suffix").agg(*sums)
    s_total = sum((F.col(f"n{i}") for i in range(n)), F.lit(0.0))
    suffixes = suffixes.select("suffix", *[((F.col(f"n{i}") + smoothing * world[i]) / (s_total + smoothing)).alias(f"s{i}") for i in range(n)])
    both = hosts.join(maybe_broadcast(suffixes), "suffix")
    prior = F.array(*[F.log((F.col(f"n{i}") + smoothing * F.col(f"s{i}")) / (s_total + smoothing)) for i in range(n)])
    return both.select("host", "suffix", prior.alias("prior"))


def fused(marked: DataFrame, model: Likelihood) -> DataFrame:
    """``marked`` (host, suffix, declared, ll, trigrams and others) with language, confidence and accepted.

    language is "und" if there are no letters or no known language has the largest posterior; accepted says that
    it isn't. Hosts of a third of all rows are dealt out by a salt unless the priors are few.
    """
    n = len(model.languages)
    if not n:
        return marked.select("*", F.lit("und").alias("language"), F.lit(0.0).alias("confidence"), F.lit(False).alias("accepted"))
    priors = host_priors(marked, n + 1)
    few = priors.count() <= 20_000
    if few:
        joined = marked.join(F.broadcast(priors), ["host", "suffix"], "left")
    else:
        spread = priors.select("*", F.explode(F.sequence(F.lit(0), F.lit(SALTS - 1))).alias("salt"))
        salt = F.pmod(F.xxhash64(*[c for c in marked.columns if c not in ("host", "suffix", "declared", "ll")]), F.lit(SALTS)).cast("int")
        joined = marked.withColumn("salt", salt).join(spread, ["host", "suffix", "salt"], "left").drop("salt")
    names = F.array(*[F.lit(x) for x in model.languages])
    right, wrong = math.log(DECLARED_RIGHT), math.log((1 - DECLARED_RIGHT) / max(1, n - 1))
    claim = F.regexp_extract(F.lower(F.coalesce("declared", F.lit(""))), "^([a-z]+)", 1)  # en-US is en, fil is not fi
    known = F.array_contains(names, claim)
    said = F.concat(
        F.transform(names, lambda x: F.when(~known, F.lit(0.0)).when(x == claim, F.lit(right)).otherwise(F.lit(wrong))),
        F.array(F.when(known, F.lit(-math.log(n))).otherwise(F.lit(0.0))),
    )
    prior = F.coalesce("prior", F.array(*[F.lit(-math.log(n + 1))] * (n + 1)))
    score = F.zip_with(F.zip_with("ll", prior, lambda a, b: a + b), said, lambda a, b: a + b)
    out = joined.withColumn("_score", score).drop("prior")
    top = F.array_max("_score")
    mass = F.aggregate("_score", F.lit(0.0), lambda acc, x: acc + F.exp(x - F.array_max("_score")))
    place = F.array_position("_score", top).cast("int")
    best = F.get(names, place - 1)
    real = (F.col("trigrams") > 0) & (place <= n)
    return out.select(*marked.columns, F.when(real, best).otherwise("und").alias("language"), F.when(real, 1 / mass).otherwise(0.0).alias("confidence"), F.coalesce(real, F.lit(False)).alias("accepted"))


def page_languages(pages: DataFrame, model: Likelihood) -> DataFrame:
    """page_id, url, declared, host, language, confidence and accepted of each row of ``pages`` (page_id, url, html).

    A null page has no letters and is "und"; a null or odd address has host "" and suffix ""; other columns are ignored.
    """
    url = F.lower(F.coalesce("url", F.lit("")))
    host = F.regexp_extract(url, r"^(?:[a-z][a-z0-9+.-]*:)?//(?:[^/?#@]*@)?([^/?#:]*)", 1)
    declared = F.regexp_extract(F.coalesce("html", F.lit("")), r"(?is)<html\b[^>]*?\blang\s*=\s*[\"']?([a-z]{2,3})", 1)
    rows = pages.select("page_id", "url", declared.alias("declared"), host.alias("host"), F.regexp_extract(host, r"([^.]*)$", 1).alias("suffix"), F.col("html").alias("body"))
    marked = written(with_likelihoods(rows, model, markup=True), "likelihoods")
    return fused(marked, model).select("page_id", "url", "declared", "host", "language", "confidence", "accepted")


def accepted_documents(docs: DataFrame, model: Likelihood) -> DataFrame:
    """The rows of ``docs`` (text, lang, source, others) in a known language; their columns stay as they are.

    lang is taken as the declared language and source as the host. Rows without letters and rows that no known
    language explains are rejected. Null sources are one host.
    """
    source = F.coalesce(F.col("source").cast("string"), F.lit(""))
    real = F.coalesce(F.length("text") > 0, F.lit(False))
    d, m = unused(docs, "rejected_id"), unused(docs, "rejected_mark")
    rows = docs.where(real).select(F.xxhash64("text").alias("mark"), F.col("doc_id"), F.col("lang").alias("declared"), source.alias("host"), F.lit("").alias("suffix"), F.col("text").alias("body"))
    marked = written(with_likelihoods(rows, model, markup=False), "likelihoods")
    bad = fused(marked, model).where(~F.col("accepted")).select(F.col("doc_id").alias(d), F.col("mark").alias(m)).distinct()
    kept = docs.where(real)
    return kept.join(maybe_broadcast(bad), F.col("doc_id").eqNullSafe(F.col(d)) & (F.xxhash64("text") == F.col(m)), "left_anti")


def op1_language(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The language of every page, by a model fitted on labelled documents; see ``page_languages``."""
    model = trained(table(spark, sf_dir, "documents"))
    return page_languages(table(spark, sf_dir, "pages"), model)
