"""Quality scores by a regularised quadratic discriminant over transformed document statistics.

One pass turns whole texts into a few statistics. Class means and covariances come from a bounded sample of
labelled rows; each covariance is shrunk towards the pooled one and a multiple of the identity, and its Cholesky
factor is kept. A score is the logistic of the difference of two Mahalanobis log densities and the log odds.
"""

from __future__ import annotations

import re
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from kdforest.llm.common import hash_sample, table, unused

#: Labelled rows that a fit takes at most (ties of hashes aside).
FIT_ROWS = 20_000
STATISTICS = (
    "log_words", "log_word_length", "symbols", "digits", "upper", "non_ascii", "stops", "repeated_lines", "repeated_words",
    "short_words", "odd_words", "entropy", "exclaims", "log_sentence",
)
_KIND = np.zeros(256, dtype=np.int64)  # 0 other, 1 lower, 2 upper, 3 digit, 4 white, 5 symbol, 6 stop, 7 shout
_KIND[[*range(97, 123)]] = 1
_KIND[[*range(65, 91)]] = 2
_KIND[[*range(48, 58)]] = 3
_KIND[[9, 10, 11, 12, 13, 32]] = 4
_KIND[[c for c in range(33, 127) if not chr(c).isalnum()]] = 5
_KIND[[ord(c) for c in ".,;:"]] = 6
_KIND[[ord(c) for c in "!?"]] = 7
_PLAIN = re.compile(rb"[A-Za-z\x80-\xff'-]+[.,;:!?]*")


def statistics(text: str | None) -> list[float]:
    raw = (text or "").encode()
    words = raw.split()
    n, b = len(words), max(1, len(raw))
    counts = np.bincount(np.frombuffer(raw, dtype=np.uint8), minlength=256)
    kind = np.bincount(_KIND, weights=counts, minlength=8)
    letters = max(1.0, kind[1] + kind[2])
    lines = [x for x in raw.split(b"\n") if x]
    share = counts[counts > 0] / b
    distinct = set(words)
    odd = sum(1 for w in distinct if not _PLAIN.fullmatch(w))
    return [
        float(np.log1p(n)), float(np.log1p(sum(map(len, words)) / max(1, n))), float(np.sqrt(kind[5] / b)), float(np.sqrt(kind[3] / b)), float(np.sqrt(kind[2] / letters)),
        float(np.sqrt(counts[128:].sum() / b)), float(np.sqrt(kind[6] / b)), 1 - len(set(lines)) / max(1, len(lines)), 1 - len(distinct) / np.sqrt(max(1, n)) / max(1.0, np.sqrt(len(distinct))),
        sum(1 for w in words if len(w) < 3) / max(1, n), float(np.sqrt(odd / max(1, len(distinct)))), float(-(share * np.log(share)).sum()), float(np.sqrt(kind[7] / b)), float(np.log1p(n / max(1.0, counts[46] + kind[7]))),
    ]


def document_statistics(docs: DataFrame, keep: list[str], text_col: str = "text") -> DataFrame:
    """Columns ``keep`` and x, the statistics of each row's whole text (null: empty)."""

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            x = pa.array([statistics(t.as_py()) for t in b.column(b.num_columns - 1)], pa.list_(pa.float64()))
            yield pa.RecordBatch.from_arrays([*(b.column(i) for i in range(len(keep))), x], [*keep, "x"])

    slim = docs.select(*keep, F.col(text_col).alias(unused(docs, "whole_text")))
    schema = docs.select(*keep).withColumn("x", F.array(F.lit(0.0))).schema
    return slim.mapInArrow(work, schema)


@dataclass
class Discriminant:
    """Means, Cholesky factors of the inverse scale and log constants of the classes 0 and 1."""

    mean: np.ndarray
    whiten: np.ndarray
    constant: np.ndarray

    def log_density(self, x: np.ndarray) -> np.ndarray:
        """Row per document, column per class, priors included."""
        out = np.empty((len(x), 2))
        for c in (0, 1):
            z = (x - self.mean[c]) @ self.whiten[c].T
            out[:, c] = self.constant[c] - 0.5 * (z * z).sum(axis=1)
        return out

    def score(self, x: np.ndarray) -> np.ndarray:
        d = self.log_density(x)
        return 1 / (1 + np.exp(np.clip(d[:, 0] - d[:, 1], -500, 500)))


def fit(x: np.ndarray, y: np.ndarray, pooled: float = 0.5, ridge: float = 0.05) -> Discriminant:
    """``pooled``: how far each class covariance is drawn to the pooled one; ``ridge``: that one to a multiple of the identity.

    A class without rows takes the statistics of all; without any rows every score is 0.5.
    """
    k = x.shape[1] if x.ndim == 2 else len(STATISTICS)
    x = x.reshape(-1, k)
    means, covs = [], []
    for c in (0, 1):
        own = x[y == c]
        means.append(own.mean(axis=0) if len(own) else x.mean(axis=0) if len(x) else np.zeros(k))
        covs.append(np.cov(own.T, bias=True).reshape(k, k) if len(own) > 1 else None)
    weights = [float((y == c).sum()) for c in (0, 1)]
    known = [(w, s) for w, s in zip(weights, covs, strict=True) if s is not None]
    pool = sum(w * s for w, s in known) / sum(w for w, _ in known) if known else np.eye(k)
    scale = np.diag(np.maximum(np.diag(pool), 1e-4))
    pool = (1 - ridge) * pool + ridge * scale + 1e-6 * np.eye(k)
    whiten, constant = [], []
    for w, s in zip(weights, covs, strict=True):
        cov = pool if s is None else (1 - pooled) * s + pooled * pool
        low = np.linalg.cholesky(cov)
        whiten.append(np.linalg.inv(low))
        constant.append(np.log((w + 1) / (sum(weights) + 2)) - np.log(np.diag(low)).sum())
    return Discriminant(np.array(means), np.array(whiten), np.array(constant))


def trained(docs: DataFrame, labels: DataFrame, rows: int = FIT_ROWS) -> Discriminant:
    """Fit on at most ``rows`` labelled documents, those whose ids have the smallest hashes; null labels don't count.

    Of several rows of one id the smallest text counts, a null one as empty.
    """
    known = labels.where("doc_id IS NOT NULL AND quality IN (0, 1)").groupBy("doc_id").agg(F.min("quality").alias("quality"))
    some = hash_sample(known, "doc_id", rows)
    ids = F.broadcast(some) if some.count() <= 2 * rows else some
    joined = docs.select("doc_id", "text").join(ids, "doc_id").groupBy("doc_id", "quality").agg(F.min("text").alias("text"))
    got = document_statistics(joined, ["quality"]).collect()  # at most the sampled ids' rows
    return fit(np.array([r.x for r in got]), np.array([r.quality for r in got]))


def scored(docs: DataFrame, model: Discriminant, keep: list[str], text_col: str = "text") -> DataFrame:
    """Columns ``keep`` with score (0 to 1) and predicted (1 from 0.5 on), for every row; null and empty texts too."""

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            x = np.array([statistics(t.as_py()) for t in b.column(b.num_columns - 1)]).reshape(-1, len(STATISTICS))
            s = model.score(x)
            cols = [*(b.column(i) for i in range(len(keep))), pa.array(s, pa.float64()), pa.array(s >= 0.5).cast(pa.int32())]
            yield pa.RecordBatch.from_arrays(cols, [*keep, "score", "predicted"])

    slim = docs.select(*keep, F.col(text_col).alias(unused(docs, "whole_text")))
    schema = docs.select(*keep).withColumns({"score": F.lit(0.0), "predicted": F.lit(0).cast("int")}).schema
    return slim.mapInArrow(work, schema)


def held_out() -> Column:
    return F.crc32(F.col("doc_id").cast("string").cast("binary")) % 3 == 1


def op6_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The quality score of every document by a model that saw no held-out label; see ``trained`` and ``scored``."""
    docs, labels = table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels")
    model = trained(docs, labels.where(~held_out()))
    return scored(docs, model, ["doc_id"]).select("doc_id", F.coalesce(held_out(), F.lit(False)).alias("held_out"), "score", "predicted")
