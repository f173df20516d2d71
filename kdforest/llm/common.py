"""What the text operators share: loading, shared scratch tables, bounded samples, small joins."""

from __future__ import annotations

import ctypes
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from kdforest.shared import scratch_path, written

__all__ = ["given_back", "hash_sample", "maybe_broadcast", "scratch_path", "table", "unused", "written"]

#: Sides up to this many rows of a few dozen bytes may be broadcast; larger ones are joined by shuffle.
BROADCAST_ROWS = 100_000


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def given_back(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """``batches``; what a task has freed at its end goes back to the system, for workers wait for later tasks and keep it."""
    try:
        yield from batches
    finally:
        pa.default_memory_pool().release_unused()
        trim = getattr(ctypes.CDLL(None), "malloc_trim", None)
        if trim:
            trim(0)


def unused(df: DataFrame, name: str) -> str:
    """``name``, with underscores before it until no column of ``df`` has it."""
    taken = {c.lower() for c in df.columns}
    while name.lower() in taken:
        name = "_" + name
    return name


def hash_sample(df: DataFrame, key: str, rows: int) -> DataFrame:
    """At least ``rows`` rows of ``df`` (ties aside, exactly), or all: those with the smallest hash of ``key``."""
    h = F.xxhash64(F.col(key).cast("string"))
    cut = df.select(h.alias("h")).orderBy("h").limit(rows).agg(F.max("h")).first()[0]
    return df if cut is None else df.where(h <= F.lit(cut))


def maybe_broadcast(df: DataFrame, limit: int = BROADCAST_ROWS) -> DataFrame:
    """``df`` with a broadcast hint if a count proves that it is small, else unchanged."""
    return F.broadcast(df) if df.limit(limit + 1).count() <= limit else df
