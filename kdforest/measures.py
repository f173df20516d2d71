"""Cost and accuracy measures of the indexes."""

from __future__ import annotations

import time
import uuid
from collections.abc import Callable
from statistics import median

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from kdforest.operators.forest import LogForest


def timed(run: Callable[[], object], warmup: int = 1, runs: int = 3) -> float:
    """Median seconds of ``runs`` after ``warmup``."""
    took = []
    for i in range(warmup + runs):
        began = time.perf_counter()
        run()
        if i >= warmup:
            took.append(time.perf_counter() - began)
    return median(took)


class CostMeter:
    """Counts what Spark ran inside a ``with``: jobs and stages (a bound on the chain of dependent steps, ``depth``) and tasks.

    ``work`` adds the rows that the caller reports, such as points moved or probed.
    """

    def __init__(self, spark: SparkSession):
        self.context, self.group = spark.sparkContext, uuid.uuid4().hex
        self.work = self.jobs = self.stages = self.tasks = 0

    def __enter__(self) -> CostMeter:
        self.context.setJobGroup(self.group, "measured")
        return self

    def add(self, rows: int) -> None:
        self.work += rows

    def __exit__(self, *_: object) -> None:
        tracker = self.context.statusTracker()
        jobs = [j for j in map(tracker.getJobInfo, tracker.getJobIdsForGroup(self.group)) if j]
        stages = [s for j in jobs for s in map(tracker.getStageInfo, j.stageIds) if s]
        self.jobs, self.stages, self.tasks = len(jobs), len(stages), sum(s.numTasks for s in stages)
        self.context.setLocalProperty("spark.jobGroup.id", None)

    @property
    def depth(self) -> int:
        return self.stages


def curve(rows: list[dict], x: str, n: str = "n", seconds: str = "seconds") -> list[tuple]:
    """(x, throughput) by x: one of the curves over threads, batch sizes or k."""
    return sorted((r[x], throughput(r[n], r[seconds])) for r in rows)


def speedups(rows: list[dict], threads: str = "threads", seconds: str = "seconds") -> dict:
    """Seconds on the fewest threads over those on the most, their mean and largest, by all other fields."""
    by: dict[tuple, dict] = {}
    for r in rows:
        key = tuple(sorted((k, v) for k, v in r.items() if k not in (threads, seconds) and isinstance(v, str)))
        by.setdefault(key, {})[r[threads]] = r[seconds]
    each = {k: speedup(v[min(v)], v[max(v)]) for k, v in by.items() if len(v) > 1}
    return {"each": each, "mean": sum(each.values()) / max(1, len(each)), "largest": max(each.values(), default=0.0)}


def throughput(n: int, seconds: float) -> float:
    return n / seconds if seconds else float("inf")


def speedup(one_thread: float, all_threads: float) -> float:
    return one_thread / all_threads


def recall(got: DataFrame, truth: DataFrame) -> DataFrame:
    """One row: truth, found and recall over (query_id, point_id)."""
    hit = truth.join(got.select("query_id", "point_id").withColumn("hit", F.lit(1)), ["query_id", "point_id"], "left")
    return hit.agg(F.count("*").alias("truth"), F.count("hit").alias("found")).withColumn("recall", F.col("found") / F.col("truth"))


def bloom_report(index: LogForest, members: DataFrame, strangers: DataFrame) -> tuple[int, float]:
    """Members that no tree's filter lets pass (must be 0), and the share of strangers that some filter lets pass."""
    keys = [f"c{j}" for j in range(index.d)]
    passed = index.prefiltered(members).select(*keys).distinct()
    missing = members.join(passed, keys, "left_anti").count()
    n = strangers.count()
    return missing, index.prefiltered(strangers).select(*keys).distinct().count() / max(1, n)


def balance(cells: list[dict]) -> dict[str, float]:
    sizes = [c["n"] for c in cells]
    return {"cells": len(sizes), "largest": max(sizes, default=0), "mean": sum(sizes) / max(1, len(sizes)), "depth": max((c["node"].bit_length() for c in cells), default=0)}


def write_amplification(index: LogForest) -> float:
    """Points moved into new trees per point inserted."""
    inserted = sum(h["rows"] for h in index.history if h["kind"] == "insert")
    return sum(h["moved"] for h in index.history) / max(1, inserted)


def forest_shape(mask: int, n: int, x: int) -> tuple[int, int]:
    """Trees, and the most there can be after inserts only."""
    return mask.bit_count(), (n // x).bit_length()


def histogram(values: DataFrame, column: str, key: str) -> DataFrame:
    """Per ``key``: rows, distinct values (exact and estimated), quartiles (exact and sketched), smallest and largest."""
    q = F.array(*[F.lit(x) for x in (0.25, 0.5, 0.75)])
    return values.groupBy(key).agg(
        F.count(column).alias("n"), F.countDistinct(column).alias("distinct"), F.approx_count_distinct(column, 0.02).alias("about"), F.percentile(column, q).alias("quartiles"), F.percentile_approx(column, [0.25, 0.5, 0.75]).alias("sketched"), F.min(column).alias("lo"), F.max(column).alias("hi")
    )


def rolled_up(rows: DataFrame, dims: list[str], value: str) -> DataFrame:
    """Sums of ``value`` over the leading subsets of ``dims``."""
    return rows.rollup(*dims).agg(F.sum(value).alias("total"), F.grouping_id(*dims).cast("long").alias("level"))


def grouped_sets(rows: DataFrame, sets: list[list[str]], dims: list[str], value: str) -> DataFrame:
    """Sums of ``value`` over chosen subsets of ``dims``."""
    return rows.groupingSets([[F.col(c) for c in s] for s in sets], *dims).agg(F.sum(value).alias("total"), F.grouping_id().cast("long").alias("level"))


def subtotals(rows: DataFrame, dims: list[str], value: str) -> DataFrame:
    """Sums and counts of ``value`` over every subset of ``dims``."""
    return rows.cube(*dims).agg(F.sum(value).alias("total"), F.count(value).alias("n"), F.grouping_id(*dims).cast("long").alias("level"))


def wide(rows: DataFrame, down: str, across: str, names: list[str], value: str) -> DataFrame:
    """A row per ``down``, a column per name of ``across``."""
    return rows.groupBy(down).pivot(across, names).agg(F.sum(value))
