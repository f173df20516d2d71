"""The experiment workloads over the point sets: construction, batches, neighbour graphs, mixed sections."""

from __future__ import annotations

import time
from collections.abc import Callable, Iterator

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from kdforest.operators import tree as kd
from kdforest.operators.baselines import FixedCells, RebuildAll
from kdforest.operators.forest import LogForest
from kdforest.operators.primitives import ranks

STRUCTURES = ("log-forest", "rebuild-all", "fixed-cells")
PRIME = 7919


def make(spark: SparkSession, name: str, d: int, rule: str = "object", x: int = 1024, cap: int = kd.CELL_CAP, **more) -> LogForest | RebuildAll | FixedCells:
    if name == "log-forest":
        return LogForest(spark, d, x, rule, cap, **more)
    return {"rebuild-all": RebuildAll, "fixed-cells": FixedCells}[name](spark, d, rule, cap)


def insert_slices(points: DataFrame, m: int) -> Iterator[DataFrame]:
    for i in range(m):
        yield points.where(F.pmod("point_id", F.lit(m)) == i)


def sized_slices(points: DataFrame, n: int, percent: int) -> Iterator[DataFrame]:
    """Consecutive cuts of ``percent`` of n in a fixed mixed order; the last may be short."""
    at = F.pmod(F.col("point_id") * PRIME, F.lit(n))
    step = max(1, n * percent // 100)
    for lo in range(0, n, step):
        yield points.where((at >= lo) & (at < lo + step))


def delete_slice(points: DataFrame, n: int, m: int, i: int) -> DataFrame:
    """Slice i of m of ids 0 to n - 1: each id in exactly one."""
    return points.where(F.floor(F.pmod(F.col("point_id") * PRIME, F.lit(n)) * m / n) == i)


def clock(run: Callable[[], object]) -> float:
    began = time.perf_counter()
    run()
    return time.perf_counter() - began


def done(df: DataFrame) -> None:
    df.write.format("noop").mode("overwrite").save()


def stepped(spark: SparkSession, points: DataFrame, d: int, structure: str, percent: int = 10, delete: bool = False, rule: str = "object", x: int = 1024, **more) -> tuple[object, list[dict]]:
    """The index and, per batch, its number, seconds, points moved and live ones: batches of ``percent`` inserted into an empty index, or deleted from a full one."""
    index = make(spark, structure, d, rule, x, **more)
    n, rows = points.count(), []
    if delete:
        index.insert(points)
    for i, b in enumerate(sized_slices(points, n, percent), start=1):
        took = clock(lambda: (index.delete if delete else index.insert)(b))  # noqa: B023
        moved = index.state.moved if structure == "log-forest" else index.moved
        size = min(n * percent // 100, n - (i - 1) * (n * percent // 100))
        rows.append({"structure": structure, "rule": rule, "percent": percent, "step": i, "n": size, "seconds": took, "moved": moved})
    return index, rows


def graph(spark: SparkSession, points: DataFrame, d: int, structure: str, k: int = 5, slices: int = 1, rule: str = "object", x: int = 1024, share: int = 1) -> dict:
    """Seconds of the neighbours of each ``share``-th point after one or several batches."""
    index = make(spark, structure, d, rule, x)
    for b in insert_slices(points, slices):
        index.insert(b)
    asked = points.where(F.pmod("point_id", F.lit(share)) == 0)
    n = asked.count()
    seconds = clock(lambda: done(index.knn(kd.as_queries(asked, d), k)))
    return {"structure": structure, "rule": rule, "k": k, "n": n, "seconds": seconds}


def mixed(spark: SparkSession, points: DataFrame, d: int, structure: str, k: int = 5, x: int = 1024, query_share: int = 1, inserts: int = 20, deletes: int = 15, every: int = 5, arrival: str = "hash", rule: str = "object") -> list[dict]:
    """Inserts of 5 %, a neighbour search after each five; then deletes of 5 %, likewise: seven sections with their results.

    ``query_share`` n takes each n-th point as a query. Arrival "sorted" inserts ranges of the first coordinate, which skews fixed cells.
    """
    index = make(spark, structure, d, rule, x)
    n = points.count()
    queries = kd.as_queries(points.where(F.pmod("point_id", F.lit(query_share)) == 0), d)
    if arrival == "sorted":
        placed = ranks(points, ["c0", "point_id"])
        slices = [placed.where(F.floor(F.col("rank") * inserts / n) == i).drop("rank") for i in range(inserts)]
    else:
        slices = list(insert_slices(points, inserts))
    steps = [("INS", i, b) for i, b in enumerate(slices)] + [("DEL", i, delete_slice(points, n, inserts, i)) for i in range(deletes)]
    sections, spent = [], 0.0
    for kind, i, batch in steps:
        spent += clock(lambda: index.insert(batch) if kind == "INS" else index.delete(batch))  # noqa: B023
        if i % every == every - 1:
            found: list = []
            search = clock(lambda: found.append(index.knn(queries, k).agg(F.count("*").alias("n"), F.sum("rank").alias("ranks"), F.sum("point_id").alias("ids")).first()))  # noqa: B023
            sections.append({"structure": structure, "section": f"{kind}{i // every}", "knn_s": search, "total_s": spent + search, "live": index.live().count(), "found": found[0].n, "ids": found[0].ids})
            spent = 0.0
    return sections
