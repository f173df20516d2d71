"""Prefix scan, partition, median partition, extents and ranks over DataFrames."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from kdforest.shared import small, written

_OPS = {"sum": (F.sum, sum), "min": (F.min, min), "max": (F.max, max)}


def ranged(df: DataFrame, order: list[str], name: str = "range") -> tuple[DataFrame, list[int]]:
    """``df`` dealt into ranges of ``order`` with the range's number ``_part``, written so that it stays; rows per range."""
    parts = int(df.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    dealt = written(df.repartitionByRange(parts, *order).withColumn("_part", F.spark_partition_id()), name)
    counts = {r["_part"]: r.n for r in dealt.groupBy("_part").agg(F.count("*").alias("n")).collect()}  # a row per range
    return dealt, [counts.get(p, 0) for p in range(parts)]


def ranks(df: DataFrame, order: list[str]) -> DataFrame:
    """``df`` and ``rank`` from 0 by ``order`` over all rows, without one sort of all: ranges are sorted side by side."""
    dealt, counts = ranged(df, order)
    start = [sum(counts[:p]) for p in range(len(counts))]
    inside = Window.partitionBy("_part").orderBy(*order)
    at = F.get(F.array(*[F.lit(s).cast("long") for s in start]), F.col("_part"))
    return dealt.withColumn("rank", F.row_number().over(inside) - 1 + at).drop("_part")


def prefix_scan(df: DataFrame, order: list[str], value: str, op: str = "sum", identity: float = 0.0) -> tuple[DataFrame, float]:
    """``df`` and ``scan``, the combination of all values before a row; and that of all values.

    ``op`` is sum, min or max; the first row gets ``identity``. Ranges are combined first and each is scanned by itself.
    """
    agg, fold = _OPS[op]
    dealt, counts = ranged(df, order)
    totals = {r["_part"]: r.t for r in dealt.groupBy("_part").agg(agg(value).alias("t")).collect()}
    carried, so_far = [], identity
    for p in range(len(counts)):
        carried.append(so_far)
        if totals.get(p) is not None:
            so_far = fold([so_far, totals[p]])
    before = Window.partitionBy("_part").orderBy(*order).rowsBetween(Window.unboundedPreceding, -1)
    carry = F.get(F.array(*[F.lit(float(c)) for c in carried]), F.col("_part"))
    own = agg(F.col(value)).over(before)
    both = {"sum": own + carry, "min": F.least(own, carry), "max": F.greatest(own, carry)}[op]
    return dealt.withColumn("scan", F.coalesce(both, carry)).drop("_part"), so_far


def partition_around(df: DataFrame, column: str, pivot: float, order: list[str]) -> DataFrame:
    """``df`` with side (0 below ``pivot``, else 1) and position, stable by ``order``: all of side 0 before side 1."""
    sided = df.withColumn("side", (F.col(column) >= F.lit(pivot)).cast("int"))
    return ranks(sided, ["side", *order]).withColumnRenamed("rank", "position")


def median_partition(df: DataFrame, column: str, tie: str, group: list[str]) -> DataFrame:
    """``df`` with half: 0 for the lowest floor(n / 2) rows of each group by (column, tie), else 1; nulls are lowest, null groups are one.

    Rows are ranked over all groups at once, so a group of any size is spread over tasks.
    """
    ranked = written(ranks(df, [*group, column, tie]), "ranked")
    names = [f"_group{i}" for i in range(len(group))]
    while set(names) & set(df.columns):
        names = ["_" + n for n in names]
    per = written(ranked.groupBy(*group).agg(F.min("rank").alias("_start"), F.count("*").alias("_n")).toDF(*names, "_start", "_n"), "groups")
    same = [F.col(a).eqNullSafe(F.col(b)) for a, b in zip(group, names, strict=True)]
    joined = ranked.join(small(per, per.count()), reduce(lambda a, b: a & b, same))
    return joined.select(*df.columns, (F.col("rank") - F.col("_start") >= F.floor(F.col("_n") / 2)).cast("int").alias("half"))


def extent(df: DataFrame, columns: list[str], group: list[str]) -> DataFrame:
    """lo and hi of each column and n, per group, by one hash aggregate."""
    return df.groupBy(*group).agg(*[f(c).alias(f"{a}{j}") for j, c in enumerate(columns) for f, a in ((F.min, "lo"), (F.max, "hi"))], F.count("*").alias("n"))


def k_smallest(df: DataFrame, by: list[str], k: int, value: Column, tie: str) -> DataFrame:
    """The ``k`` rows of each group with the smallest (value, tie) and their rank from 1; cut before the shuffle."""
    ranked = df.withColumn("rank", F.row_number().over(Window.partitionBy(*by).orderBy(value, tie)))
    return ranked.where(F.col("rank") <= k)
