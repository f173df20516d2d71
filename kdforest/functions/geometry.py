"""Distances, box bounds and bit masks as column expressions; all stay in generated code."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column
from pyspark.sql import functions as F


def coords(d: int, prefix: str = "c") -> list[str]:
    return [f"{prefix}{j}" for j in range(d)]


def combined(parts: list[Column], metric: str) -> Column:
    """Per-dimension distances as one value that orders like the distance: squares summed, sum, or largest; left to right."""
    if metric == "euclid":
        return reduce(lambda a, b: a + b, [x * x for x in parts])
    if metric == "l1":
        return reduce(lambda a, b: a + b, [F.abs(x) for x in parts])
    if metric == "linf":
        return F.greatest(*[F.abs(x) for x in parts]) if len(parts) > 1 else F.abs(parts[0])
    raise ValueError(f"no such metric: {metric}")


def dist2(d: int, metric: str = "euclid", a: str = "q", b: str = "c") -> Column:
    return combined([F.col(f"{a}{j}") - F.col(f"{b}{j}") for j in range(d)], metric)


def mind2(d: int, metric: str = "euclid", q: str = "q", lo: str = "lo", hi: str = "hi") -> Column:
    """Smallest distance from a point to a closed box; summed in the order of ``dist2``, so never above a member's."""
    gap = [F.greatest(F.col(f"{lo}{j}") - F.col(f"{q}{j}"), F.lit(0.0), F.col(f"{q}{j}") - F.col(f"{hi}{j}")) for j in range(d)]
    return combined(gap, metric)


def maxd2(d: int, metric: str = "euclid", q: str = "q", lo: str = "lo", hi: str = "hi") -> Column:
    far = [F.greatest(F.abs(F.col(f"{q}{j}") - F.col(f"{lo}{j}")), F.abs(F.col(f"{q}{j}") - F.col(f"{hi}{j}"))) for j in range(d)]
    return combined(far, metric)


def box_mind2(d: int, metric: str = "euclid") -> Column:
    """Smallest distance between the boxes (qlo, qhi) and (lo, hi)."""
    gap = [F.greatest(F.col(f"lo{j}") - F.col(f"qhi{j}"), F.lit(0.0), F.col(f"qlo{j}") - F.col(f"hi{j}")) for j in range(d)]
    return combined(gap, metric)


def next_pow2(x: Column) -> Column:
    """The smallest power of two that is at least ``x`` (a positive integer)."""
    return F.call_function("shiftleft", F.lit(1).cast("long"), F.length(F.bin(x.cast("long") - 1)).cast("int") - F.when(x == 1, 1).otherwise(0))


def mask_vanish(before: Column, after: Column) -> Column:
    return before.bitwiseAND(F.bitwise_not(after))


def mask_appear(before: Column, after: Column) -> Column:
    return after.bitwiseAND(F.bitwise_not(before))
