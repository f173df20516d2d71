"""Bloom filters of trees as rows of 64 bits: built by one aggregate, probed by one equi join for all trees."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from kdforest.shared import small


def _places(keys: list[str], bits: Column, hashes: int) -> Column:
    return F.explode(F.array(*[F.pmod(F.xxhash64(F.lit(s), *keys), bits) for s in range(hashes)])).alias("place")


def bits_for(n: int, per_key: int = 10) -> int:
    return max(64, 1 << (per_key * max(1, n) - 1).bit_length())


def build(points: DataFrame, keys: list[str], bits: int, hashes: int = 3) -> DataFrame:
    """(tree, word, bits) over the trees of ``points``; words without a bit have no row."""
    placed = points.select("tree", _places(keys, F.lit(bits), hashes))
    bit = F.call_function("shiftleft", F.lit(1).cast("long"), (F.col("place") % 64).cast("int"))
    return placed.groupBy("tree", F.floor(F.col("place") / 64).alias("word")).agg(F.bit_or(bit).alias("bits"))


def candidates(batch: DataFrame, filters: DataFrame, keys: list[str], sizes: dict[int, int], hashes: int = 3, rows: int | None = None) -> DataFrame:
    """(tree, *keys): the distinct keys of ``batch`` that each tree may hold; none that it holds is missing. ``sizes``: bits by tree.

    A batch of ``rows`` rows has as many places for each tree and hash, which Spark's guess of its size leaves out.
    """
    trees = F.explode(F.array(*[F.struct(F.lit(t).alias("tree"), F.lit(n).cast("long").alias("m")) for t, n in sizes.items()]))
    each = batch.select(*keys).distinct().select(*keys, trees.alias("t")).select(*keys, "t.tree", "t.m")
    placed = each.select(*keys, "tree", _places(keys, F.col("m"), hashes)).withColumn("word", F.floor(F.col("place") / 64))
    placed = placed.hint("merge") if rows is None else small(placed, rows * len(sizes) * hashes)
    hit = placed.join(filters, ["tree", "word"]).where(F.getbit(F.col("bits"), (F.col("place") % 64).cast("int")) == 1)
    return hit.groupBy("tree", *keys).agg(F.count("*").alias("n")).where(F.col("n") >= hashes).drop("n")
