"""Tests of the second round's findings."""

import random

import pytest
from pyspark.sql import functions as F

from kdforest.operators import baselines, bloom
from kdforest.operators import tree as kd
from kdforest.plans.veb import positions
from kdforest.queries import QUERIES
from kdforest.shared import local_table, written
from kdforest.sources.pointsets import point_set, points_from

SCHEMA = "point_id long, c0 double, c1 double, seq long"


def made(spark, rows):
    return local_table(spark, [(i, float(x), float(y), i) for i, x, y in rows], SCHEMA)


def test_layout_of_the_orders(spark):
    keys = sorted(r.o_orderkey for r in spark.read.parquet("/root/testdata/sf0.001/orders.parquet").select("o_orderkey").collect())
    levels = len(keys).bit_length()
    want = [(k, levels, n, p) for n, (k, p) in enumerate(zip(keys, positions(levels), strict=False), 1)]
    assert sorted(map(tuple, QUERIES["veb_layout"](spark, "/root/testdata/sf0.001").collect())) == want


@pytest.mark.parametrize("exclude_self", [False, True])
def test_brute_force_of_many_queries(spark, monkeypatch, exclude_self):
    """More queries than may be broadcast, in several blocks; many equal distances."""
    for name, n in (("BROADCAST_ROWS", 10), ("QUERY_BLOCK", 30), ("POINT_BLOCK", 40)):
        monkeypatch.setattr(baselines, name, n)
    rng = random.Random(4)
    rows = [(i, rng.randrange(9), rng.randrange(9)) for i in range(150)]
    got = baselines.brute_knn(kd.as_queries(made(spark, rows[:70]), 2), made(spark, rows), 2, 4, exclude_self=exclude_self)
    want = []
    for q, x, y in rows[:70]:
        best = sorted(((px - x) ** 2 + (py - y) ** 2, p) for p, px, py in rows if not (exclude_self and p == q))[:4]
        want += [(q, r, p, float(d)) for r, (d, p) in enumerate(best, 1)]
    assert sorted(map(tuple, got.collect())) == sorted(want)


def test_plans_of_fixed_cells_stay_small(spark):
    """The plan of the points names no cell by a literal, and points are right after many splits, deletes and returns."""
    rng = random.Random(8)
    rows = [(i, rng.randrange(50), rng.randrange(50)) for i in range(480)]
    index, live = baselines.FixedCells(spark, 2, cap=10), {}
    for i in range(4):
        index.insert(made(spark, rows[i * 120 : i * 120 + 120]))
        live |= {r[0]: r for r in rows[i * 120 : i * 120 + 120]}
    index.delete(made(spark, rows[30:150]))
    index.insert(made(spark, [(i, x + 3, y) for i, x, y in rows[30:60]]))
    live = {k: v for k, v in live.items() if not 30 <= k < 150} | {i: (i, x + 3, y) for i, x, y in rows[30:60]}
    assert sorted((r.point_id, r.c0, r.c1) for r in index.live().select("point_id", "c0", "c1").collect()) == sorted((i, float(x), float(y)) for i, x, y in live.values())
    plan = index.forest.points._jdf.queryExecution().analyzed().toString()
    assert " IN (" not in plan and plan.count("Filter") <= 1


def test_coordinates_are_judged_by_themselves(spark):
    """The check of one coordinate names no other, for constraints over all of them double with each that is renamed; a bad one is still an error."""
    points, _ = point_set(spark, "/root/testdata/sf0.001", "emb16")
    plan = points.select("c0")._jdf.queryExecution().optimizedPlan().toString()
    assert "[0]" in plan and "[1]" not in plan
    for bad in (None, float("nan"), float("-inf")):
        rows = local_table(spark, [(1, 0.5, bad)], "id long, x double, y double")
        with pytest.raises(Exception, match="not finite"):
            points_from(rows, "id", ["x", "y"]).collect()
        assert points_from(rows, "id", ["x", "y"], bad="drop").count() == 0


def test_a_join_of_known_size_is_not_sent_along(spark):
    """A batch times trees and hashes beyond the limit is merged, however small Spark takes its files for; a small one still goes along."""
    sizes = {t: bloom.bits_for(20_000) for t in range(3)}
    points = written(spark.range(20_000).select(F.explode(F.array(F.lit(0), F.lit(1), F.lit(2))).alias("tree"), F.col("id").alias("point_id")), "points")
    filters = written(bloom.build(points, ["point_id"], sizes[0]), "bloom")
    for n, sent in ((6000, False), (100, True)):
        batch = written(points.where(f"tree = 0 and point_id < {n}").select("point_id"), "batch")
        found = bloom.candidates(batch, filters, ["point_id"], sizes, 3, n)
        plan = found._jdf.queryExecution().sparkPlan().toString()
        assert ("BroadcastHashJoin" in plan) is sent and ("SortMergeJoin" in plan) is not sent
        assert found.count() >= 3 * n
