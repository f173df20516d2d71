"""Primitives, queries around the indexes, saved versions, sources, functions, streams and measures on small tables."""

import random

import pytest
from pyspark.sql import functions as F

from kdforest import measures, workloads
from kdforest.functions import udfs
from kdforest.operators import primitives, spatial
from kdforest.operators import tree as kd
from kdforest.operators.baselines import FixedCells, RebuildAll, brute_knn
from kdforest.operators.forest import LogForest
from kdforest.plans.veb import positions
from kdforest.shared import local_table
from kdforest.sources import index_source, pointsets
from kdforest.streaming import updates

from .test_indexes import made, nearest


def test_primitives_with_nulls_and_ties(spark):
    rows = [("a", 1.0, 1), ("a", 1.0, 2), ("a", None, 3), (None, 5.0, 4), (None, 2.0, 5), ("b", 7.0, 6)]
    df = local_table(spark, rows, "g string, v double, id long")
    half = {r.id: r.half for r in primitives.median_partition(df, "v", "id", ["g"]).collect()}
    assert half == {3: 0, 1: 1, 2: 1, 5: 0, 4: 1, 6: 1}
    assert primitives.median_partition(df.limit(0), "v", "id", ["g"]).count() == 0
    assert [r["rank"] for r in primitives.ranks(df, ["id"]).orderBy("id").collect()] == list(range(6))
    scan, total = primitives.prefix_scan(df.where("v IS NOT NULL"), ["id"], "v")
    assert total == 16.0 and [r.scan for r in scan.orderBy("id").collect()] == [0.0, 1.0, 2.0, 7.0, 9.0]
    assert primitives.prefix_scan(df.limit(0), ["id"], "v")[1] == 0.0


def test_queries_around(spark):
    points = made(spark, [(1, 0, 0), (2, 0, 0), (3, 3, 4)])
    queries = kd.as_queries(points, 2)
    pairs = lambda r: sorted((x.query_id, x.point_id) for x in spatial.radius_join(queries, points, 2, r).collect())
    assert pairs(0.0) == [(1, 1), (1, 2), (2, 1), (2, 2), (3, 3)] and len(pairs(5.0)) == 9
    a = local_table(spark, [(1, 1.0), (2, 4.0), (3, None)], "a long, x double").withColumn("_bucket", F.lit("kept"))
    b = local_table(spark, [(1, 1.0), (2, 4.5)], "b long, y double")
    assert [(r.a, r.b, r["_bucket"]) for r in spatial.interval_join(a, b, "x", "y", 0.0).collect()] == [(1, 1, "kept")]
    assert spatial.interval_join(a, b, "x", "y", 0.5).count() == 2
    left = local_table(spark, [(1, 5), (None, 5), (2, 1)], "k long, t long")
    right = local_table(spark, [(1, 5, 9), (1, 6, 8), (None, 2, 7)], "k long, t long, v long")
    assert {(r.k, r.asof_v) for r in spatial.asof(left, right, ["k"], "t", "v").collect()} == {(1, 9), (None, 7), (2, None)}


@pytest.mark.parametrize("along", [50_000, 0])
def test_search_beyond_tables_that_go_along(spark, monkeypatch, along):
    """Many equal points, parted by id; with ``along`` 0 every walk is by joins. Some cells have many queries."""
    monkeypatch.setattr(kd, "ALONG", along)
    monkeypatch.setattr(kd, "QUERY_BLOCK", 7)
    rng = random.Random(9)
    rows = [(i, rng.randrange(5), rng.randrange(5)) for i in range(160)] + [(500 + i, 2, 2) for i in range(90)]
    queries = [(1000 + i, rng.randrange(6), rng.random() * 6) for i in range(40)]
    points = made(spark, rows)
    tree = kd.stored(kd.build(points.selectExpr("0 AS tree", "*"), 2, "object", 20))
    assert max(c["n"] for c in tree.cells) <= 20
    for fill in (True, False):
        got = kd.ranked(kd.search(kd.as_queries(made(spark, queries), 2), tree, 6, fill=fill), 6)
        assert sorted(map(tuple, got.collect())) == nearest(rows, queries, 6)
    assert sorted(map(tuple, spatial.dual_search(kd.as_queries(made(spark, queries), 2), tree, 6, 8).collect())) == nearest(rows, queries, 6)
    gone = kd.erase(tree, made(spark, [(9000, 2, 2)]), 1, "coords")
    assert sorted(r.point_id for r in gone.collect()) == sorted(r[0] for r in rows if r[1:] == (2, 2))


def test_deleted_points_come_again(spark):
    first, moved = [(i, i, i % 3) for i in range(10)], [(3, 50, 50)]
    queries = [(100, 50, 50), (101, 3, 0)]
    live = [r for r in first if r[0] != 3] + moved
    for index in (FixedCells(spark, 2, cap=4), RebuildAll(spark, 2, cap=4), LogForest(spark, 2, 4, cap=4)):
        index.insert(made(spark, first))
        index.delete(made(spark, [first[3]]))
        index.insert(made(spark, moved))
        assert sorted(r.point_id for r in index.live().collect()) == list(range(10))
        assert sorted(map(tuple, index.knn(kd.as_queries(made(spark, queries), 2), 3).collect())) == nearest(live, queries, 3)


def test_fixed_cells_touch_what_overflows(spark):
    index = FixedCells(spark, 2, "spatial", 8)
    index.insert(made(spark, [(i, i, 0) for i in range(32)]))
    before = {c["node"]: c["n"] for c in index.forest.cells}
    index.insert(made(spark, [(100 + i, 0.5, i / 10) for i in range(8)]))
    after = {c["node"]: c["n"] for c in index.forest.cells}
    changed = {n for n in before if after.get(n) != before[n]}
    assert len(changed) == 1 and index.moved < 32 and sum(after.values()) == 40


def test_saved_versions(spark, tmp_path):
    root, rng = f"file://{tmp_path}/index", random.Random(1)
    rows = [(i, rng.random(), rng.random()) for i in range(60)]
    index = LogForest(spark, 2, 8, cap=8)
    index.insert(made(spark, rows[:40]), batch_id="a")
    assert index.save(root) == 1
    index.delete(made(spark, rows[:7]))
    index.insert(made(spark, rows[40:]))
    assert index.save(root) == 3
    ids = lambda df: sorted(r.point_id for r in df.select("point_id").collect())
    old, new = LogForest.load(spark, root, 1), LogForest.load(spark, root)
    assert ids(old.live()) == list(range(40)) and ids(new.live()) == list(range(7, 60))
    new.insert(made(spark, rows[:3]), batch_id="a")  # seen before it was saved
    new.insert(made(spark, rows[:3]))
    queries = [(900, 0.5, 0.5), (901, 0.1, 0.9)]
    assert sorted(map(tuple, new.knn(kd.as_queries(made(spark, queries), 2), 4).collect())) == nearest(rows[:3] + rows[7:], queries, 4)
    index_source.register(spark)
    read = lambda v: spark.read.format("kdforest").option("version", v).load(root)
    assert ids(read(1)) == list(range(40)) and ids(read(3)) == list(range(7, 60))
    some = read(3).where("c0 BETWEEN 0.25 AND 0.5 AND c1 > 0.5")
    assert ids(some) == sorted(i for i, x, y in rows[7:] if 0.25 <= x <= 0.5 and y > 0.5)
    with pytest.raises(ValueError, match="no such version"):
        LogForest.load(spark, root, 9)
    new.compact()
    assert new.state.tombs is None and ids(new.live()) == [0, 1, 2, *range(7, 60)]
    assert new.vacuum() > 0 and ids(new.live()) == [0, 1, 2, *range(7, 60)]
    spark.udtf.register("kd_forest_info", udfs.ForestInfo)
    info = {r.tree: r.live for r in spark.sql(f"SELECT * FROM kd_forest_info('{root}')").collect()}
    assert info.pop(-1) == index.state.buffered and info == {i: s.live for i, s in index.state.slots.items()}


def test_files_and_scales(spark, tmp_path):
    points = made(spark, [(1, 0, 5), (2, 10, 5), (3, 5, 5)])
    for fmt in pointsets.FORMATS:
        pointsets.write_points(points, f"file://{tmp_path}/{fmt}", fmt)
        back = pointsets.read_points(spark, f"file://{tmp_path}/{fmt}", fmt, "point_id long, c0 double, c1 double, seq long", "point_id", ["c0", "c1"])
        assert sorted((r.point_id, r.c0, r.c1) for r in back.collect()) == [(1, 0.0, 5.0), (2, 10.0, 5.0), (3, 5.0, 5.0)]
    assert sorted((r.c0, r.c1) for r in pointsets.scaled(points, 2).collect()) == [(0.0, 0.0), (0.5, 0.0), (1.0, 0.0)]
    assert sum(r.c0 for r in pointsets.scaled(points, 2, "zscore").collect()) == pytest.approx(0)
    odd = local_table(spark, [(1, '{"page": "x"}'), (2, "no json"), (3, None)], "id long, props string")
    assert [r.page for r in pointsets.payload(odd, "page string").orderBy("id").collect()] == ["x", None, None]


def test_sql_functions(spark):
    udfs.register(spark, 2, 2)
    assert spark.sql("SELECT kd_dist2(0, 0, 3, 4) AS d").first().d == 25.0
    assert [r.position for r in spark.sql("SELECT * FROM kd_veb_layout(4)").collect()] == list(positions(4))
    spark.createDataFrame([(1, 2.0, 7), (1, 1.0, 9), (1, 1.0, 8)], "q long, d2 double, point_id long").createOrReplaceTempView("candidates")
    assert spark.sql("SELECT kd_topk(d2, point_id) AS ids FROM candidates GROUP BY q").first().ids == [8, 9]
    rows = [(None, 1, 0.0, 0.0), (None, 2, 1.0, 0.0), (None, 3, 9.0, 9.0), (50, None, 0.2, 0.0)]
    spark.createDataFrame(rows, "query_id long, point_id long, c0 double, c1 double").createOrReplaceTempView("cell")
    got = spark.sql("SELECT * FROM kd_knn_in_cell(TABLE(cell) WITH SINGLE PARTITION)").collect()
    assert [(r.query_id, r.point_id) for r in got] == [(50, 1), (50, 2)]
    route = udfs.route_udf([(1, 0, 5.0), (3, 1, 2.0)])
    at = spark.createDataFrame([([1.0, 9.0],), ([6.0, 1.0],), ([6.0, 2.0],)], "x array<double>")
    assert [r.n for r in at.select(route("x").alias("n")).collect()] == [2, 6, 7]


def test_streams_in_several_batches(spark, tmp_path):
    rows = [(i, f"2024-01-01 {i // 4:02d}:{15 * (i % 4):02d}:00", i % 3, float(i % 7)) for i in range(40)]
    rows[20] = (20, "2024-01-01 00:01:00", 2, 6.0)  # hours late
    table = spark.createDataFrame(rows, "event_id long, t string, user_id long, value double").selectExpr("event_id", "cast(t AS timestamp) AS ts", "user_id", "value")
    for b in range(4):
        table.where(F.col("event_id").between(10 * b, 10 * b + 9)).coalesce(1).write.parquet(f"file://{tmp_path}/events{b}.parquet")
    stream = lambda: updates.event_stream(spark, f"file://{tmp_path}", 1) if (tmp_path / "events.parquet").exists() else spark.readStream.schema(table.schema).option("maxFilesPerTrigger", 1).parquet(f"file://{tmp_path}/events*.parquet")
    late, seen = updates.LateRows(spark, "ts", 3600.0), []
    updates.run_once(stream(), "late", lambda batch, i: seen.extend(r.event_id for r in late.on_time(batch, i).collect()))
    assert [r.event_id for r in late.table().collect()] == [20] and sorted(seen) == [i for i in range(40) if i != 20]
    index = LogForest(spark, 2, 8, cap=8)
    index.insert(made(spark, [(i, i, i) for i in range(20)]))
    ask = lambda b: b.select(F.col("event_id").alias("query_id"), F.col("value").alias("q0"), F.col("value").alias("q1"))
    got = updates.neighbours(stream(), "asked", index, 1, ask).collect()
    assert {r.query_id: r.point_id for r in got} == {r[0]: int(r[3]) for r in rows}
    assert len({r.batch for r in got}) == 4
    points = stream().selectExpr("user_id", "event_id AS point_id", "value AS c0", "ts")
    near = {r.point_id: (r.user_id, r.neighbour, r.d2) for r in updates.to_table(updates.per_key_nearest(points, "user_id", ["c0"], "ts"), "per_key").collect()}
    assert len(near) == 40 and {u for u, n, _ in near.values() if n is None} == {0, 1, 2}
    for i, _, user, v in rows:
        if i < 20 and near[i][1] is not None:
            best = min(((v - w) ** 2, j) for j, _, u, w in rows if u == user and j < i)
            assert (near[i][2], near[i][1]) == best


def test_measures(spark):
    points = made(spark, [(i, i % 10, i // 10) for i in range(100)])
    with measures.CostMeter(spark) as meter:
        assert points.repartition(2).count() == 100
        meter.add(100)
    assert meter.jobs >= 1 and meter.depth >= 1 and meter.tasks >= 2 and meter.work == 100
    index, rows = workloads.stepped(spark, points, 2, "log-forest", 30, x=16)
    assert [r["n"] for r in rows] == [30, 30, 30, 10] and index.live().count() == 100
    assert measures.write_amplification(index) > 0
    assert measures.forest_shape(index.mask, 100, 16)[0] <= measures.forest_shape(index.mask, 100, 16)[1]
    queries = kd.as_queries(points.where("point_id % 9 = 0"), 2)
    row = measures.recall(index.knn(queries, 3), brute_knn(queries, points, 2, 3)).first()
    assert row.recall == 1.0 and row.truth == 36
    timing = [{"structure": "a", "threads": t, "seconds": 8.0 / t, "n": 80} for t in (1, 2, 4)]
    assert measures.speedups(timing) == {"each": {(("structure", "a"),): 4.0}, "mean": 4.0, "largest": 4.0}
    assert measures.curve(timing, "threads") == [(1, 10.0), (2, 20.0), (4, 40.0)]
    h = measures.histogram(points.withColumn("g", F.lit("x")), "c0", "g").first()
    assert (h.n, h.distinct, h.lo, h.hi, h.quartiles[1]) == (100, 10, 0.0, 9.0, 4.5)
    two = points.selectExpr("point_id % 2 AS a", "point_id % 3 AS b", "1 AS n")
    assert measures.rolled_up(two, ["a", "b"], "n").count() == 9 and measures.grouped_sets(two, [["a"], ["b"]], ["a", "b"], "n").count() == 5
    assert measures.timed(lambda: None, 0, 1) >= 0 and measures.balance(kd.build(points.selectExpr("0 AS tree", "*"), 2, "object", 25).cells) == {"cells": 4, "largest": 25, "mean": 25.0, "depth": 3}
