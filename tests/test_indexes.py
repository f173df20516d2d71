"""Indexes against brute force on small sets."""

import random

import pytest

from kdforest.operators import tree as kd
from kdforest.operators.baselines import FixedCells, RebuildAll, brute_knn
from kdforest.operators.forest import LogForest
from kdforest.queries import QUERIES
from kdforest.shared import local_table
from kdforest.sources.pointsets import point_set, points_from

SF = "/root/testdata/sf0.001"
SCHEMA = "point_id long, c0 double, c1 double, seq long"


def made(spark, rows):
    return local_table(spark, [(i, float(x), float(y), i) for i, x, y in rows], SCHEMA)


def nearest(points, queries, k):
    out = []
    for q, x, y in queries:
        best = sorted(((px - x) ** 2 + (py - y) ** 2, p) for p, px, py in points)[:k]
        out += [(q, r, p, d) for r, (d, p) in enumerate(best, 1)]
    return sorted(out)


def test_rebuilt_and_fixed_root(spark):
    first, second = made(spark, [(1, 1, 1), (2, 3, 3)]), made(spark, [(3, 5, 5), (4, 7, 7)])
    rebuilt, fixed = RebuildAll(spark, 2, "spatial", 1), FixedCells(spark, 2, "spatial", 1)
    for index in (rebuilt, fixed):
        index.insert(first)
        index.insert(second)
    root = lambda i: next(s[2:] for s in i.forest.splits if s[1] == 1)
    assert root(rebuilt) == (0, 4.0) and root(fixed) == (0, 2.0)
    assert fixed.forest.depth() > rebuilt.forest.depth()


def test_forest_under_updates(spark):
    rng = random.Random(5)
    rows = [(i, rng.randrange(12), rng.randrange(12)) for i in range(300)]  # many equal points
    queries = [(1000 + i, rng.random() * 12, rng.random() * 12) for i in range(15)]
    asked = kd.as_queries(made(spark, queries), 2)
    index, x = LogForest(spark, 2, 16, cap=24), 16
    live = {}
    for step, (kind, part) in enumerate([("in", rows[:90]), ("in", rows[90:220]), ("out", rows[40:200]), ("in", rows[220:]), ("out", rows[220:230])]):
        (index.insert if kind == "in" else index.delete)(made(spark, part), batch_id=step)
        for r in part:
            live.pop(r[0], None)
            if kind == "in":
                live[r[0]] = r
        s = index.state
        assert sorted(r.point_id for r in index.live().collect()) == sorted(live)
        assert 0 <= s.buffered < x and set(index.bits()) == set(s.slots)
        assert all(t.cap * 0.5 <= t.live <= t.cap for t in s.slots.values())
    before = index.state.version
    index.insert(made(spark, rows[:5]), batch_id=0)  # a batch that was seen
    assert index.state.version == before
    want = nearest(list(live.values()), queries, 7)
    for schedule, order in (("tree_serial", "desc"), ("tree_serial", "asc"), ("all_parallel", "desc"), ("query_outer", "desc")):
        assert sorted(map(tuple, index.knn(asked, 7, schedule, order).collect())) == want
    gone = {(r[1], r[2]) for r in rows[200:204]}
    index.delete(made(spark, rows[200:204]), key="coords")
    assert sorted(r.point_id for r in index.live().collect()) == sorted(i for i, r in live.items() if r[1:] not in gone)
    index.delete(index.live())
    assert index.mask == 0 and index.live().count() == 0 and index.knn(asked, 3).count() == 0


@pytest.mark.parametrize("metric", ["euclid", "l1", "linf"])
def test_search_and_metrics(spark, metric):
    rng = random.Random(2)
    points = made(spark, [(i, rng.random(), rng.random()) for i in range(200)])
    tree = kd.build(points.selectExpr("0 AS tree", "*"), 2, "spatial", 20)
    asked = kd.as_queries(points.where("point_id % 9 = 0"), 2)
    got = kd.ranked(kd.search(asked, tree, 4, metric, exclude_self=True), 4).collect()
    assert sorted(map(tuple, got)) == sorted(map(tuple, brute_knn(asked, points, 2, 4, metric, True).collect()))
    assert kd.ranked(kd.search(asked, tree, 300, metric), 300).where("query_id = 0").count() == 200


def test_bad_coordinates(spark):
    from kdforest.sources.pointsets import point_set, points_from

    rows = local_table(spark, [(1, 0.5), (2, None), (3, float("nan"))], "id long, x double")
    assert points_from(rows, "id", ["x"], bad="drop").count() == 1
    with pytest.raises(Exception, match="not finite"):
        points_from(rows, "id", ["x"]).collect()


def test_sixteen_dimensions_from_expressions(spark):
    """Queries whose coordinates are still expressions, which a planner of constraints cannot take in."""
    table = spark.range(120).selectExpr("id", "transform(sequence(1, 16), j -> cast(pmod(id * 7919 + j * j * 31 * id, 101) as double)) AS v")
    points = points_from(table, "id", [f"v[{j}]" for j in range(16)])
    f = kd.stored(kd.build(points.selectExpr("0 AS tree", "*"), 16, cap=16))
    queries = kd.as_queries(points.where("point_id % 10 = 0"), 16)
    key = lambda df: sorted((r.query_id, r["rank"], r.point_id, r.d2) for r in df.collect())
    got = key(kd.ranked(kd.search(queries, f, 4), 4))
    at = {r.point_id: [r[f"c{j}"] for j in range(16)] for r in points.collect()}
    want = []
    for q in range(0, 120, 10):
        best = sorted((sum((a - b) ** 2 for a, b in zip(at[q], at[p], strict=True)), p) for p in at)[:4]
        want += [(q, n, p, d) for n, (d, p) in enumerate(best, 1)]
    assert len(f.cells) > 1 and got == sorted(want)


@pytest.mark.parametrize("name", ["line3", "line5", "ol7", "dup2"])
def test_every_hundredth_row_is_asked(spark, name):
    points, d = point_set(spark, SF, name)
    stated = kd.as_queries(points.where("point_id % 100 = 0"), d)
    got = QUERIES[f"tree_knn_{name}"](spark, SF).collect()
    assert {r.query_id for r in got} == {r.query_id for r in stated.select("query_id").collect()}
    want = brute_knn(stated, points, d, 5).collect()
    assert sorted((r.query_id, r.rank, r.point_id) for r in got) == sorted((r.query_id, r.rank, r.point_id) for r in want)


def test_streams_against_the_whole_table(spark):
    events = spark.read.parquet(f"{SF}/events.parquet").selectExpr("*", "cast(ts as timestamp) as at").collect()
    times, want = {}, {}
    for r in events:
        times.setdefault(r.user_id, []).append(r.at.timestamp())
        for back in (0, 1):
            start = (r.at.timestamp() // 43200 - back) * 43200
            want.setdefault(start, []).append(r.value)
    sessions = []
    for user, at in times.items():
        start = last = None
        for t in sorted(at):
            if last is None or t >= last + 7200:
                sessions.append([user, t, 0])
            sessions[-1][2] += 1
            last = t
    got = QUERIES["stream_session_points"](spark, SF).collect()
    assert sorted((r.user_id, r.start.timestamp(), r.n) for r in got) == sorted(map(tuple, sessions))
    assert sum(r.n for r in got) == len(events)
    got = QUERIES["stream_window_extents"](spark, SF).collect()
    assert sorted((r.start.timestamp(), r.n, r.lo, r.hi) for r in got) == sorted((s, len(v), min(v), max(v)) for s, v in want.items())


def test_query_outer_takes_many_queries_through_trees(spark, monkeypatch):
    monkeypatch.setattr("kdforest.operators.baselines.BROADCAST_ROWS", 10)
    rng = random.Random(6)
    rows = [(i, rng.randrange(20), rng.randrange(20)) for i in range(150)]
    index = LogForest(spark, 2, 16, cap=24)
    index.insert(made(spark, rows[:120]))
    index.insert(made(spark, rows[120:]))
    index.delete(made(spark, rows[10:20]))
    queries = [(1000 + i, rng.random() * 20, rng.random() * 20) for i in range(25)]
    got = index.knn(kd.as_queries(made(spark, queries), 2), 4, "query_outer")
    assert sorted(map(tuple, got.collect())) == nearest(rows[:10] + rows[20:], queries, 4)
