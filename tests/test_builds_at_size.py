"""Builds by spatial median: levels above a task's size, and what several builds share."""

import numpy as np
import pytest

from kdforest import queries
from kdforest.operators import tree as kd
from kdforest.shared import local_table


@pytest.mark.parametrize("steps", [4096, 0])
def test_rows_find_their_nodes(spark, monkeypatch, steps):
    """As ``Router``, in several trees, with equal values and equal points parted by id; without Python unless there are too many splits."""
    monkeypatch.setattr(kd, "STEPS", steps)
    splits = [(0, 1, 0, 5.0), (0, 2, 1, 3.0, 33), (0, 3, 2, 50.5), (0, 7, 1, 2.0), (1, 1, 1, 2.0)]
    nodes, starts = [(0, 4), (0, 5), (0, 14), (1, 3), (2, 9)], [(0, 1), (1, 1), (2, 9)]
    rows = [(i % 3, 9 if i % 3 == 2 else 1, i, float(i % 10), float(i % 7)) for i in range(200)]
    found = kd.placed(local_table(spark, rows, "tree int, node long, point_id long, c0 double, c1 double"), splits, starts, nodes, 2)
    tree, node, ids, *x = (np.array(c) for c in zip(*rows, strict=True))
    _, to = kd.Router(splits).down(tree, node, np.column_stack([*x, ids]))
    want = {i: nodes.index(k) if k in nodes else -1 for i, k in enumerate(zip(tree.tolist(), to.tolist(), strict=True))}
    assert {r.point_id: r.slot for r in found.collect()} == want and len(set(want.values())) == 6
    some = found.where("slot >= 0")
    assert sorted(r.point_id for r in some.collect()) == [i for i, s in want.items() if s >= 0]
    assert ("MapInArrow" in some._jdf.queryExecution().optimizedPlan().toString()) is not bool(steps)


def test_rows_of_a_build_are_made_once(spark):
    """What makes the rows of a spatial build runs once, whatever levels follow."""
    runs = spark.sparkContext.accumulator(0)

    def work(batches):
        for b in batches:
            runs.add(b.num_rows)
            yield b

    points = spark.range(500).selectExpr("0 AS tree", "id AS point_id", "cast(id % 40 AS double) AS c0", "cast(id AS double) AS c1", "id AS seq")
    f = kd.build(points.mapInArrow(work, points.schema), 2, "spatial", 20)
    assert f.points.count() == sum(c["n"] for c in f.cells) == 500 and runs.value == 500


def test_lineitem_is_numbered_once(spark, monkeypatch):
    made, number = [], queries.numbered_lineitem
    monkeypatch.setattr(queries, "numbered_lineitem", lambda *a: made.append(1) or number(*a))
    monkeypatch.setattr("kdforest.sources.pointsets.numbered_lineitem", lambda *a: pytest.fail("numbered again"))
    rows = {r.points: r.n for r in queries.QUERIES["w1_build"](spark, "/root/testdata/sf0.001").collect()}
    n = spark.read.parquet("/root/testdata/sf0.001/lineitem.parquet").count()
    assert rows["line3"] == rows["line5"] == rows["ol7"] == n and len(rows) == 9 and made == [1]
