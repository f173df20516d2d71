"""Builds with exact medians, on nodes split over all tasks and inside one, against a plain halving of all rows."""

import random

import pytest

from kdforest.operators import tree as kd
from kdforest.queries import QUERIES
from kdforest.shared import local_table

SCHEMA = "point_id long, c0 double, c1 double, seq long"


def plain(rows, rule, cap, levels, ties):
    """{node: ids} of halving in the depth's dimension."""
    out, todo = {}, [(1, rows)]
    while todo:
        node, some = todo.pop()
        depth = node.bit_length() - 1
        if not some:
            continue
        if len(some) <= cap or depth >= levels:
            out[node] = sorted(r[0] for r in some)
            continue
        key = (lambda r, j=1 + depth % 2: (r[j], r[0])) if ties else (lambda r, j=1 + depth % 2: r[j])
        values = sorted(map(key, some))
        cut = values[len(values) // 2] if rule == "object" else (values[0] + values[-1]) / 2
        todo += [(2 * node, [r for r in some if key(r) < cut]), (2 * node + 1, [r for r in some if key(r) >= cut])]
    return out


@pytest.mark.parametrize(("rule", "ties"), [("object", False), ("object", True), ("spatial", False)])
@pytest.mark.parametrize("task_bytes", [24 << 20, 8 * 5 * 60])
def test_exact_cells(spark, monkeypatch, rule, ties, task_bytes):
    monkeypatch.setattr(kd, "TASK_BYTES", task_bytes)
    monkeypatch.setattr(kd, "SAMPLE", 100)
    rng = random.Random(3)
    rows = [(i, float(min(rng.randrange(40), 12)), rng.random() ** 3) for i in range(1000)]  # most c0 are one value
    points = local_table(spark, [(*r, r[0]) for r in rows], SCHEMA)
    f = kd.build(points.selectExpr("0 AS tree", "*"), 2, rule, 20, exact=True, levels=7, cycle=True, ties=ties)
    want = plain(rows, rule, 20, 7, ties)
    got = {}
    for r in f.points.select("node", "point_id").collect():
        got.setdefault(r.node, []).append(r.point_id)
    assert {n: sorted(v) for n, v in got.items()} == want
    assert {c["node"]: c["n"] for c in f.cells} == {n: len(v) for n, v in want.items()}
    if ties:
        assert max(map(len, want.values())) - min(map(len, want.values())) <= 1


def test_balance_beyond_the_sample(spark, monkeypatch):
    monkeypatch.setattr(kd, "SAMPLE", 700)
    assert all(r.fits for r in QUERIES["w12_balance"](spark, "/root/testdata/sf0.01").collect())


def test_deletes_by_coordinates_on_both_sides_of_a_tie(spark):
    rows = [(i, float(i % 3), 1.0) for i in range(60)]
    points = local_table(spark, [(*r, r[0]) for r in rows], SCHEMA).selectExpr("0 AS tree", "*")
    f = kd.build(points, 2, "object", 8, exact=True, ties=True)
    gone = kd.erase(f, points.where("point_id = 1").drop("tree"), 1, "coords").collect()
    assert sorted(r.point_id for r in gone) == [r[0] for r in rows if r[1] == 1.0]
