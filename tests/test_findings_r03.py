"""Tests of the third round's findings."""

import random

import numpy as np
import pytest

from kdforest.operators import baselines
from kdforest.operators import cells as inside
from kdforest.operators import tree as kd
from kdforest.queries import QUERIES
from kdforest.shared import local_table


def cell(x, ids):
    return inside.CellTree(x, ids, inside.leaf_numbers(x, ids))


def plain(x, ids, q, r2, k, own):
    out = []
    for i in range(len(q)):
        d2 = inside.distance(np.broadcast_to(q[i], x.shape), x, "euclid")
        order = [j for j in np.lexsort((ids, d2)) if d2[j] <= r2[i] and (own is None or ids[j] != own[i])][:k]
        out += [(i, int(ids[j]), float(d2[j])) for j in order]
    return out


@pytest.mark.parametrize("exclude_self", [False, True])
def test_cells_of_many_dimensions_compute_few_distances_in_full(monkeypatch, exclude_self):
    rng, seen = np.random.default_rng(5), []
    x, q = rng.normal(size=(2000, 16)), rng.normal(size=(600, 16))
    ids, own = rng.permutation(2000), rng.integers(0, 2000, 600) if exclude_self else None
    r2 = np.where(np.arange(600) % 2, np.inf, 12.0)
    want, was = plain(x, ids, q, r2, 5, own), inside.distance
    monkeypatch.setattr(inside, "distance", lambda a, b, metric: (seen.append(len(a)), was(a, b, metric))[1])
    got = inside.nearest(cell(x, ids), q, r2, 5, "euclid", own)
    assert list(zip(*(c.tolist() for c in got), strict=True)) == want
    assert sum(seen) < 0.15 * len(q) * len(x)


@pytest.mark.parametrize("kind", ["far", "ties", "equal", "tiny", "huge", "one far query"])
def test_rounded_distances_leave_nothing_out(kind):
    rng = np.random.default_rng(6)
    x, q = rng.normal(size=(300, 3)), rng.normal(size=(100, 3))
    shift, scale = {"far": (1e9, 1e-3), "tiny": (0.0, 1e-60), "huge": (0.0, 1e150)}.get(kind, (0.0, 1.0))
    x, q = x * scale + shift, q * scale + shift
    if kind == "ties":
        x, q = np.floor(x * 2), np.floor(q * 2)
    if kind == "equal":
        x[:], q[:50] = 1.5, 1.5
    if kind == "one far query":
        q[7] = 1e30
    ids = rng.permutation(300)
    t, r2 = cell(x, ids), np.full(100, np.inf)
    got = inside.all_pairs(t, q, r2, 4)
    if kind == "huge":  # not rounded, the tree is searched
        assert got is None
        got = inside.nearest(t, q, r2, 4)
        assert len(got[0]) == len(plain(x, ids, q, r2, 4, None))
    else:
        assert list(zip(*(c.tolist() for c in got), strict=True)) == plain(x, ids, q, r2, 4, None)


def listed(found):
    """(row, id, d2) in order of rows; in a row the order found."""
    order = np.argsort(found[0], kind="stable")
    return list(zip(*(c[order].tolist() for c in found), strict=True))


def test_a_window_spares_most_pairs(monkeypatch):
    rng, seen, was = np.random.default_rng(7), [], inside.combined
    x, q = rng.random((20000, 2)) * [100, 2400], rng.random((400, 2)) * [100, 2400]
    ids = rng.permutation(20000)
    want = plain(x, ids, q, np.full(400, np.inf), 5, None)
    monkeypatch.setattr(baselines, "TOGETHER", 8)
    monkeypatch.setattr(inside, "combined", lambda parts, metric: (seen.append(np.broadcast(*parts).size), was(parts, metric))[1])
    assert listed(baselines.in_window(q, None, x, ids, 5, "euclid")) == want
    assert sum(seen) < 0.1 * len(q) * len(x)


@pytest.mark.parametrize("metric", ["euclid", "l1", "linf"])
@pytest.mark.parametrize("kind", ["grid", "equal", "few", "far"])
def test_windows_with_ties(monkeypatch, kind, metric):
    rng = np.random.default_rng(8)
    n = 3 if kind == "few" else 400
    x, q = np.floor(rng.normal(size=(n, 3)) * 3), np.floor(rng.normal(size=(90, 3)) * 3)
    if kind == "equal":
        x[:], q[:40] = 1.5, 1.5
    if kind == "far":
        x, q[:5], q[5:9] = x * 1e-7 + 1e9, 1e200, -1e12
    ids = rng.permutation(n)
    monkeypatch.setattr(baselines, "TOGETHER", 7)
    monkeypatch.setattr(baselines, "BESIDE", 5)
    monkeypatch.setattr(inside, "BLOCK", 500)
    for own in (None, rng.integers(0, n, 90)):
        want = []
        for i in range(90):
            d2 = inside.distance(np.broadcast_to(q[i], x.shape), x, metric)
            want += [(i, int(ids[m]), float(d2[m])) for m in [m for m in np.lexsort((ids, d2)) if d2[m] < np.inf and (own is None or ids[m] != own[i])][:4]]
        assert listed(baselines.in_window(q, own, x, ids, 4, metric)) == want


@pytest.mark.parametrize("exclude_self", [False, True])
def test_windows_of_several_blocks(spark, monkeypatch, exclude_self):
    monkeypatch.setattr(baselines, "SORTED_POINTS", 120)
    monkeypatch.setattr(baselines, "SORTED_QUERIES", 90)
    rng = random.Random(9)
    rows = [(i, float(rng.randrange(9)), float(rng.randrange(9)), i) for i in range(150)]
    points = local_table(spark, rows, "point_id long, c0 double, c1 double, seq long")
    asked = kd.as_queries(points.where("point_id < 70"), 2)
    got, want = (baselines.brute_knn(asked, points, 2, 4, exclude_self=exclude_self, window=w) for w in (True, False))
    assert sorted(map(tuple, got.collect())) == sorted(map(tuple, want.collect()))
    assert baselines.brute_knn(asked, points.limit(0), 2, 4, window=True).count() == baselines.brute_knn(asked.limit(0), points, 2, 4, window=True).count() == 0


def test_the_query_takes_a_window(spark, monkeypatch):
    """The registered query, whose blocks of all pairs don't end at size, has the rows of these blocks."""
    used, was = [], baselines.brute_knn
    monkeypatch.setitem(QUERIES["base_brute_knn"].__globals__, "brute_knn", lambda *a, **b: (used.append(b), was(*a, **b))[1])
    got = QUERIES["base_brute_knn"](spark, "/root/testdata/sf0.001").collect()
    assert used == [{"window": True}]
    monkeypatch.setitem(QUERIES["base_brute_knn"].__globals__, "brute_knn", lambda *a, **b: was(*a))
    assert sorted(got) == sorted(QUERIES["base_brute_knn"](spark, "/root/testdata/sf0.001").collect())
