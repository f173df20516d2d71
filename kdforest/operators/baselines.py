"""The strategies that the log-forest is compared with, and brute force."""

from __future__ import annotations

from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from kdforest.functions.geometry import coords
from kdforest.operators import cells as inside
from kdforest.operators import tree as kd
from kdforest.shared import BROADCAST_ROWS, local_table, small, written


#: Rows of a block of points and of queries at most.
POINT_BLOCK, QUERY_BLOCK = 100_000, 20_000
#: The same for blocks that lie sorted, in values; queries that share a window, and the points on either side that give them a bound.
SORTED_POINTS, SORTED_QUERIES = 2_250_000, 1_500_000
TOGETHER, BESIDE = 128, 64


def in_window(at: np.ndarray, own: np.ndarray | None, x: np.ndarray, ids: np.ndarray, k: int, metric: str) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(row, id, d2) of the k nearest points to each query of a block, without its ``own``; exact, ties by id.

    Points and queries are sorted by the coordinate of the widest range. Points beside a query give a bound, and distances
    are computed to all points that are within it in that coordinate: others are farther by that one alone.
    """
    d = x.shape[1]
    j = int(np.argmax(x.max(axis=0) - x.min(axis=0)))
    x, ids = x[order := np.argsort(x[:, j], kind="stable")], ids[order]
    v, turn, got = np.ascontiguousarray(x[:, j]), np.argsort(at[:, j], kind="stable"), []

    def distances(rows: np.ndarray, lo: int, hi: int) -> np.ndarray:
        d2 = inside.combined([at[rows, i, None] - x[None, lo:hi, i] for i in range(d)], metric)
        if own is not None:
            d2[own[rows, None] == ids[None, lo:hi]] = np.inf
        return d2

    beside = max(BESIDE, k + 1)
    for start in range(0, len(turn), TOGETHER):
        rows = turn[start : start + TOGETHER]
        place = at[rows, j]
        lo, hi = max(0, int(np.searchsorted(v, place[0])) - beside), int(np.searchsorted(v, place[-1], side="right")) + beside
        step = max(1, inside.BLOCK // len(rows))
        d2 = distances(rows, lo, min(hi, lo + step))
        most = np.partition(d2, k - 1, axis=1)[:, k - 1] if d2.shape[1] > k else np.full(len(rows), np.inf)
        far = (np.sqrt(most) if metric == "euclid" else most) * (1 + 1e-12) + 1e-150
        first, last = int(np.searchsorted(v, np.nextafter(place - far, -np.inf).min())), int(np.searchsorted(v, np.nextafter(place + far, np.inf).max(), side="right"))
        held = [(rows[:0], ids[:0], np.zeros(0))]
        for a in range(first, last, step):
            d2 = distances(rows, a, min(last, a + step))
            row, col = np.divmod(np.flatnonzero((d2 <= most[:, None]) & (d2 < np.inf)), d2.shape[1])
            held = [inside.smallest(*(np.concatenate(w) for w in zip(*held, (row, ids[a + col], d2[row, col]), strict=True)), k)]
        got.append((rows[held[0][0]], *held[0][1:]))
    return tuple(np.concatenate(w) for w in zip(*got, strict=True))


def brute_knn(queries: DataFrame, points: DataFrame, d: int, k: int, metric: str = "euclid", exclude_self: bool = False, window: bool = False) -> DataFrame:
    """All pairs of queries and points: each block of queries meets each block of points, and a pair of blocks keeps the k best of a query.

    With ``window`` a pair of blocks skips pairs that one coordinate puts beyond the bound (``in_window``): the same rows, but no longer brute force.
    """
    spark, q, c = queries.sparkSession, coords(d, "q"), coords(d)
    qblock, pblock = (max(1, SORTED_QUERIES // (d + 1)), max(1, SORTED_POINTS // (d + 1))) if window else (QUERY_BLOCK, POINT_BLOCK)
    asked, held = written(queries.select("query_id", *q), "queries"), written(points.select("point_id", *c), "points")
    rows, wide = held.count(), 2 * spark.sparkContext.defaultParallelism
    qparts, pparts = max(1, -(-asked.count() // qblock)), max(1, -(-rows // pblock), min(wide, rows // 4096))
    every = lambda n: F.explode(F.sequence(F.lit(0), F.lit(n - 1)))
    part = lambda col, n: F.pmod(F.xxhash64(col), F.lit(n)).cast("int")
    left = asked.withColumn("qpart", part("query_id", qparts)).select("*", every(pparts).alias("ppart"))
    right = held.withColumn("ppart", part("point_id", pparts)).select("*", every(qparts).alias("qpart"))

    def work(qs: pa.Table, ps: pa.Table) -> pa.Table:
        own, ids = qs.column("query_id").to_numpy(), ps.column("point_id").to_numpy()
        at, x = (np.column_stack([t.column(n).to_numpy() for n in names]) for t, names in ((qs, q), (ps, c)))
        got, step = [], max(1, inside.BLOCK // max(1, len(ids)))
        if window and len(own) and len(ids):
            row, near, dist = in_window(at, own if exclude_self else None, x, ids, k, metric)
            got.append((own[row], near, dist))
        for lo in range(0, len(own) if len(ids) and not window else 0, step):
            d2 = inside.combined([at[lo : lo + step, j, None] - x[None, :, j] for j in range(d)], metric)
            if exclude_self:
                d2[own[lo : lo + step, None] == ids[None, :]] = np.inf
            most = np.partition(d2, k - 1, axis=1)[:, k - 1] if len(ids) > k else np.full(len(d2), np.inf)
            row, col = np.nonzero((d2 <= most[:, None]) & (d2 < np.inf))
            row, near, dist = inside.smallest(row, ids[col], d2[row, col], k)
            got.append((own[lo + row], near, dist))
        found = [np.concatenate(v) for v in zip(*got, strict=True)] if got else [own[:0], ids[:0], np.zeros(0)]
        return pa.table([pa.array(v, t) for v, t in zip(found, (pa.int64(), pa.int64(), pa.float64()), strict=True)], names=["query_id", "point_id", "d2"])

    key = ["qpart", "ppart"]
    return kd.ranked(left.groupBy(*key).cogroup(right.groupBy(*key)).applyInArrow(work, "query_id long, point_id long, d2 double"), k)


class _Index:
    def __init__(self, spark: SparkSession, d: int, rule: str = "object", cap: int = kd.CELL_CAP):
        self.spark, self.d, self.rule, self.cap = spark, d, rule, cap
        self.columns = ["point_id", *coords(d), "seq"]
        self.forest: kd.Forest | None = None
        self.tombs: DataFrame | None = None
        self.moved = 0

    def live(self) -> DataFrame:
        if self.forest is None:
            return local_table(self.spark, [], "point_id long, " + ", ".join(f"{c} double" for c in coords(self.d)) + ", seq long")
        points = self.forest.points
        if self.tombs is not None:
            points = points.join(self.tombs, [c for c in ("tree", "node", "point_id", "gen") if c in points.columns], "left_anti")
        return points.select(*self.columns)

    def knn(self, queries: DataFrame, k: int, metric: str = "euclid", exclude_self: bool = False) -> DataFrame:
        queries = queries.select("query_id", *coords(self.d, "q"), F.lit(None).cast("double").alias("r2"))
        if self.forest is None or not self.forest.cells:
            return brute_knn(queries.limit(0), self.live(), self.d, k)
        return kd.ranked(kd.search(queries, self.forest, k, metric, exclude_self=exclude_self, tombs=self.tombs), k)


class RebuildAll(_Index):
    """Every batch builds one balanced tree over all live points anew."""

    def _rebuild(self, rows: DataFrame) -> None:
        self.forest = kd.stored(kd.build(rows.select(F.lit(0).alias("tree"), *self.columns), self.d, self.rule, self.cap), rule=self.rule)
        self.moved = sum(c["n"] for c in self.forest.cells)

    def insert(self, batch: DataFrame) -> None:
        self._rebuild(self.live().unionByName(batch.select(*self.columns)))

    def delete(self, batch: DataFrame, key: str = "id") -> None:
        if self.forest is not None and self.forest.cells:
            gone = kd.erase(self.forest, batch.select(*[c for c in self.columns if c in batch.columns]), BROADCAST_ROWS + 1, key)
            self._rebuild(self.live().join(gone.select("point_id").distinct(), "point_id", "left_anti"))


class FixedCells(_Index):
    """Splits are never recomputed: inserts go to the cells they fall in, which split if they overflow; deletes leave tombstones.

    An insert reads and writes its own rows and those of overflowing cells alone. ``gen``, the number of the batch that
    brought a point, tells a point from one of the same id that was deleted before it. Rows of a cell that was split stay in the
    files and count no more; plans name such cells in one small table, however many updates there were.
    """

    def __init__(self, spark: SparkSession, d: int, rule: str = "object", cap: int = kd.CELL_CAP):
        super().__init__(spark, d, rule, cap)
        self.parts: list[DataFrame] = []
        self.gen = 0

    def _add(self, rows: DataFrame, splits: list, cells: list[dict]) -> None:
        self.parts.append(rows)
        points = reduce(DataFrame.unionByName, self.parts)
        if splits:
            points = points.join(self._nodes([s[1] for s in splits]), "node", "left_anti").select(*rows.columns)
        self.forest = kd.Forest(points, self.d, splits, cells)

    def _nodes(self, nodes: list[int]) -> DataFrame:
        return small(local_table(self.spark, [(n,) for n in nodes], "node long"), len(nodes))

    def insert(self, batch: DataFrame) -> None:
        self.gen += 1
        rows = batch.select(F.lit(0).alias("tree"), F.lit(1).cast("long").alias("node"), *self.columns, F.lit(self.gen).alias("gen"))
        splits = self.forest.splits if self.forest else []
        routed = written(kd.route(rows, splits, self.d), "batch")
        new = {c["node"]: c for c in kd.cell_table(routed, self.d)}
        self.moved = sum(c["n"] for c in new.values())
        cells = {c["node"]: c for c in self.forest.cells} if self.forest else {}
        for node, c in new.items():
            old = cells.get(node)
            if old:
                c = c | {"n": c["n"] + old["n"]} | {f"lo{j}": min(c[f"lo{j}"], old[f"lo{j}"]) for j in range(self.d)} | {f"hi{j}": max(c[f"hi{j}"], old[f"hi{j}"]) for j in range(self.d)}
            cells[node] = c
        self._add(routed, splits, list(cells.values()))
        full = [n for n, c in cells.items() if c["n"] > self.cap]
        if full:
            self._split(full)

    def _split(self, full: list[int]) -> None:
        """New splits below the cells ``full``: only their rows are read, and written without the deleted ones."""
        touched = self._nodes(full)
        mine = self.forest.points.join(touched, "node", "left_semi")
        if self.tombs is not None:
            mine = mine.join(self.tombs, ["tree", "node", "point_id", "gen"], "left_anti")
        mine = written(mine.select(*self.forest.points.columns), "overflow")
        grown = kd.build(mine, self.d, self.rule, self.cap)
        gone, inner = set(full), {p[1] for p in grown.splits}
        stay = self._nodes([n for n in full if n not in inner])  # small enough without the deleted rows: they stay as they are
        touched = self._nodes([n for n in full if n in inner])
        named = written(kd.route(mine, grown.splits, self.d).join(stay, "node", "left_anti").select(*mine.columns), "cells")
        self._add(named, self.forest.splits + grown.splits, [c for c in self.forest.cells if c["node"] not in gone] + grown.cells)
        if self.tombs is not None:
            self.tombs = written(self.tombs.join(touched, "node", "left_anti").select(*self.tombs.columns), "tombs")
        self.moved += sum(c["n"] for c in grown.cells)

    def delete(self, batch: DataFrame, key: str = "id") -> None:
        if self.forest is not None and self.forest.cells:
            rows = written(batch.select(*[c for c in self.columns if c in batch.columns]), "erase")
            hits = kd.erase(self.forest, rows, rows.count(), key)
            self.tombs = written(hits if self.tombs is None else self.tombs.unionByName(hits).distinct(), "tombs")
            self.moved = 0
