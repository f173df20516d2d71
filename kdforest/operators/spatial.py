"""Queries around the nearest-neighbour methods: boxes, radius joins, pairs, votes, time joins."""

from __future__ import annotations

from functools import reduce

import numpy as np
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from kdforest.functions.geometry import coords, dist2
from kdforest.operators import tree as kd
from kdforest.shared import local_table, small


def in_box(points: DataFrame, lo: list[float], hi: list[float]) -> DataFrame:
    """Points in a closed box; the comparisons reach the file scan."""
    tests = [F.col(f"c{j}").between(a, b) for j, (a, b) in enumerate(zip(lo, hi, strict=True))]
    return points.where(reduce(lambda a, b: a & b, tests))


def box_query(forest: kd.Forest, lo: list[float], hi: list[float]) -> DataFrame:
    """Points of an indexed set in a box: only cells that meet it are read, those inside it untested."""
    near = [c for c in forest.cells if all(c[f"lo{j}"] <= hi[j] and c[f"hi{j}"] >= lo[j] for j in range(forest.d))]
    if not near:
        return forest.points.where("false")
    inside = {(c["tree"], c["node"]) for c in near if all(c[f"lo{j}"] >= lo[j] and c[f"hi{j}"] <= hi[j] for j in range(forest.d))}
    table = local_table(forest.points.sparkSession, [(c["tree"], c["node"], (c["tree"], c["node"]) in inside) for c in near], "tree int, node long, whole boolean")
    rows = forest.points.join(small(table, len(near)), ["tree", "node"])
    tests = reduce(lambda a, b: a & b, [F.col(f"c{j}").between(lo[j], hi[j]) for j in range(forest.d)])
    return rows.where(F.col("whole") | tests).drop("whole")


def range_count(points: DataFrame, boxes: DataFrame, d: int) -> DataFrame:
    """(box_id, n) for few closed boxes (box_id, lo0.., hi0..), which are broadcast after a count."""
    n = boxes.count()
    tests = reduce(lambda a, b: a & b, [(F.col(f"c{j}") >= F.col(f"lo{j}")) & (F.col(f"c{j}") <= F.col(f"hi{j}")) for j in range(d)])
    hit = points.join(small(boxes, n), tests).groupBy("box_id").agg(F.count("*").alias("n"))
    return boxes.select("box_id").join(hit, "box_id", "left").select("box_id", F.coalesce("n", F.lit(0).cast("long")).alias("n"))


def radius_join(a: DataFrame, b: DataFrame, d: int, r: float) -> DataFrame:
    """(query_id, point_id, d2) of all pairs within ``r``, 0 or more: an equi join on grid cells of side r and their neighbours; for few dimensions. Null coordinates meet nothing."""
    side = r if r > 0 else 1.0  # with no radius only equal points are pairs
    cell = [F.floor(F.col(f"c{j}") / side) for j in range(d)]
    around = [F.array(*[F.floor(F.col(f"q{j}") / side) + s for s in (-1, 0, 1)]) for j in range(d)]
    left = a
    for j in range(d):
        left = left.withColumn(f"g{j}", F.explode(around[j]))
    right = b.withColumns({f"g{j}": cell[j] for j in range(d)})
    pairs = left.join(right, [f"g{j}" for j in range(d)]).withColumn("d2", dist2(d))
    return pairs.where(F.col("d2") <= r * r).select("query_id", "point_id", "d2")


def reverse_knn(graph: DataFrame) -> DataFrame:
    """(point_id, n): how many queries have a point among their neighbours."""
    return graph.groupBy("point_id").agg(F.count("*").alias("n"))


def mutual_edges(graph: DataFrame) -> DataFrame:
    """(a, b), a < b: pairs that are neighbours of each other."""
    e = graph.select(F.least("query_id", "point_id").alias("a"), F.greatest("query_id", "point_id").alias("b"))
    return e.groupBy("a", "b").agg(F.count("*").alias("n")).where("n = 2").select("a", "b")


def closest_pairs(graph: DataFrame, n: int) -> DataFrame:
    """The n closest pairs (a, b, d2), from a graph of the nearest neighbours of all points (k at least n, or 1 for n = 1)."""
    e = graph.select(F.least("query_id", "point_id").alias("a"), F.greatest("query_id", "point_id").alias("b"), "d2").distinct()
    return e.orderBy("d2", "a", "b").limit(n)


def farthest(points: DataFrame, at: list[float], n: int) -> DataFrame:
    """The n points farthest from ``at``: each task keeps its n."""
    d2 = reduce(lambda a, b: a + b, [(F.col(f"c{j}") - F.lit(x)) * (F.col(f"c{j}") - F.lit(x)) for j, x in enumerate(at)])
    return points.select("point_id", d2.alias("d2")).orderBy(F.desc("d2"), "point_id").limit(n)


def knn_vote(graph: DataFrame, labels: DataFrame) -> DataFrame:
    """(query_id, predicted): the most frequent label among the neighbours, the smallest of equal ones."""
    votes = graph.join(labels, "point_id").groupBy("query_id", "label").agg(F.count("*").alias("n"))
    return votes.groupBy("query_id").agg(F.max_by("label", F.struct("n", -F.col("label"))).alias("predicted"))


def lateral_knn(queries: DataFrame, points: DataFrame, d: int, k: int) -> DataFrame:
    """Neighbours by a lateral subquery per query: plain SQL, for few queries."""
    spark = queries.sparkSession
    queries.createOrReplaceTempView("_lateral_queries")
    points.createOrReplaceTempView("_lateral_points")
    total = " + ".join(f"(q.q{j} - p.c{j}) * (q.q{j} - p.c{j})" for j in range(d))
    return spark.sql(f"SELECT q.query_id, n.point_id, n.d2 FROM _lateral_queries q, LATERAL (SELECT p.point_id, {total} AS d2 FROM _lateral_points p ORDER BY d2, point_id LIMIT {k}) n")


def asof(left: DataFrame, right: DataFrame, by: list[str], on: str, value: str) -> DataFrame:
    """``left`` and the ``value`` (not null) of the last row of ``right`` at or before it in ``on``, per key; one sort, no join. Null keys are one key."""
    side = "_side"
    while side in left.columns:
        side = "_" + side
    a = left.withColumn(side, F.lit(1)).withColumn(f"asof_{value}", F.lit(None).cast(right.schema[value].dataType))
    b = right.select(*by, on, F.lit(0).alias(side), F.col(value).alias(f"asof_{value}"))
    both = a.unionByName(b, allowMissingColumns=True)
    last = Window.partitionBy(*by).orderBy(on, side).rowsBetween(Window.unboundedPreceding, 0)
    return both.withColumn(f"asof_{value}", F.last(f"asof_{value}", ignorenulls=True).over(last)).where(F.col(side) == 1).drop(side)


def interval_join(a: DataFrame, b: DataFrame, x: str, y: str, w: float) -> DataFrame:
    """Pairs whose ``x`` and ``y`` are within ``w``, 0 or more: an equi join on buckets of width w and their neighbours. Nulls meet nothing."""
    side, key = (w if w > 0 else 1.0), "_bucket"
    while key in {*a.columns, *b.columns}:
        key = "_" + key
    left = a.withColumn(key, F.explode(F.array(*[F.floor(F.col(x) / side) + s for s in (-1, 0, 1)])))
    right = b.withColumn(key, F.floor(F.col(y) / side))
    return left.join(right, key).where(F.abs(F.col(x) - F.col(y)) <= w).drop(key)


def dual_search(queries: DataFrame, forest: kd.Forest, k: int, cap: int = kd.CELL_CAP, rule: str = "object", metric: str = "euclid", exclude_self: bool = False, tombs: DataFrame | None = None, pairs_seen: list | None = None) -> DataFrame:
    """(query_id, rank, point_id, d2) by two trees: the queries' cells share a bound, and pairs of cells beyond it are dropped unseen.

    ``forest`` may hold several trees. The number of pairs of cells met is added to ``pairs_seen``.
    """
    d, spark = forest.d, queries.sparkSession
    q = coords(d, "q")
    as_points = queries.select(F.lit(0).alias("tree"), F.col("query_id").alias("point_id"), *[F.col(f"q{j}").alias(f"c{j}") for j in range(d)], F.lit(0).cast("long").alias("seq"))
    splits = [s for s in kd.build(as_points, d, rule, cap).splits if s[2] < d]

    def meet(asked: DataFrame) -> DataFrame:
        placed = kd.route(asked.select("query_id", *q, "r2", F.col("tree").alias("home_tree"), F.col("node").alias("home"), F.lit(0).alias("tree"), F.lit(1).cast("long").alias("node")), splits, d, "q")
        box = [f(c).alias(f"{a}{j}") for j, c in enumerate(q) for f, a in ((F.min, "lo"), (F.max, "hi"))]
        cells = placed.groupBy("node").agg(F.max("r2").alias("r2"), *box).collect()  # a row per query cell
        lo, hi = (np.array([[c[f"{a}{j}"] for j in range(d)] for c in cells], dtype=float).reshape(len(cells), d) for a in ("lo", "hi"))
        top = forest.top()
        row, cell = top.near_boxes(lo, hi, np.array([c.r2 for c in cells], dtype=float), metric)
        if pairs_seen is not None:
            pairs_seen.append(len(row))
        pairs = local_table(spark, [(cells[r].node, int(top.tree[c]), int(top.node[c])) for r, c in zip(row.tolist(), cell.tolist(), strict=True)], "qnode long, tree int, node long")
        met = placed.drop("tree").withColumnRenamed("node", "qnode").join(small(pairs, len(row)), "qnode")
        return met.where("tree <> home_tree OR node <> home").select("query_id", *q, "r2", "tree", "node")

    return kd.ranked(kd.search(queries, forest, k, metric, exclude_self=exclude_self, tombs=tombs, meet=meet), k)


def knn_dual(queries: DataFrame, points: DataFrame, d: int, k: int, cap: int = kd.CELL_CAP, rule: str = "object", exclude_self: bool = False) -> DataFrame:
    """Neighbours by a tree over the points and one over the queries."""
    return dual_search(queries, kd.stored(kd.build(points.withColumn("tree", F.lit(0)), d, rule, cap), rule=rule), k, cap, rule, exclude_self=exclude_self)


def visited(queries: DataFrame, forest: kd.Forest, r2: Column) -> DataFrame:
    """(query_id, cells): how many cells a query with bound ``r2`` has to search."""
    cells = kd.candidate_cells(queries.withColumn("r2", r2), forest, forest.trees, "euclid")
    return cells.groupBy("query_id").agg(F.count("*").alias("cells"))

