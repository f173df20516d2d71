"""Functions for SQL users: expressions, Arrow and grouped functions, and table functions."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import SparkSession
from pyspark.sql.functions import PandasUDFType, arrow_udf, pandas_udf, udtf
from pyspark.sql.types import Row

from kdforest.operators import cells
from kdforest.plans.veb import positions


def squared_distance(spark: SparkSession, d: int, name: str = "kd_dist2") -> None:
    """``name(q0.., c0..)`` as a temporary SQL function: an expression, so it stays in generated code."""
    args = ", ".join(f"{p}{j} DOUBLE" for p in "qc" for j in range(d))
    body = " + ".join(f"(q{j} - c{j}) * (q{j} - c{j})" for j in range(d))
    spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {name}({args}) RETURNS DOUBLE RETURN {body}")


def route_udf(splits: list[tuple[int, int, float]]):
    """An Arrow function of an array of coordinates: the node that ``splits`` (node, dimension, value) lead to from node 1."""
    from kdforest.operators.tree import Router

    router = Router([(0, *s) for s in splits])

    @arrow_udf("long")
    def route(coords: pa.Array) -> pa.Array:
        x = np.array([c if c is not None else [] for c in coords.to_pylist()], dtype=np.float64).reshape(len(coords), -1)
        ones = np.ones(len(x), dtype=np.int64)
        return pa.array(router.down(ones * 0, ones, x)[1])

    return route


def topk_agg(k: int):
    """A grouped function of (d2, point_id): the ids of the k nearest, nearest first."""

    @pandas_udf("array<long>", PandasUDFType.GROUPED_AGG)
    def merge(d2, point_id):
        order = np.lexsort((point_id.to_numpy(), d2.to_numpy()))[:k]
        return point_id.to_numpy()[order].tolist()

    return merge


@udtf(returnType="node int, position int")
class VebLayout:
    """``kd_veb_layout(levels)``: the position of each node of a complete tree in the recursive order."""

    def eval(self, levels: int):
        for node, p in enumerate(positions(levels), start=1):
            yield node, p


@udtf(returnType="tree int, cap long, built long, live long")
class ForestInfo:
    """``kd_forest_info(root)``: the trees of the newest saved version."""

    def eval(self, root: str):
        from kdforest.sources.index_source import manifest

        m = manifest(root, None)
        for tree, slot in m["slots"].items():
            yield int(tree), slot["cap"], slot["built"], slot["live"]
        yield -1, m["options"]["x"], m["buffered"], m["buffered"]


def knn_in_cell(d: int, k: int):
    """A table function over one partition of rows (query_id or null, point_id or null, c0..): the k nearest points to each query of the partition."""

    @udtf(returnType="query_id long, point_id long, d2 double")
    class KnnInCell:
        def __init__(self):
            self.queries, self.points = [], []

        def eval(self, row: Row):
            at = [row[f"c{j}"] for j in range(d)]
            if row["query_id"] is not None:
                self.queries.append((row["query_id"], at))
            if row["point_id"] is not None:
                self.points.append((row["point_id"], at))

        def terminate(self):
            if not self.queries or not self.points:
                return
            x, ids = np.array([p[1] for p in self.points], dtype=float), np.array([p[0] for p in self.points], dtype=np.int64)
            tree = cells.CellTree(x, ids, cells.leaf_numbers(x, ids))
            q = np.array([p[1] for p in self.queries], dtype=float)
            for row, point, d2 in zip(*cells.nearest(tree, q, np.full(len(q), np.inf), k), strict=True):
                yield self.queries[int(row)][0], int(point), float(d2)

    return KnnInCell


def register(spark: SparkSession, d: int = 2, k: int = 5) -> None:
    """All of them under names that begin with kd_."""
    squared_distance(spark, d)
    spark.udf.register("kd_topk", topk_agg(k))
    spark.udtf.register("kd_veb_layout", VebLayout)
    spark.udtf.register("kd_forest_info", ForestInfo)
    spark.udtf.register("kd_knn_in_cell", knn_in_cell(d, k))
