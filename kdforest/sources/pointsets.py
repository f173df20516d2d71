"""Point sets: named mappings from the given tables, and generators."""

from __future__ import annotations

from dataclasses import dataclass
from functools import reduce
from operator import and_

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from kdforest.functions.geometry import coords
from kdforest.operators.primitives import prefix_scan, ranks

_DAYS = "unix_micros(cast({} as timestamp)) / 8.64e10D"
_LINE_KEY = ["l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", "l_shipdate", "l_extendedprice", "l_quantity", "l_discount", "l_tax"]
_LINE3 = ["l_quantity", "l_extendedprice / 1000", f"{_DAYS.format('l_shipdate')} / 10"]
_LINE5 = [*_LINE3, "l_discount * 100", "l_tax * 100"]


@dataclass(frozen=True)
class PointSpec:
    """How a table's rows become points: the id and the coordinate expressions."""

    table: str
    point_id: str
    exprs: tuple[str, ...]

    @property
    def d(self) -> int:
        return len(self.exprs)


SPECS = {
    "ord2": PointSpec("orders", "o_orderkey", ("o_totalprice / 5000", _DAYS.format("o_orderdate"))),
    "evt2": PointSpec("events", "event_id", ("unix_micros(cast(ts as timestamp)) / 3.6e9D", "value")),
    "line3": PointSpec("lineitem", "rid", tuple(_LINE3)),
    "line5": PointSpec("lineitem", "rid", tuple(_LINE5)),
    "dup2": PointSpec("lineitem", "rid", ("l_discount", "l_tax")),
    "cust2": PointSpec("customer", "c_custkey", ("c_acctbal", "c_nationkey")),
    "supp2": PointSpec("supplier", "s_suppkey", ("s_acctbal", "s_nationkey")),
    "part2": PointSpec("part", "p_partkey", ("p_size", "p_retailprice")),
    "ol7": PointSpec("lineitem+orders", "rid", (*_LINE5, "o_totalprice / 5000", f"{_DAYS.format('o_orderdate')} / 10")),
    **{f"emb{d}": PointSpec("embeddings", "vec_id", tuple(f"embedding[{j}]" for j in range(d))) for d in (5, 7, 10, 16)},
}


def points_from(df: DataFrame, point_id: str, exprs: list[str], bad: str = "fail") -> DataFrame:
    """(point_id, c0.., seq) with double coordinates; -0.0 is 0.0.

    Null, NaN and infinite coordinates raise an error, or are dropped with ``bad="drop"``. seq is the id, the arrival order.
    """
    cs = [(F.expr(e).cast("double") + F.lit(0.0)).alias(f"c{j}") for j, e in enumerate(exprs)]
    out = df.select(F.expr(point_id).cast("long").alias("point_id"), *cs)
    # each coordinate is judged by itself: the optimizer derives 2^d constraints from an expression over all that are renamed later
    fine = {c: F.coalesce(F.col(c).isNotNull() & ~F.isnan(c) & (F.abs(c) != F.lit(float("inf"))), F.lit(False)) for c in coords(len(exprs))}
    if bad == "drop":
        return out.where(reduce(and_, fine.values())).withColumn("seq", F.col("point_id"))
    raised = F.raise_error(F.lit("a coordinate is null or not finite")).cast("double")
    return out.withColumns({c: F.when(f, F.col(c)).otherwise(raised) for c, f in fine.items()} | {"seq": F.col("point_id")})


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def numbered_lineitem(spark: SparkSession, sf_dir: str) -> DataFrame:
    """lineitem and rid, its rank by all columns that points use, counted over ranges side by side."""
    return ranks(load(spark, sf_dir, "lineitem").select(*_LINE_KEY), _LINE_KEY).withColumnRenamed("rank", "rid")


def point_set(spark: SparkSession, sf_dir: str, name: str, numbered: DataFrame | None = None) -> tuple[DataFrame, int]:
    """The points of a named set and their number of dimensions: those of SPECS, evt5, evt7, uni2.. and var2..

    ``numbered`` is what ``numbered_lineitem`` returns, for callers that make several sets of it.
    """
    if name.startswith(("uni", "var")):
        d = int(name[3:])
        n = load(spark, sf_dir, "events").count()
        return (uniform if name.startswith("uni") else variable_density)(spark, n, d), d
    if name in ("evt5", "evt7"):
        d = int(name[3:])
        by_user = Window.partitionBy("user_id").orderBy("ts", "event_id")
        df = load(spark, sf_dir, "events").select("event_id", *[F.lag("value", j).over(by_user).alias(f"v{j}") for j in range(d)]).dropna()
        return points_from(df, "event_id", [f"v{j}" for j in range(d)]), d
    spec = SPECS[name]
    if spec.table == "lineitem":
        df = numbered_lineitem(spark, sf_dir) if numbered is None else numbered
    elif spec.table == "lineitem+orders":
        df = (numbered_lineitem(spark, sf_dir) if numbered is None else numbered).join(load(spark, sf_dir, "orders"), F.col("l_orderkey") == F.col("o_orderkey"))
    else:
        df = load(spark, sf_dir, spec.table)
    return points_from(df, spec.point_id, list(spec.exprs)), spec.d


def _unit(key: str, j: int) -> Column:
    """An integer hash of (id, dimension) as a fraction; DuckDB can repeat it."""
    x = F.expr(f"(({key} + 1) * 2654435761L + {j + 1} * 40503L) % 4294967291L")
    return ((x * 69069 + 12345) % 4294967291 % 1000003) / F.lit(1000003.0)


def uniform(spark: SparkSession, n: int, d: int) -> DataFrame:
    """``n`` points in a cube with side sqrt(n)."""
    return points_from(spark.range(n).select("id", *[(_unit("id", j) * n**0.5).alias(f"u{j}") for j in range(d)]), "id", [f"u{j}" for j in range(d)])


def variable_density(spark: SparkSession, n: int, d: int, jump: float = 0.01) -> DataFrame:
    """``n`` points of a random walk that jumps to another site with probability ``jump`` before each step; step lengths differ by site."""
    flagged = spark.range(n).withColumn("flag", (_unit("id", 89) < jump).cast("int"))
    scanned, _ = prefix_scan(flagged, ["id"], "flag")
    df = scanned.select("id", (F.col("scan") + F.col("flag")).cast("long").alias("seg"))
    steps = Window.partitionBy("seg").orderBy("id")
    size = 0.02 + F.pmod(F.col("seg") * 7919, F.lit(97)) / F.lit(97.0)
    sites = [_unit("seg", j + 50) * n**0.5 for j in range(d)]
    walked = [(sites[j] + F.sum((_unit("id", j) - 0.5) * size).over(steps)).alias(f"u{j}") for j in range(d)]
    return points_from(df.select("id", *walked), "id", [f"u{j}" for j in range(d)])


FORMATS = ("parquet", "csv", "json", "orc")


def read_points(spark: SparkSession, path: str, fmt: str, schema: str, point_id: str, exprs: list[str], bad: str = "fail") -> DataFrame:
    """Points from files in one of FORMATS with a stated ``schema``; text that doesn't fit it is an error, or null and so a bad row with ``bad="drop"``."""
    if fmt not in FORMATS:
        raise ValueError(f"no such format: {fmt}")
    reader = spark.read.schema(schema)
    if fmt in ("csv", "json"):
        reader = reader.option("mode", "FAILFAST" if bad == "fail" else "PERMISSIVE")
    if fmt == "csv":
        reader = reader.option("header", "true")
    return points_from(reader.format(fmt).load(path), point_id, exprs, bad)


def write_points(points: DataFrame, path: str, fmt: str, compression: str | None = None) -> None:
    if fmt not in FORMATS:
        raise ValueError(f"no such format: {fmt}")
    sink = points.write.format(fmt)
    sink = sink.option("header", "true") if fmt == "csv" else sink
    (sink.option("compression", compression) if compression else sink).save(path)


def scaled(points: DataFrame, d: int, how: str = "minmax") -> DataFrame:
    """Coordinates as shares of their range ("minmax") or as deviations from the mean in standard deviations ("zscore"); a constant one is 0."""
    if how not in ("minmax", "zscore"):
        raise ValueError(f"no such scale: {how}")
    first, second = (F.min, F.max) if how == "minmax" else (F.avg, F.stddev_pop)
    row = points.agg(*[f(c).alias(f"{a}{j}") for j, c in enumerate(coords(d)) for f, a in ((first, "a"), (second, "b"))]).first()
    out = {}
    for j, c in enumerate(coords(d)):
        a, b = row[f"a{j}"], row[f"b{j}"]
        width = None if a is None else (b - a if how == "minmax" else b)
        out[c] = (F.col(c) - F.lit(a)) / F.lit(width) if width else F.col(c) * 0.0
    return points.withColumns(out)


def payload(events: DataFrame, schema: str, column: str = "props") -> DataFrame:
    """``events`` with the fields of a JSON column as columns; text that is no JSON gives nulls."""
    parsed = F.from_json(column, schema)
    return events.withColumn(column, parsed).select(*[c for c in events.columns if c != column], f"{column}.*")
