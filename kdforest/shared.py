"""Tables written to the folder that all machines share, and checked broadcasts."""

from __future__ import annotations

import tempfile
import uuid

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.pandas.types import to_arrow_type
from pyspark.sql.types import StructType

#: Sides up to this many rows may be broadcast.
BROADCAST_ROWS = 50_000


def scratch_path(spark: SparkSession, name: str) -> str:
    """A new path in the folder all machines share (spark.checkpoint.dir); on one machine alone a temporary one will do if that is unset."""
    base = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not base:
        if not spark.sparkContext.master.startswith("local"):
            raise RuntimeError("set spark.checkpoint.dir to a folder that all machines share")
        base = f"file://{tempfile.mkdtemp(prefix='kdforest-')}"
        spark.sparkContext.setCheckpointDir(base)
    return f"{base.rstrip('/')}/{name}-{uuid.uuid4().hex}"


def written(df: DataFrame, name: str) -> DataFrame:
    """``df`` read back from Parquet in the shared folder: no lineage, nothing lost with an executor. Its path is in ``scratch``."""
    path = scratch_path(df.sparkSession, name)
    df.write.parquet(path)
    return read_back(df.sparkSession, path, df.schema)


def read_back(spark: SparkSession, path: str, schema: StructType | str) -> DataFrame:
    out = spark.read.schema(schema).parquet(path)
    out.scratch = path
    return out


def emptied(spark: SparkSession, path: str) -> None:
    """Frees the files of a table that ``written`` made: an empty table takes its place, which works in any store."""
    spark.read.parquet(path).limit(0).coalesce(1).write.mode("overwrite").parquet(f"{path}-empty")
    spark.read.parquet(f"{path}-empty").write.mode("overwrite").parquet(path)


def local_table(spark: SparkSession, rows: list[tuple], schema: str) -> DataFrame:
    """Rows that the driver has as a local relation: no task makes them."""
    fields = StructType.fromDDL(schema)
    columns = list(zip(*rows, strict=True)) or [()] * len(fields)
    table = pa.table([pa.array(c, to_arrow_type(f.dataType)) for c, f in zip(columns, fields, strict=True)], names=[f.name for f in fields])
    return spark.createDataFrame(table, fields)


def small(df: DataFrame, rows: int) -> DataFrame:
    """``df`` to broadcast if its known number of rows allows it; else to merge, for Spark's guess from the bytes of packed files would send along far larger ones."""
    return F.broadcast(df) if rows <= BROADCAST_ROWS else df.hint("merge")
