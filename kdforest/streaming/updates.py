"""Structured Streaming around the indexes: micro-batch updates, expiry, windows, sessions, deduplication."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout
from pyspark.sql.types import StructType

from kdforest.shared import scratch_path


def event_stream(spark: SparkSession, sf_dir: str, files: int | None = None) -> DataFrame:
    """The events table as a file stream, ``files`` files a micro-batch."""
    schema = spark.read.parquet(f"{sf_dir}/events.parquet").schema
    reader = spark.readStream.schema(schema)
    return (reader.option("maxFilesPerTrigger", files) if files else reader).parquet(f"{sf_dir}/events*.parquet")


def run_once(stream: DataFrame, name: str, work: Callable[[DataFrame, int], None]) -> None:
    """Runs ``work`` on each micro-batch of what is there now; a batch that runs again has the same id."""
    q = stream.writeStream.foreachBatch(work).option("checkpointLocation", scratch_path(stream.sparkSession, name)).trigger(availableNow=True).start()
    q.awaitTermination()


def to_table(stream: DataFrame, name: str, mode: str = "append") -> DataFrame:
    """What a stream gives for the rows there are now, as a table in the shared folder."""
    spark = stream.sparkSession
    path = scratch_path(spark, name)
    q = stream.writeStream.format("parquet").outputMode(mode).option("path", path).option("checkpointLocation", scratch_path(spark, f"{name}-state")).trigger(availableNow=True).start()
    q.awaitTermination()
    return spark.read.schema(stream.schema).parquet(path)


def whole_table(stream: DataFrame, name: str) -> DataFrame:
    """A grouped stream's last values for the rows there are now, as a table in the shared folder.

    All groups are written anew after each micro-batch, so those that the watermark has not passed are there too.
    Groups are kept as state until the end, and no row is too late.
    """
    spark = stream.sparkSession
    path, last = scratch_path(spark, name), []

    def work(batch: DataFrame, batch_id: int) -> None:
        batch.write.mode("overwrite").parquet(f"{path}/{batch_id}")
        last[:] = [batch_id]

    q = stream.writeStream.outputMode("complete").foreachBatch(work).option("checkpointLocation", scratch_path(spark, f"{name}-state")).trigger(availableNow=True).start()
    q.awaitTermination()
    return spark.read.schema(stream.schema).parquet(f"{path}/{last[0]}") if last else spark.createDataFrame([], stream.schema)


class LateRows:
    """Takes rows that come more than ``delay`` seconds after newer ones out of a micro-batch and into a side table.

    The newest time seen is that of the batches before; rows without a time are late. A batch that runs again writes
    the same side rows once more in place of the first ones.
    """

    def __init__(self, spark: SparkSession, time: str, delay: float):
        self.spark, self.time, self.delay, self.newest, self.path = spark, time, delay, None, scratch_path(spark, "late")
        self.batches: set[int] = set()

    def on_time(self, batch: DataFrame, batch_id: int) -> DataFrame:
        at = F.unix_micros(F.col(self.time).cast("timestamp"))
        limit = None if self.newest is None else self.newest - int(self.delay * 1e6)
        late = at.isNull() if limit is None else at.isNull() | (at < limit)
        batch.where(late).write.mode("overwrite").parquet(f"{self.path}/{batch_id}")
        self.batches.add(batch_id)
        top = batch.agg(F.max(at)).first()[0]
        self.newest = top if self.newest is None or top is not None and top > self.newest else self.newest
        return batch.where(~late)

    def table(self) -> DataFrame | None:
        """The late rows so far."""
        return self.spark.read.parquet(*[f"{self.path}/{b}" for b in sorted(self.batches)]) if self.batches else None


def neighbours(stream: DataFrame, name: str, index, k: int, queries_of: Callable[[DataFrame], DataFrame]) -> DataFrame:
    """(batch, query_id, rank, point_id, d2): each arriving row's neighbours in the index's newest version at that time, as a table."""
    path, batches = scratch_path(stream.sparkSession, name), []

    def work(batch: DataFrame, batch_id: int) -> None:
        index.knn(queries_of(batch), k).write.mode("overwrite").parquet(f"{path}/{batch_id}")
        batches.append(batch_id)

    run_once(stream, f"{name}-state", work)
    schema = "query_id long, rank int, point_id long, d2 double"
    out = None
    for b in sorted(set(batches)):
        part = stream.sparkSession.read.schema(schema).parquet(f"{path}/{b}").select(F.lit(b).cast("long").alias("batch"), "*")
        out = part if out is None else out.unionByName(part)
    return out if out is not None else stream.sparkSession.createDataFrame([], f"batch long, {schema}")


def per_key_nearest(stream: DataFrame, key: str, coords: list[str], order: str) -> DataFrame:
    """(key, point_id, neighbour, d2): for each point the nearest earlier one of its key, null for the first; a small index per key is the state.

    Inside a micro-batch points come in the order of (``order``, point_id). Keys are longs; rows with a null key are left out.
    State is as many points as the key has.
    """
    d = len(coords)
    out = StructType.fromDDL(f"{key} long, point_id long, neighbour long, d2 double")
    state_type = StructType.fromDDL("ids array<long>, flat array<double>")

    def work(group: tuple, frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        ids, flat = state.get if state.exists else ([], [])
        new = pd.concat(list(frames)).sort_values([order, "point_id"])
        at = np.concatenate([np.array(flat, dtype=float).reshape(-1, d), new[coords].to_numpy(dtype=float)])
        known = np.concatenate([np.array(ids, dtype=np.int64), new["point_id"].to_numpy(dtype=np.int64)])
        rows = []
        for i in range(len(ids), len(known)):
            if i:
                d2 = ((at[:i] - at[i]) ** 2).sum(axis=1)
                j = np.lexsort((known[:i], d2))[0]
                rows.append((group[0], known[i], known[j], d2[j]))
            else:
                rows.append((group[0], known[i], None, None))
        state.update((known.tolist(), at.ravel().tolist()))
        yield pd.DataFrame(rows, columns=[f.name for f in out]).astype({key: "int64", "point_id": "int64", "neighbour": "Int64", "d2": "float64"})

    slim = stream.where(F.col(key).isNotNull()).select(key, "point_id", *coords, order)
    return slim.groupBy(key).applyInPandasWithState(work, out, state_type, "append", GroupStateTimeout.NoTimeout)


def apply_changes(index, points_of: Callable[[DataFrame], DataFrame], deleted_of: Callable[[DataFrame], DataFrame]) -> Callable[[DataFrame, int], None]:
    """A micro-batch as two one-kind batches, inserts first; its id makes a retry do nothing."""

    def work(batch: DataFrame, batch_id: int) -> None:
        index.insert(points_of(batch), batch_id=("insert", batch_id))
        gone = deleted_of(batch)
        if not gone.isEmpty():
            index.delete(gone, batch_id=("delete", batch_id))

    return work


def deduplicated(stream: DataFrame, key: list[str], time: str, delay: str) -> DataFrame:
    return stream.withWatermark(time, delay).dropDuplicatesWithinWatermark(key)


def window_extents(stream: DataFrame, time: str, width: str, slide: str | None, delay: str, value: str) -> DataFrame:
    """Count and extent of ``value`` in tumbling or sliding windows; in append mode rows later than ``delay`` are dropped."""
    w = F.window(time, width, slide) if slide else F.window(time, width)
    return stream.withWatermark(time, delay).groupBy(w.alias("w")).agg(F.count("*").alias("n"), F.min(value).alias("lo"), F.max(value).alias("hi")).select(F.col("w.start").alias("start"), "n", "lo", "hi")


def sessions(stream: DataFrame, time: str, key: str, gap: str, delay: str) -> DataFrame:
    """Rows of each key's sessions, which end after ``gap`` without one."""
    return stream.withWatermark(time, delay).groupBy(key, F.session_window(time, gap).alias("w")).agg(F.count("*").alias("n")).select(key, F.col("w.start").alias("start"), "n")
