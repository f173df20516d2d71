"""A Python data source over a saved index: a partition per few cells, cells outside a box never read."""

from __future__ import annotations

import json
from collections.abc import Iterable, Iterator

import pyarrow as pa
import pyarrow.dataset as ds
import pyarrow.parquet as pq
from pyarrow import fs
from pyspark.sql import SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, EqualTo, Filter, GreaterThan, GreaterThanOrEqual, InputPartition, LessThan, LessThanOrEqual

#: Points of a partition (about).
POINTS = 1 << 20


def _store(path: str) -> tuple[fs.FileSystem, str]:
    return fs.FileSystem.from_uri(path if "://" in path or path.startswith("file:") else f"file://{path}")


def manifest(root: str, version: int | None) -> dict:
    store, at = _store(f"{root.rstrip('/')}/manifest")
    found = {}
    for info in store.get_file_info(fs.FileSelector(at, recursive=True)):
        if info.is_file and info.size and info.base_name.startswith("part-") and "version=" in info.path:
            found[int(info.path.rsplit("version=", 1)[1].split("/")[0])] = info.path
    if not found or version is not None and version not in found:
        raise ValueError(f"no such version: {version}")
    with store.open_input_stream(found[max(found) if version is None else version]) as f:
        return json.loads(f.read())


def _table(path: str) -> pa.Table:
    store, at = _store(path)
    return pq.ParquetDataset(at, filesystem=store).read()


class CellPartition(InputPartition):
    def __init__(self, path: str, tree: int, nodes: list[int]):
        self.path, self.tree, self.nodes = path, tree, nodes


class IndexReader(DataSourceReader):
    def __init__(self, root: str, version: int | None):
        self.manifest = manifest(root, version)
        self.d = self.manifest["options"]["d"]
        self.lo, self.hi = [float("-inf")] * self.d, [float("inf")] * self.d

    def pushFilters(self, filters: list[Filter]) -> Iterable[Filter]:
        """Bounds on coordinates choose cells; Spark still tests the rows."""
        for f in filters:
            name = f.attribute[0] if hasattr(f, "attribute") and len(f.attribute) == 1 else ""
            if name.startswith("c") and name[1:].isdigit() and int(name[1:]) < self.d:
                j = int(name[1:])
                if isinstance(f, (GreaterThan, GreaterThanOrEqual, EqualTo)):
                    self.lo[j] = max(self.lo[j], float(f.value))
                if isinstance(f, (LessThan, LessThanOrEqual, EqualTo)):
                    self.hi[j] = min(self.hi[j], float(f.value))
            yield f

    def partitions(self) -> list[InputPartition]:
        cells = _table(f"{self.manifest['tables']}/cells").to_pylist()
        near = [c for c in cells if all(a <= y and b >= x for a, b, x, y in zip(c["lo"], c["hi"], self.lo, self.hi, strict=True))]
        out: list[InputPartition] = []
        for tree, slot in self.manifest["slots"].items():
            held, n = [], 0
            for c in [c for c in near if c["tree"] == int(tree)]:
                held.append(c["node"])
                n += c["n"]
                if n >= POINTS:
                    out.append(CellPartition(slot["path"], int(tree), held))
                    held, n = [], 0
            if held:
                out.append(CellPartition(slot["path"], int(tree), held))
        if self.manifest["buffer"]:
            out.append(CellPartition(self.manifest["buffer"], -1, [1]))
        return out or [CellPartition("", 0, [])]

    def read(self, partition: CellPartition) -> Iterator[pa.RecordBatch]:
        if not partition.path:
            return
        names = ["tree", "node", "point_id", *(f"c{j}" for j in range(self.d)), "seq"]
        store, at = _store(partition.path)
        rows = ds.dataset(at, filesystem=store, format="parquet").to_table(columns=names, filter=(ds.field("tree") == partition.tree) & ds.field("node").isin(partition.nodes))
        if self.manifest["tombs"]:
            gone = _table(self.manifest["tombs"]).select(["tree", "node", "point_id"])
            gone = gone.filter((ds.field("tree") == partition.tree) & ds.field("node").isin(partition.nodes))
            rows = rows.join(gone.group_by(["tree", "node", "point_id"]).aggregate([]), ["tree", "node", "point_id"], join_type="left anti")
        schema = pa.schema([("tree", pa.int32()), ("node", pa.int64()), ("point_id", pa.int64()), *((f"c{j}", pa.float64()) for j in range(self.d)), ("seq", pa.int64())])
        yield from rows.select(names).cast(schema).to_batches()


class IndexSource(DataSource):
    """``spark.read.format("kdforest").option("version", v).load(root)``: the live points of a saved index (tree, node, point_id, c0.., seq)."""

    @classmethod
    def name(cls) -> str:
        return "kdforest"

    def _version(self) -> int | None:
        return int(self.options["version"]) if "version" in self.options else None

    def schema(self) -> str:
        d = manifest(self.options["path"], self._version())["options"]["d"]
        return "tree int, node long, point_id long, " + ", ".join(f"c{j} double" for j in range(d)) + ", seq long"

    def reader(self, schema) -> IndexReader:
        return IndexReader(self.options["path"], self._version())


def register(spark: SparkSession) -> None:
    spark.conf.set("spark.sql.python.filterPushdown.enabled", "true")
    spark.dataSource.register(IndexSource)
