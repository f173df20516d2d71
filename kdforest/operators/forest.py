"""The log-forest: a small buffer and static kd-trees of doubling capacity, updated in batches.

A manifest (mask of nonempty trees, counts, paths) is all the state a driver keeps; each update writes new files
and a new manifest version, so readers of older versions are not disturbed.
"""

from __future__ import annotations

import json
from dataclasses import dataclass, field, replace

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from kdforest.functions.geometry import coords
from kdforest.operators import bloom as bloom_filter
from kdforest.operators import tree as kd
from kdforest.operators.cells import LEAF
from kdforest.operators.primitives import ranks
from kdforest.operators.spatial import dual_search
from kdforest.plans.schedule import bits, plan_insert, shares
from kdforest.shared import emptied, local_table, read_back, small, written


@dataclass
class Slot:
    """A static tree: its cells' splits, boxes and live counts, its points' table and its counts."""

    cap: int
    points: DataFrame
    splits: list
    cells: list
    built: int
    live: int
    path: str | None = None
    blooms: dict[str, tuple[int, DataFrame]] = field(default_factory=dict)  # by the kind of key: bits and rows


@dataclass
class State:
    version: int = 0
    mask: int = 0
    buffered: int = 0
    buffer: DataFrame | None = None
    slots: dict[int, Slot] = field(default_factory=dict)
    tombs: DataFrame | None = None
    moved: int = 0
    batches: tuple = ()
    probed: int = 0


class LogForest:
    """Batch-dynamic nearest-neighbour index.

    ``x`` is the buffer's size, ``cap`` a cell's, ``leaf`` that of a leaf inside a cell; trees of up to ``serial`` points are
    one cell. ``min_fill`` is the share of its capacity below which a tree is emptied into a new insert, ``bloom``
    "lazy" (built at the first delete), "eager" or "off".
    """

    def __init__(self, spark: SparkSession, d: int, x: int = 1024, rule: str = "object", cap: int = kd.CELL_CAP, min_fill: float = 0.5, bloom: str = "lazy", hashes: int = 3, leaf: int = LEAF, serial: int = 0):
        self.spark, self.d, self.x, self.rule, self.cap, self.min_fill, self.bloom, self.hashes, self.leaf, self.serial = spark, d, x, rule, cap, min_fill, bloom, hashes, leaf, serial
        self.columns = ["point_id", *coords(d), "seq"]
        self.states = [State()]
        self.history: list[dict] = []

    @property
    def state(self) -> State:
        return self.states[-1]

    @property
    def mask(self) -> int:
        return self.state.mask

    def _commit(self, new: State, kind: str, rows: int) -> None:
        new.version = self.state.version + 1
        self.states.append(new)
        self.history.append({"version": new.version, "kind": kind, "rows": rows, "mask": new.mask, "buffered": new.buffered, "moved": new.moved, "probed": new.probed, "trees": {i: (s.cap, s.built, s.live) for i, s in new.slots.items()}})

    def save(self, root: str) -> int:
        """Commits the newest version to ``root``: a version is there once its manifest is written as a whole. Points stay where they are."""
        s, spark = self.state, self.spark
        keep = lambda df, name: None if df is None else getattr(df, "scratch", None) or written(df, name).scratch
        cells = [(i, c["node"], c["n"], [float(c[f"lo{j}"]) for j in range(self.d)], [float(c[f"hi{j}"]) for j in range(self.d)]) for i, x in s.slots.items() for c in x.cells]
        splits = [tuple(p) for x in s.slots.values() for p in x.splits]
        at = f"{root.rstrip('/')}/tables/v{s.version}"
        local_table(spark, cells, "tree int, node long, n long, lo array<double>, hi array<double>").coalesce(1).write.mode("overwrite").parquet(f"{at}/cells")
        local_table(spark, splits, "tree int, node long, dim int, val double").coalesce(1).write.mode("overwrite").parquet(f"{at}/splits")
        options = {k: getattr(self, k) for k in ("d", "x", "rule", "cap", "min_fill", "bloom", "hashes", "leaf", "serial")}
        slots = {i: {"cap": x.cap, "built": x.built, "live": x.live, "path": x.path} for i, x in s.slots.items()}
        line = {"version": s.version, "options": options, "mask": s.mask, "buffered": s.buffered, "buffer": keep(s.buffer, "buffer"), "slots": slots, "tombs": keep(s.tombs, "tombs"), "tables": at, "batches": [json.dumps(b) for b in s.batches], "history": self.history}
        local_table(spark, [(json.dumps(line),)], "value string").coalesce(1).write.mode("overwrite").text(f"{root.rstrip('/')}/manifest/version={s.version}")
        return s.version

    @classmethod
    def load(cls, spark: SparkSession, root: str, version: int | None = None) -> LogForest:
        """The index as ``save`` left it, the newest version or a given one; it can be searched and updated further."""
        lines = spark.read.text(f"{root.rstrip('/')}/manifest")
        lines = lines if version is None else lines.where(F.col("version") == version)
        row = lines.orderBy(F.desc("version")).first()
        if row is None:
            raise ValueError(f"no such version: {version}")
        m = json.loads(row.value)
        index = cls(spark, **m["options"])
        rows = {"cells": spark.read.parquet(f"{m['tables']}/cells").collect(), "splits": spark.read.parquet(f"{m['tables']}/splits").collect()}  # a row per cell and split
        point = "tree int, node long, leaf long, point_id long, " + ", ".join(f"{c} double" for c in coords(index.d)) + ", seq long"
        s = State(m["version"], m["mask"], m["buffered"], batches=tuple(tuple(b) if isinstance(b, list) else b for b in map(json.loads, m["batches"])))
        for i, x in ((int(i), x) for i, x in m["slots"].items()):
            cells = [{"tree": i, "node": c.node, "n": c.n} | {f"lo{j}": v for j, v in enumerate(c.lo)} | {f"hi{j}": v for j, v in enumerate(c.hi)} for c in rows["cells"] if c.tree == i]
            points = read_back(spark, x["path"], point).where(F.col("tree") == i)
            s.slots[i] = Slot(x["cap"], points, [tuple(p) for p in rows["splits"] if p.tree == i], cells, x["built"], x["live"], x["path"])
        s.buffer = read_back(spark, m["buffer"], point) if m["buffer"] else None
        s.tombs = read_back(spark, m["tombs"], "tree int, node long, point_id long, gen int") if m["tombs"] else None
        index.states, index.history = [s], m["history"]
        return index

    def vacuum(self, keep: int = 1) -> int:
        """Forgets all but the last ``keep`` versions and frees the tables that only forgotten ones use; returns how many."""

        def used(states: list[State]) -> set[str]:
            frames = [getattr(f, "scratch", None) for s in states for f in (s.buffer, s.tombs, *(b[1] for x in s.slots.values() for b in x.blooms.values()))]
            return {p for p in [*frames, *(x.path for s in states for x in s.slots.values())] if p}

        old, self.states = self.states[:-keep], self.states[-keep:]
        gone = used(old) - used(self.states)
        for path in gone:
            emptied(self.spark, path)
        return len(gone)

    def compact(self) -> None:
        """Rewrites all live points as a new forest without tombstones; the result is a new version."""
        s = State(version=self.state.version, batches=self.state.batches)
        rows = written(self.live(), "compacted")
        n = rows.count()
        self._commit(self._inserted(s, rows, n), "compact", n)

    def insert(self, batch: DataFrame, batch_id: object = None) -> None:
        """Adds points (point_id, c0.., seq). A ``batch_id`` that was seen before changes nothing."""
        s = self.state
        if batch_id is not None and batch_id in s.batches:
            return
        rows = written(batch.select(*self.columns), "batch")
        n = rows.count()
        new = self._inserted(replace(s, slots=dict(s.slots), moved=0, probed=0), rows, n)
        new.batches = (*s.batches, batch_id) if batch_id is not None else s.batches
        self._commit(new, "insert", n)

    def _buffer(self, rows: DataFrame) -> DataFrame:
        """The buffer's table: one cell of tree -1, whose nodes are searched in heap order."""
        one = rows.select(F.lit(-1).alias("tree"), F.lit(1).cast("long").alias("node"), *self.columns)
        return kd.stored(kd.Forest(one, self.d), self.leaf, self.rule).points

    def _inserted(self, s: State, rows: DataFrame, n: int) -> State:
        if not n:
            return s
        p = plan_insert(s.mask, s.buffered, self.x, n)
        young = rows.select(F.lit(1).alias("stage"), *self.columns)
        if s.buffer is not None:
            young = young.unionByName(s.buffer.select(F.lit(1).alias("stage"), *self.columns))
        if not p.appear:  # everything fits in the buffer
            s.buffer, s.buffered = self._buffer(young), p.buffer
            return s
        pool = young
        for i in p.vanish:
            pool = pool.unionByName(self._live_of(s, i).select(F.lit(0).alias("stage"), *self.columns))
        old = sum(s.slots[i].live for i in p.vanish)
        total = old + s.buffered + n - p.buffer
        order = ranks(pool, ["stage", "seq", "point_id"])
        caps = [self.x << i for i in p.appear]
        cuts = shares(total, caps)
        target = F.lit(-1)
        for i, (lo, hi) in zip(p.appear, zip(cuts, cuts[1:], strict=False), strict=True):
            target = F.when((F.col("rank") >= lo) & (F.col("rank") < hi), F.lit(i)).otherwise(target)
        dealt = order.withColumn("tree", target)
        s.buffer = self._buffer(dealt.where("tree = -1")) if p.buffer else None
        built = kd.stored(kd.build(dealt.where("tree >= 0"), self.d, self.rule, self.cap, serial=self.serial), self.leaf, self.rule)
        for i in p.vanish:
            s.slots.pop(i)
        if s.tombs is not None and p.vanish:
            s.tombs = written(s.tombs.where(~F.col("tree").isin(list(p.vanish))), "tombs")
        for i, lo, hi, cap in zip(p.appear, cuts, cuts[1:], caps, strict=False):
            own = Slot(cap, built.points.where(F.col("tree") == i), [x for x in built.splits if x[0] == i], [c for c in built.cells if c["tree"] == i], hi - lo, hi - lo, built.points.scratch)
            s.slots[i] = own
        if self.bloom == "eager":
            self._blooms(s, list(p.appear), "coords")
        s.mask, s.buffered, s.moved = p.mask, p.buffer, s.moved + total
        return s

    def _live_of(self, s: State, i: int) -> DataFrame:
        slot, key = s.slots[i], ["tree", "node", "point_id"]
        return slot.points if s.tombs is None else slot.points.join(small(s.tombs.where(F.col("tree") == i).select(*key), slot.built - slot.live), key, "left_anti")

    def _keys(self, kind: str) -> list[str]:
        return ["point_id"] if kind == "id" else coords(self.d)

    def _blooms(self, s: State, trees: list[int], kind: str) -> None:
        for i in trees:
            if kind not in s.slots[i].blooms:
                bits = bloom_filter.bits_for(s.slots[i].built)
                rows = written(bloom_filter.build(s.slots[i].points, self._keys(kind), bits, self.hashes), "bloom")
                s.slots[i] = replace(s.slots[i], blooms=s.slots[i].blooms | {kind: (bits, rows)})

    def prefiltered(self, batch: DataFrame, kind: str = "coords", state: State | None = None, rows: int | None = None) -> DataFrame:
        """(tree, c0.. or point_id): the keys of a delete batch that each tree may hold, by its Bloom filter over coordinates or ids."""
        s, keys = state or self.state, self._keys(kind)
        self._blooms(s, list(s.slots), kind)
        if not s.slots:
            return batch.select(F.lit(0).alias("tree"), *keys).where("false")
        filters = None
        for slot in s.slots.values():
            filters = slot.blooms[kind][1] if filters is None else filters.unionByName(slot.blooms[kind][1])
        return bloom_filter.candidates(batch, filters, keys, {i: x.blooms[kind][0] for i, x in s.slots.items()}, self.hashes, rows)

    def delete(self, batch: DataFrame, key: str = "id", batch_id: object = None) -> int:
        """Deletes the points that ``batch`` (point_id, c0..) names, all equal ones for key "coords"; returns how many.

        The batch is routed to the cells it may be in, less what the trees' Bloom filters exclude; coordinates that come
        with key "id" must be those of the points. Trees left with under ``min_fill`` of their capacity are emptied and
        their points inserted again.
        """
        s = replace(self.state, slots=dict(self.state.slots), moved=0, probed=0)
        if batch_id is not None and batch_id in s.batches:
            return 0
        rows = written(batch.select(*[c for c in self.columns if c in batch.columns and c != "seq"]), "erase")
        gone = 0
        if s.slots:
            named, n = rows, rows.count()
            kind = "coords" if set(coords(self.d)) <= set(rows.columns) else "id"
            s.probed = n * len(s.slots)
            if self.bloom != "off":
                may = self.prefiltered(rows, kind, s, n)
                named = written(may if key == "coords" or kind == "id" else may.join(small(rows, n), self._keys(kind)), "candidates")
                s.probed = named.count()
            hits = written(kd.erase(self._as_forest(s, list(s.slots)), named, max(n, s.probed), key), "tombs")
            if s.tombs is not None:
                dead = small(s.tombs, sum(x.built - x.live for x in s.slots.values()))
                hits = written(hits.join(dead, ["tree", "node", "point_id"], "left_anti"), "tombs")
            counts = {(r.tree, r.node): r.n for r in hits.groupBy("tree", "node").agg(F.count("*").alias("n")).collect()}  # a row per cell at most
            if counts:
                s.tombs = hits if s.tombs is None else written(s.tombs.unionByName(hits), "tombs")
                for i in {t for t, _ in counts}:
                    n = sum(v for (t, _), v in counts.items() if t == i)
                    s.slots[i] = replace(s.slots[i], live=s.slots[i].live - n, cells=kd.erased(s.slots[i].cells, counts))
                gone += sum(counts.values())
        if s.buffer is not None:
            on = {"id": ["point_id"], "coords": coords(self.d)}.get(key, ["point_id", *coords(self.d)])
            near = rows.join(small(s.buffer.select(*on), s.buffered), on, "left_semi")  # the batch may be large, the buffer is not
            stay = s.buffer.join(kd.matches(s.buffer, near, self.d, key).select("point_id"), "point_id", "left_anti").select(*self.columns)
            stay = self._buffer(stay)
            n = stay.count()
            gone += s.buffered - n
            s.buffer, s.buffered = (stay if n else None), n
        poor = [i for i, x in s.slots.items() if x.live < self.min_fill * x.cap]
        if poor:
            again = None
            for i in poor:
                part = self._live_of(s, i).select(*self.columns)
                again = part if again is None else again.unionByName(part)
            again, n = written(again, "reinserted"), sum(s.slots[i].live for i in poor)
            for i in poor:
                s.slots.pop(i)
                s.mask &= ~(1 << i)
            s.tombs = written(s.tombs.where(~F.col("tree").isin(poor)), "tombs")
            s = self._inserted(s, again, n)
        s.batches = (*s.batches, batch_id) if batch_id is not None else s.batches
        self._commit(s, "delete", gone)
        return gone

    def live(self, version: int | None = None) -> DataFrame:
        """All points of the newest or an older version."""
        s = self.state if version is None else next((x for x in self.states if x.version == version), None)
        if s is None:
            raise ValueError(f"no such version: {version}")
        parts = [self._live_of(s, i).select(*self.columns) for i in s.slots] + ([s.buffer.select(*self.columns)] if s.buffer is not None else [])
        if not parts:
            return local_table(self.spark, [], "point_id long, " + ", ".join(f"{c} double" for c in coords(self.d)) + ", seq long")
        out = parts[0]
        for p in parts[1:]:
            out = out.unionByName(p)
        return out

    def _as_forest(self, s: State, trees: list[int]) -> kd.Forest:
        """Trees as one; the buffer is tree -1 with a single cell."""
        points, splits, cells = None, [], []
        for i in trees:
            if i < 0:
                part = s.buffer.select("tree", "node", "leaf", *self.columns)
                own = kd.cell_table(part, self.d)
            else:
                part, own = s.slots[i].points.select("tree", "node", "leaf", *self.columns), s.slots[i].cells
                splits += s.slots[i].splits
            cells += own
            points = part if points is None else points.unionByName(part)
        return kd.Forest(points, self.d, splits, cells)

    def knn(self, queries: DataFrame, k: int, schedule: str = "tree_serial", order: str = "desc", metric: str = "euclid", exclude_self: bool = False) -> DataFrame:
        """(query_id, rank, point_id, d2) of the k nearest live points to each query (query_id, q0..); exact.

        Schedules: "tree_serial" takes the trees one after another (largest first, or last with order "asc") and hands each
        query's bound on, the small ones together; "all_parallel" searches all trees at once, each with a bound of
        its own; "query_outer" takes each query through all trees together: its home cells in all of them give one bound, which
        prunes every tree's cells. That is done for all queries at once, without a limit to their number. "dual" puts the
        queries in a tree too, whose cells share a bound.
        """
        s = self.state
        queries = queries.select("query_id", *coords(self.d, "q"), F.lit(None).cast("double").alias("r2"))
        trees = sorted(s.slots, reverse=order == "desc")
        trees = ([*trees, -1] if order == "desc" else [-1, *trees]) if s.buffer is not None else trees
        if not trees:
            return queries.select("query_id", F.lit(1).alias("rank"), F.col("query_id").alias("point_id"), F.lit(0.0).alias("d2")).where("false")
        if schedule == "all_parallel":
            found = kd.search(queries, self._as_forest(s, trees), k, metric, exclude_self=exclude_self, tombs=s.tombs, shared_bound=False)
            return kd.ranked(found, k)
        if schedule == "query_outer":
            return kd.ranked(kd.search(queries, self._as_forest(s, trees), k, metric, exclude_self=exclude_self, tombs=s.tombs), k)
        if schedule == "dual":
            return dual_search(queries, self._as_forest(s, trees), k, self.cap, self.rule, metric, exclude_self, s.tombs)
        if schedule != "tree_serial":
            raise ValueError(f"no such schedule: {schedule}")
        total = sum(s.slots[i].live for i in s.slots) + s.buffered
        rounds, tail = [], []
        for i in trees:  # trees with under a tenth of the points are one round
            (tail if i < 0 or s.slots[i].live * 10 < total else rounds).append(i)
        groups = [[i] for i in rounds] + ([tail] if tail else [])
        groups = groups if order == "desc" else ([tail] if tail else []) + [[i] for i in rounds]
        best = None
        for g in groups:
            asked = queries
            if best is not None:
                bound = best.groupBy("query_id").agg(F.max("d2").alias("b"), F.count("*").alias("m")).where(F.col("m") >= k)
                asked = queries.drop("r2").join(bound.select("query_id", F.col("b").alias("r2")), "query_id", "left")
            found = kd.search(asked, self._as_forest(s, g), k, metric, exclude_self=exclude_self, tombs=s.tombs, homes=best is None)
            found = found if best is None else kd.top_k(best.unionByName(found), k).select("query_id", "point_id", "d2")
            best = found if g is groups[-1] else written(found, "best")
        return kd.ranked(best, k)

    def shape(self) -> DataFrame:
        """(tree, cap, built, live) of the nonempty trees; the buffer is tree -1."""
        s = self.state
        rows = [(i, x.cap, x.built, x.live) for i, x in sorted(s.slots.items())] + [(-1, self.x, s.buffered, s.buffered)]
        return local_table(self.spark, rows, "tree int, cap long, built long, live long")

    def bits(self) -> tuple[int, ...]:
        return bits(self.state.mask)
