"""Static kd-trees as tables: building, routing, exact two-round search, routed deletion.

Points are rows (tree, node, leaf, point_id, c0.., seq). A node of the upper part is named by its path from the root
(1; children 2i and 2i + 1); its leaves are cells, whose rows lie together in files and in tasks. ``leaf`` numbers the nodes
inside a cell in the same way (see ``cells``). Splits and boxes of the upper part are small tables that go along with a
task up to a checked number of rows, and are joined level by level beyond it. Several trees are built, routed and
searched at once, keyed by (tree, node).
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from kdforest.functions.geometry import coords, mind2
from kdforest.operators import cells as inside
from kdforest.shared import BROADCAST_ROWS, local_table, small, written

#: Points of a cell; few here so that tests have many cells. On a cluster take ``cap_for``.
CELL_CAP = 4096
MOST_LEVELS = 40
#: Rows that a build takes to the driver at most (about) to choose splits; all rows of smaller tables.
SAMPLE = 100_000
#: Queries that a task takes to one cell at a time; a cell with more is searched in several tasks.
QUERY_BLOCK = 200_000
#: Bytes of a node whose rows one task takes in to choose all splits below it; larger nodes are split a level at a time over all tasks.
TASK_BYTES = 24 << 20
#: Splits that a plan names as arrays to route rows by; more are taken along by Python.
STEPS = 4096
Split = tuple  # tree, node, dimension, value and, if equal values are parted, an id: left iff below; dimension d is the id
#: Set to a smaller number of rows in tests of the way beyond it.
ALONG = BROADCAST_ROWS


def cap_for(d: int, cell_bytes: int = 128 << 20) -> int:
    """Points of a cell of about ``cell_bytes``."""
    return max(1, cell_bytes // (8 * (d + 5)))


class TopTree:
    """Boxes and live counts of the nodes above the cells of several trees, as arrays. Empty cells and paths to them are collapsed."""

    def __init__(self, cells: list[dict], d: int, trees: list[int] | None = None):
        rows = [c for c in cells if c["n"] > 0 and (trees is None or c["tree"] in trees)]
        tree, node = np.array([c["tree"] for c in rows], dtype=np.int64), np.array([c["node"] for c in rows], dtype=np.int64)
        live = np.array([c["n"] for c in rows], dtype=np.int64)
        self.tree, self.node, self.live = tree, node, live
        self.lo, self.hi = (np.array([[c[f"{a}{j}"] for j in range(d)] for c in rows], dtype=np.float64).reshape(len(rows), d) for a in ("lo", "hi"))
        self.left, self.right = np.full(len(rows), -1), np.full(len(rows), -1)
        self.roots: dict[int, int] = {}
        made: dict[str, list] = {k: [] for k in ("tree", "node", "live", "lo", "hi", "left", "right")}
        size, by_depth, front = len(rows), {}, {}
        for i, key in enumerate(zip(tree.tolist(), node.tolist(), strict=True)):
            by_depth.setdefault(key[1].bit_length(), []).append(key)
            front[key] = i

        def of(name: str, at: int) -> object:
            return made[name][at - size] if at >= size else getattr(self, name)[at]

        for depth in range(max(by_depth, default=1), 1, -1):
            for t, n in by_depth.get(depth, []):
                if (t, n) not in front:
                    continue  # its sibling took it along
                i, other = front.pop((t, n)), front.pop((t, n ^ 1), None)
                by_depth.setdefault(depth - 1, []).append((t, n >> 1))
                front[t, n >> 1] = i  # the only child stands for its parent
                if other is not None:
                    low, high = (other, i) if n & 1 else (i, other)
                    pair = {"tree": t, "node": n >> 1, "live": of("live", i) + of("live", other), "left": low, "right": high}
                    pair |= {"lo": np.minimum(of("lo", i), of("lo", other)), "hi": np.maximum(of("hi", i), of("hi", other))}
                    for name, value in pair.items():
                        made[name].append(value)
                    front[t, n >> 1] = size + len(made["tree"]) - 1
        for name, more in made.items():
            if more:
                setattr(self, name, np.concatenate([getattr(self, name), np.array(more)]))
        self.roots = {t: i for (t, _), i in front.items()}

    def __len__(self) -> int:
        return len(self.tree)

    def largest(self) -> int:
        return max(self.roots, key=lambda t: self.live[self.roots[t]])

    def home(self, q: np.ndarray, tree: int, k: int, metric: str) -> tuple[np.ndarray, np.ndarray]:
        """The cell (a row number) nearest to each query's way down, and a bound: the far side of the smallest node with k live points."""
        at = np.full(len(q), self.roots[tree])
        r2 = np.full(len(q), np.inf)
        down = np.arange(len(q))
        while len(down):
            now = at[down]
            far = inside.box_most(q[down], self.lo[now], self.hi[now], metric)
            r2[down] = np.where(self.live[now] >= k, np.minimum(r2[down], far), r2[down])
            deep = self.left[now] >= 0
            down, now = down[deep], now[deep]
            l, r = self.left[now], self.right[now]
            nearer = inside.box_least(q[down], self.lo[l], self.hi[l], metric) <= inside.box_least(q[down], self.lo[r], self.hi[r], metric)
            at[down] = np.where(nearer, l, r)
        return at, r2

    def within(self, q: np.ndarray, r2: np.ndarray, metric: str, trees: list[int]) -> tuple[np.ndarray, np.ndarray]:
        """(query, cell) pairs whose box is within the bound, of all ``trees``; both are row numbers."""
        out_q, out_c = [], []
        row = np.tile(np.arange(len(q)), len(trees))
        at = np.repeat([self.roots[t] for t in trees], len(q)).astype(np.int64)
        while len(row):
            near = inside.box_least(q[row], self.lo[at], self.hi[at], metric) <= r2[row]
            row, at = row[near], at[near]
            cell = self.left[at] < 0
            out_q.append(row[cell])
            out_c.append(at[cell])
            row, at = np.repeat(row[~cell], 2), np.column_stack([self.left[at[~cell]], self.right[at[~cell]]]).ravel()
        return (np.concatenate(out_q), np.concatenate(out_c)) if out_q else (row, at)

    def near_boxes(self, lo: np.ndarray, hi: np.ndarray, r2: np.ndarray, metric: str) -> tuple[np.ndarray, np.ndarray]:
        """(box, cell) pairs whose distance is within the box's bound: two trees walked as one."""
        out_q, out_c = [], []
        row = np.tile(np.arange(len(lo)), len(self.roots))
        at = np.repeat(list(self.roots.values()), len(lo)).astype(np.int64)
        while len(row):
            gap = inside.combined([np.maximum(np.maximum(self.lo[at, j] - hi[row, j], 0.0), lo[row, j] - self.hi[at, j]) for j in range(lo.shape[1])], metric)
            near = gap <= r2[row]
            row, at = row[near], at[near]
            cell = self.left[at] < 0
            out_q.append(row[cell])
            out_c.append(at[cell])
            row, at = np.repeat(row[~cell], 2), np.column_stack([self.left[at[~cell]], self.right[at[~cell]]]).ravel()
        return np.concatenate([*out_q, row]), np.concatenate([*out_c, at])


@dataclass
class Forest:
    """Trees whose cells are known: the points table, the splits and the closed boxes of the cells."""

    points: DataFrame
    d: int
    splits: list[Split] = field(default_factory=list)
    cells: list[dict] = field(default_factory=list)

    @property
    def trees(self) -> list[int]:
        return sorted({c["tree"] for c in self.cells if c["n"] > 0})

    def depth(self) -> int:
        return max((c["node"].bit_length() for c in self.cells), default=1) - 1

    def top(self, trees: list[int] | None = None) -> TopTree:
        return TopTree(self.cells, self.d, trees)

    def nodes(self, spark: SparkSession) -> tuple[DataFrame, int]:
        """(tree, parent, node, lo0.., hi0..): children and their boxes; a cell is its own child. A row per node."""
        boxes: dict[tuple[int, int], list[list[float]]] = {}
        leaf = {(c["tree"], c["node"]) for c in self.cells}
        for c in self.cells:
            lo, hi = [c[f"lo{j}"] for j in range(self.d)], [c[f"hi{j}"] for j in range(self.d)]
            node = c["node"]
            while node:
                have = boxes.get((c["tree"], node))
                boxes[c["tree"], node] = [list(map(min, have[0], lo)), list(map(max, have[1], hi))] if have else [lo, hi]
                node //= 2
        rows = [(t, n // 2, n, *lo, *hi) for (t, n), (lo, hi) in boxes.items()] + [(t, n, n, *boxes[t, n][0], *boxes[t, n][1]) for t, n in leaf]
        schema = "tree int, parent long, node long, " + ", ".join(f"{a} double" for a in (*coords(self.d, "lo"), *coords(self.d, "hi")))
        return local_table(spark, rows, schema), len(rows)


def _one_level(df: DataFrame, splits: list[Split], d: int, prefix: str = "c") -> DataFrame:
    """Rows whose (tree, node) is split go to the child on their side."""
    table = local_table(df.sparkSession, [(*s[:4], s[4] if len(s) > 4 else None) for s in splits], "tree int, node long, dim int, val double, tie long")
    df = df.join(small(table, len(splits)), ["tree", "node"], "left")
    own = [F.col("point_id").cast("double")] if "point_id" in df.columns else []  # queries have none
    x = F.get(F.array(*coords(d, prefix), *own), F.col("dim"))
    right = x >= F.col("val")
    if own:
        right = right & ((x > F.col("val")) | F.col("tie").isNull() | (F.col("point_id") >= F.col("tie")))
    moved = F.when(F.col("dim").isNull(), F.col("node")).otherwise(F.col("node") * 2 + right.cast("long"))
    return df.withColumn("node", moved).drop("dim", "val", "tie")


class Router:
    """Splits as arrays; takes rows down from the node they are in."""

    def __init__(self, splits: list[Split]):
        key = np.array([(s[0] + 1 << 48) + s[1] for s in splits], dtype=np.int64)
        by = np.argsort(key)
        self.key = key[by]
        self.dim = np.array([s[2] for s in splits], dtype=np.int64)[by]
        self.val = np.array([s[3] for s in splits], dtype=np.float64)[by]
        self.tie = np.array([s[4] if len(s) > 4 else np.nan for s in splits], dtype=np.float64)[by]
        self.tied = not np.isnan(self.tie).all()

    def down(self, tree: np.ndarray, node: np.ndarray, x: np.ndarray, both: int | None = None, ids: bool = True) -> tuple[np.ndarray, np.ndarray]:
        """(row, node): the cell of each row; with ``both``, rows go to either side of a split in that dimension, or that parts their value by id.

        The last column of ``x`` is the id, if there are ``ids``.
        """
        row, node, done_row, done_node = np.arange(len(node)), node.astype(np.int64), [], []
        base = (tree.astype(np.int64) + 1) << 48
        while len(row) and len(self.key):
            key = base[row] + node
            at = np.minimum(np.searchsorted(self.key, key), len(self.key) - 1)
            split = self.key[at] == key
            done_row.append(row[~split])
            done_node.append(node[~split])
            row, node, at = row[split], node[split], at[split]
            value = x[row, np.minimum(self.dim[at], x.shape[1] - 1)]
            right = value >= self.val[at]
            level = (value == self.val[at]) & ~np.isnan(self.tie[at]) if self.tied else np.zeros(len(at), dtype=bool)
            if ids and both is None:
                right &= ~level | (x[row, -1] >= self.tie[at])
            if both is not None and (twin := (self.dim[at] == both) | level).any():
                row, node = np.concatenate([row, row[twin]]), np.concatenate([2 * node + (right & ~twin), 2 * node[twin] + 1])
            else:
                node = 2 * node + right
        row, node = np.concatenate([*done_row, row]), np.concatenate([*done_node, node])
        order = np.argsort(row, kind="stable")
        return row[order], node[order]


def route(df: DataFrame, splits: list[Split], d: int, prefix: str = "c", both: bool = False) -> DataFrame:
    """Each row's cell, from the node (tree, node) it is in. ``both``: rows are a batch that names coordinates, not ids."""
    if not splits:
        return df
    if len(splits) > ALONG and not both:
        by_depth: dict[int, list[Split]] = {}
        for s in splits:
            by_depth.setdefault(s[1].bit_length(), []).append(s)
        for depth in sorted(by_depth):
            df = _one_level(df, by_depth[depth], d, prefix)
        return df
    router, names = Router(splits), [*coords(d, prefix), *(["point_id"] if "point_id" in df.columns else [])]

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            x = np.column_stack([b.column(c).to_numpy(zero_copy_only=False).astype(np.float64) for c in names])
            row, node = router.down(b.column("tree").to_numpy(), b.column("node").to_numpy(), x, d if both else None, "point_id" in names)
            out = b if len(row) == b.num_rows else b.take(pa.array(row))
            yield out.set_column(out.schema.get_field_index("node"), "node", pa.array(node, pa.int64()))

    return df.mapInArrow(work, df.schema)


def _cell_stats(points: DataFrame, d: int, by: list[str] | None = None) -> list[dict]:
    agg = [f(c).alias(f"{a}{j}") for j, c in enumerate(coords(d)) for f, a in ((F.min, "lo"), (F.max, "hi"))]
    agg += [F.min("point_id").alias("lo_id"), F.max("point_id").alias("hi_id")]
    return [r.asDict() for r in points.groupBy(*(by or ["tree", "node"])).agg(F.count("*").alias("n"), *agg).collect()]


def cell_table(points: DataFrame, d: int) -> list[dict]:
    """n and the tight box of each (tree, node): one hash aggregate; a row per cell comes back."""
    return [{k: v for k, v in c.items() if k not in ("lo_id", "hi_id")} for c in _cell_stats(points, d)]


def choose_splits(cells: list[dict], d: int, rule: str, cap: int, median_of: dict | None = None) -> list[Split]:
    """A split for each cell over ``cap``: by the depth's dimension, or the next with any extent; of equal points by id, if ids are known."""
    out = []
    for c in cells:
        depth = c["node"].bit_length() - 1
        dim = next((j % d for j in range(depth, depth + d) if c[f"lo{j % d}"] < c[f"hi{j % d}"]), None)
        if c["n"] <= cap or depth >= MOST_LEVELS:
            continue
        if dim is None:
            if c.get("lo_id") is not None and c["lo_id"] < c["hi_id"]:
                out.append((c["tree"], c["node"], d, (c["lo_id"] + c["hi_id"] + 1) / 2))
            continue
        lo, hi = c[f"lo{dim}"], c[f"hi{dim}"]
        val = median_of.get((c["tree"], c["node"])) if rule == "object" and dim == depth % d and median_of else None
        if val is None or not lo < val <= hi:
            val = (lo + hi) / 2
            val = val if lo < val <= hi else hi
        out.append((c["tree"], c["node"], dim, val))
    return out


def sampled_splits(over: list[dict], rows: pa.Table, d: int, cap: int) -> list[Split]:
    """Splits by object median of the cells ``over`` the cap, as many levels as their counts need, from a sample of their rows."""
    tree, node = rows.column("tree").to_numpy(), rows.column("node").to_numpy()
    x = np.column_stack([rows.column(c).to_numpy() for c in coords(d)]) if rows.num_rows else np.zeros((0, d))
    out: list[Split] = []
    for c in over:
        own = np.flatnonzero((tree == c["tree"]) & (node == c["node"]))
        todo = [(c["node"], own, float(c["n"]))]
        while todo:
            at, some, n = todo.pop()
            depth = at.bit_length() - 1
            if n <= cap or len(some) < 2 or depth >= MOST_LEVELS:
                continue
            lo, hi = x[some].min(axis=0), x[some].max(axis=0)
            dim = next((j % d for j in range(depth, depth + d) if lo[j % d] < hi[j % d]), None)
            if dim is None:
                continue
            value = x[some, dim]
            val = float(np.partition(value, len(some) // 2)[len(some) // 2])
            if val <= lo[dim]:  # many equal values: those above them go right
                val = float(value[value > lo[dim]].min())
            left = value < val
            out.append((c["tree"], at, dim, val))
            share = left.mean()
            todo += [(2 * at, some[left], n * share), (2 * at + 1, some[~left], n * (1 - share))]
    return out


def task_rows(d: int) -> int:
    return max(2, TASK_BYTES // (8 * (d + 3)))


@dataclass(frozen=True)
class Halving:
    """How nodes of over ``cap`` rows are split: by ``rule``, down to ``levels``; with ``cycle`` in the depth's dimension
    even if all its values are equal (all rows go right then), with ``ties`` at the middle row by (value, id)."""

    d: int
    rule: str
    cap: int
    levels: int = MOST_LEVELS
    cycle: bool = False
    ties: bool = False

    def dim(self, node: int, lo: np.ndarray | list, hi: np.ndarray | list) -> int | None:
        depth = node.bit_length() - 1
        return depth % self.d if self.cycle else next((j % self.d for j in range(depth, depth + self.d) if lo[j % self.d] < hi[j % self.d]), None)

    def middle(self, lo: float, hi: float) -> float:
        val = (lo + hi) / 2
        return val if self.cycle or lo < val <= hi else hi

    def below(self, tree: int, node: int, x: np.ndarray, ids: np.ndarray) -> tuple[list[Split], list[tuple]]:
        """All splits below a node, from all its rows, and the cells (tree, node, n, lo, hi)."""
        splits, cells, todo = [], [], [(node, np.ascontiguousarray(x.T), ids)]
        while todo:
            at, own_x, own = todo.pop()
            lo, hi = own_x.min(axis=1), own_x.max(axis=1)
            split = right = None
            if len(own) > self.cap and at.bit_length() <= self.levels:
                dim = self.dim(at, lo, hi)
                value = own_x[dim] if dim is not None else None
                if dim is None:
                    split = (tree, at, self.d, float(int(own.min()) + int(own.max()) + 1) / 2)
                    right = own >= split[3]
                elif self.rule != "object":
                    split = (tree, at, dim, self.middle(float(lo[dim]), float(hi[dim])))
                    right = value >= split[3]
                elif self.ties:
                    pick = np.lexsort((own, value))[len(own) // 2]
                    split = (tree, at, dim, float(value[pick]), int(own[pick]))
                    right = (value > value[pick]) | ((value == value[pick]) & (own >= own[pick]))
                else:
                    val = float(np.partition(value, len(own) // 2)[len(own) // 2])
                    if not self.cycle and val <= lo[dim]:  # many equal values: those above them go right
                        val = float(value[value > lo[dim]].min())
                    split, right = (tree, at, dim, val), value >= val
                if right.all() and not self.cycle:  # equal rows with one id
                    split = None
            if split is None:
                cells.append((tree, at, len(own), lo.tolist(), hi.tolist()))
                continue
            splits.append(split)
            todo += [(2 * at + side, own_x[:, some], own[some]) for side, some in ((0, np.flatnonzero(~right)), (1, np.flatnonzero(right))) if len(some)]
        return splits, cells


def middles(rows: DataFrame, splits: list[Split], big: list[dict], dims: list[int], d: int, ties: bool, some: tuple[np.ndarray, np.ndarray] | None) -> dict[int, tuple[float, int]]:
    """(value, id) of the row at rank n // 2 of each node in ``big`` by its position there, exactly; without ``ties`` values alone count.

    A sample ``some`` (keys and coordinates) gives a range that the row is likely in; rows below it are counted, the values in it are
    ranked over all tasks. A node whose row is elsewhere is ranked as a whole.
    """
    keys = np.array([(c["tree"] + 1 << 48) + c["node"] for c in big], dtype=np.int64)
    by = np.argsort(keys)
    lo, hi = np.full(len(big), -np.inf), np.full(len(big), np.inf)
    for i, c in enumerate(big if some is not None else []):
        value = np.sort(some[1][some[0] == keys[i], dims[i]])
        at, off = len(value) * (c["n"] // 2) / c["n"], 3 * len(value) ** 0.5 + 3
        lo[i] = value[int(at - off)] if at >= off else -np.inf
        hi[i] = value[int(at + off)] if at + off < len(value) else np.inf
    router, names, which = Router(splits), [*coords(d), "point_id"], np.array(dims)

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            x = np.column_stack([b.column(c).to_numpy().astype(np.float64) for c in names])
            tree, ids = b.column("tree").to_numpy().astype(np.int64), b.column("point_id").to_numpy()
            _, node = router.down(tree, b.column("node").to_numpy(), x)
            key = ((tree + 1) << 48) + node
            at = by[np.minimum(np.searchsorted(keys, key, sorter=by), len(by) - 1)]
            mine = np.flatnonzero(keys[at] == key)
            at, value = at[mine], x[mine, which[at[mine]]]
            less = np.bincount(at[value < lo[at]], minlength=len(keys))
            fits = (value >= lo[at]) & (value <= hi[at])
            at, value, own = at[fits], value[fits], ids[mine][fits] if ties else np.zeros(int(fits.sum()), dtype=np.int64)
            order = np.lexsort((own, value, at))
            at, value, own = at[order], value[order], own[order]
            new = np.flatnonzero(np.concatenate([[True], (at[1:] != at[:-1]) | (value[1:] != value[:-1]) | (own[1:] != own[:-1])])) if len(at) else np.zeros(0, dtype=np.int64)
            under = np.flatnonzero(less)
            columns = [np.concatenate([under, at[new]]), np.concatenate([np.full(len(under), -np.inf), value[new]]), np.concatenate([np.zeros(len(under), dtype=np.int64), own[new]]), np.concatenate([less[under], np.diff(np.append(new, len(at)))])]
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(columns, (pa.int32(), pa.float64(), pa.int64(), pa.int64()), strict=True)], ["cell", "value", "own", "m"])

    seen = rows.select("tree", "node", *names).mapInArrow(work, "cell int, value double, own long, m long")
    so_far = Window.partitionBy("cell").orderBy("value", "own").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    ranked = seen.groupBy("cell", "value", "own").agg(F.sum("m").alias("m")).withColumn("upto", F.sum("m").over(so_far))
    wanted = local_table(rows.sparkSession, [(i, c["n"] // 2) for i, c in enumerate(big)], "cell int, target long")
    found = ranked.join(small(wanted, len(big)), "cell").where("upto > target").groupBy("cell").agg(F.min(F.struct("value", "own")).alias("r"))
    out = {r.cell: (r.r.value, r.r.own) for r in found.collect() if r.r.value != -np.inf}  # a row per node
    if len(out) < len(big) and some is not None:
        left = [i for i in range(len(big)) if i not in out]
        again = middles(rows, splits, [big[i] for i in left], [dims[i] for i in left], d, ties, None)
        out |= {left[i]: v for i, v in again.items()}
    return out


def _grown(rows: DataFrame, how: Halving, splits: list[Split]) -> tuple[list[Split], list[dict]]:
    """The splits of all nodes of ``rows`` and its cells, the same whatever the tasks: nodes too large for a task are split by aggregates, a level at a time."""
    d, fits, some = how.d, task_rows(how.d), None
    box = lambda c, a: [c[f"{a}{j}"] for j in range(d)]
    splits, cells, done = list(splits), _cell_stats(rows, d), []
    starts = [(c["tree"], c["node"]) for c in cells]
    more = lambda c: c["n"] > how.cap and c["node"].bit_length() <= how.levels
    while big := [c for c in cells if more(c) and c["n"] > fits]:
        dims = [how.dim(c["node"], box(c, "lo"), box(c, "hi")) for c in big]
        new: list[Split] = [(c["tree"], c["node"], d, (c["lo_id"] + c["hi_id"] + 1) / 2) for c, j in zip(big, dims, strict=True) if j is None and c["lo_id"] < c["hi_id"]]
        if how.rule == "object":
            if some is None:
                share = min(1.0, SAMPLE / sum(c["n"] for c in cells))
                few = rows.where(F.pmod(F.xxhash64("point_id", F.lit(7)), F.lit(1 << 30)) < int(share * (1 << 30))).select("tree", "node", *coords(d), "point_id").toArrow()
                some = [few.column(c).to_numpy().astype(np.int64) for c in ("tree", "node")] + [np.column_stack([few.column(c).to_numpy().astype(np.float64) for c in (*coords(d), "point_id")])]
                some[1] = Router(splits).down(*some)[1] if splits else some[1]
            asked = [i for i, j in enumerate(dims) if j is not None]
            key = (((some[0] + 1) << 48) + some[1], some[2])
            for i, (val, own) in middles(rows, splits, [big[i] for i in asked], [dims[i] for i in asked], d, how.ties, key).items():
                c, j = big[asked[i]], dims[asked[i]]
                if how.ties:
                    new.append((c["tree"], c["node"], j, val, own))
                elif how.cycle or val > c[f"lo{j}"]:
                    new.append((c["tree"], c["node"], j, val))
                else:  # over half of the rows have the smallest value: half way to the largest parts them
                    new.append((c["tree"], c["node"], j, how.middle(c[f"lo{j}"], c[f"hi{j}"])))
            some[1] = Router(new).down(*some)[1] if new else some[1]
        else:
            new += [(c["tree"], c["node"], j, how.middle(c[f"lo{j}"], c[f"hi{j}"])) for c, j in zip(big, dims, strict=True) if j is not None]
        had = {(s[0], s[1]) for s in new}
        done += [c for c in cells if not (more(c) and c["n"] > fits) or (c["tree"], c["node"]) not in had]
        splits += new
        cells = _routed_stats(rows, splits, starts, [k for t, n in had for k in ((t, 2 * n), (t, 2 * n + 1))], d) if new else []
    cells += done
    over = [c for c in cells if more(c) and c["n"] <= fits]
    keep = ["tree", "node", "n", *coords(d, "lo"), *coords(d, "hi")]
    out = [{k: c[k] for k in keep} for c in cells if not (more(c) and c["n"] <= fits)]
    if over:

        nodes = [(c["tree"], c["node"]) for c in over]

        def work(part: pa.Table) -> pa.Table:
            x = np.column_stack([part.column(c).to_numpy() for c in coords(d)])
            got, cut = how.below(*nodes[part.column("slot")[0].as_py()], x, part.column("point_id").to_numpy())
            made = [(s[0], s[1], s[2], s[3], s[4] if len(s) > 4 else None, None, None) for s in got] + [(c[0], c[1], None, None, None, c[2], c[3] + c[4]) for c in cut]
            types = (pa.int32(), pa.int64(), pa.int32(), pa.float64(), pa.int64(), pa.int64(), pa.list_(pa.float64()))
            return pa.table([pa.array(c, t) for c, t in zip(zip(*made, strict=True), types, strict=True)], names=["tree", "node", "dim", "val", "tie", "n", "box"])

        part = placed(rows, splits, starts, nodes, d).where("slot >= 0").select("slot", "point_id", *coords(d))
        made = part.groupBy("slot").applyInArrow(work, "tree int, node long, dim int, val double, tie long, n long, box array<double>").toArrow()  # a row per split and cell
        for r in made.to_pylist():
            if r["n"] is None:
                splits.append((r["tree"], r["node"], r["dim"], r["val"], *([r["tie"]] if r["tie"] is not None else [])))
            else:
                out.append({"tree": r["tree"], "node": r["node"], "n": r["n"]} | dict(zip([*coords(d, "lo"), *coords(d, "hi")], r["box"], strict=True)))
    return splits, out


def placed(rows: DataFrame, splits: list[Split], starts: list[tuple[int, int]], nodes: list[tuple[int, int]], d: int) -> DataFrame:
    """``rows`` with ``slot``: the position in ``nodes`` of the node that ``splits`` lead to from the row's own, one of ``starts``; -1 if it is elsewhere.

    A step down is two looks into arrays that go along with the plan; with over STEPS splits rows are routed in Python and joined.
    """
    split_of = {(s[0], s[1]): s for s in splits}
    slot_of, leads = {k: i for i, k in enumerate(nodes)}, set()
    for t, n in nodes:
        while n and (t, n) not in leads:
            leads.add((t, n))
            n >>= 1
    if len(split_of) > STEPS:
        table = local_table(rows.sparkSession, [(*k, i) for k, i in slot_of.items()], "tree int, node long, slot int")
        found = route(rows.withColumn("tree", F.col("tree").cast("int")), splits, d).join(small(table, len(nodes)), ["tree", "node"], "left")
        return found.withColumn("slot", F.coalesce("slot", F.lit(-1)))
    # a place is that of a split among those of its level, or -2 - slot of a node that is asked for, or -1
    level: list[tuple[int, int]] = []

    def place(key: tuple[int, int], among: list) -> int:
        if key in slot_of:
            return -2 - slot_of[key]
        if key not in leads or key not in split_of:
            return -1
        among.append(key)
        return len(among) - 1

    array = lambda of, kind: F.expr(f"array({', '.join(of)})").cast(f"array<{kind}>")
    first = {k: place(k, level) for k in starts}
    if len(set(first.values())) == 1 and len(starts) == 1:
        out = rows.withColumn("slot", F.lit(first[starts[0]]))
    else:
        table = local_table(rows.sparkSession, [(*k, p) for k, p in first.items()], "tree int, node long, slot int")
        out = rows.join(small(table, len(first)), ["tree", "node"])
    x = [F.col(c) for c in coords(d)] + [F.col("point_id").cast("double")]
    while level:
        below: list[tuple[int, int]] = []
        own = [split_of[k] for k in level]
        to = [place((t, 2 * n + side), below) for t, n in level for side in (0, 1)]
        dims, at = sorted({s[2] for s in own}), F.col("slot")
        value = x[dims[0]]
        if len(dims) > 1:
            dim, value = F.get(array([str(s[2]) for s in own], "int"), at), x[dims[-1]]
            for j in dims[-2::-1]:
                value = F.when(dim == j, x[j]).otherwise(value)
        val = F.get(array([f"{s[3]!r}D" for s in own], "double"), at)
        right = value >= val
        if any(len(s) > 4 and s[4] is not None for s in own):
            tie = F.get(array([f"{s[4]}L" if len(s) > 4 and s[4] is not None else "NULL" for s in own], "double"), at)
            right = right & ((value > val) | tie.isNull() | (x[d] >= tie))
        out = out.withColumn("slot", F.when(at < 0, at).otherwise(F.get(array(map(str, to), "int"), at * 2 + right.cast("int"))))
        level = below
    # not deterministic, so that no filter on the slot is moved through the steps, which would write out each step for every use of the one before
    return out.withColumn("slot", F.when(F.col("slot") < -1, -2 - F.col("slot")).otherwise(-1) + (F.monotonically_increasing_id() * 0).cast("int"))


def _routed_stats(rows: DataFrame, splits: list[Split], starts: list[tuple[int, int]], nodes: list[tuple[int, int]], d: int) -> list[dict]:
    """As ``_cell_stats``, for some nodes that ``splits`` lead to."""
    found = _cell_stats(placed(rows, splits, starts, nodes, d), d, ["slot"])
    return [c | dict(zip(("tree", "node"), nodes[c["slot"]], strict=True)) for c in found if c["slot"] >= 0]


def build(points: DataFrame, d: int, rule: str = "object", cap: int = CELL_CAP, splits: list[Split] | None = None, serial: int = 0, exact: bool = False, levels: int = MOST_LEVELS, cycle: bool = False, ties: bool = False) -> Forest:
    """Trees over rows (tree, node or none, point_id, c0.., seq); nodes over ``cap`` are split.

    ``rule`` "object" halves nodes by the median of the cycling dimension: exact in tables of up to SAMPLE rows and, at
    any size, with ``exact``; else by that many sampled ones in larger tables, where only balance depends on it; all levels need one pass
    unless a cell comes out too large. "spatial" splits half way between smallest and largest. ``levels``, ``cycle`` and ``ties`` are those of
    ``Halving``, for exact and spatial trees. Equal points are parted by id. A table of up to ``serial`` rows is one cell. An empty table has no cells.
    """
    df = points if "node" in points.columns else points.withColumn("node", F.lit(1).cast("long"))
    base = df.select("tree", F.col("node").cast("long").alias("node"), "point_id", *coords(d), "seq")
    if exact or rule == "spatial":
        base = written(base, "rows")  # what makes the rows runs once
        splits, cells = _grown(base, Halving(d, rule, max(cap, serial), levels, cycle, ties), splits or [])
        return Forest(route(base, splits, d), d, splits, cells)
    splits, df = list(splits or []), base
    for level in range(2 * MOST_LEVELS):
        cells = _cell_stats(df, d)
        over = [c for c in cells if c["n"] > cap and c["n"] > serial]
        new = []
        if over:
            share = min(1.0, SAMPLE / sum(c["n"] for c in over))
            keys = local_table(base.sparkSession, [(c["tree"], c["node"]) for c in over], "tree int, node long")
            some = df.join(small(keys, len(over)), ["tree", "node"], "left_semi")
            if share < 1:
                some = some.where(F.pmod(F.xxhash64("point_id", F.lit(level)), F.lit(1 << 30)) < int(share * (1 << 30)))
            new = sampled_splits(over, some.select("tree", "node", *coords(d)).toArrow(), d, cap)
            had = {(s[0], s[1]) for s in new}
            over = [c for c in over if (c["tree"], c["node"]) not in had]
        new += choose_splits(over, d, rule, cap)
        if not new:
            break
        splits += new
        df = route(df, new, d)
        if level % 8 == 7:
            df = written(df, "levels")
    keep = ["tree", "node", "n", *coords(d, "lo"), *coords(d, "hi")]
    return Forest(df, d, splits, [{k: c[k] for k in keep} for c in cells])


def stored(forest: Forest, leaf: int = inside.LEAF, rule: str = "object") -> Forest:
    """The points written cell by cell, each with its leaf: the lower parts of all trees are built side by side."""
    d = forest.d
    plain = forest.points.select("tree", "node", F.lit(1).cast("long").alias("leaf"), "point_id", *coords(d), "seq")

    def work(rows: pa.Table) -> pa.Table:
        x = np.column_stack([rows.column(c).to_numpy() for c in coords(d)])
        number = inside.leaf_numbers(x, rows.column("point_id").to_numpy(), leaf, rule)
        depth = inside._depth(number)
        out = rows.set_column(2, "leaf", pa.array(number))
        return out.take(pa.array(np.argsort(number << (depth.max(initial=0) - depth), kind="stable")))

    made = plain.groupBy("tree", "node").applyInArrow(work, plain.schema)
    return Forest(written(made, "tree"), d, forest.splits, forest.cells)


def top_k(rows: DataFrame, k: int, by: list[str] | None = None) -> DataFrame:
    """The k best rows (d2, point_id) of each query, cut in each task before they are dealt."""
    best = Window.partitionBy(*(by or ["query_id"])).orderBy("d2", "point_id")
    return rows.withColumn("rank", F.row_number().over(best)).where(F.col("rank") <= k)


def candidate_cells(queries: DataFrame, forest: Forest, trees: list[int], metric: str) -> DataFrame:
    """(query_id, q.., r2, tree, node): the cells whose box is within the query's bound r2."""
    q, live = coords(forest.d, "q"), [t for t in trees if t in forest.trees]
    if not live:
        return queries.select("query_id", *q, "r2", F.lit(0).alias("tree"), F.lit(1).cast("long").alias("node")).where("false")
    if len(forest.cells) <= ALONG:
        top, schema = forest.top(live), queries.select("query_id", *q, "r2", F.lit(0).alias("tree"), F.lit(1).cast("long").alias("node")).schema

        def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for b in batches:
                at = np.column_stack([b.column(c).to_numpy() for c in q])
                row, cell = top.within(at, b.column("r2").to_numpy(), metric, live)
                out = b.take(pa.array(row))
                yield pa.RecordBatch.from_arrays([*out.columns, pa.array(top.tree[cell], pa.int32()), pa.array(top.node[cell], pa.int64())], [*b.schema.names, "tree", "node"])

        return queries.select("query_id", *q, "r2").mapInArrow(work, schema)
    nodes, n = forest.nodes(queries.sparkSession)
    front = queries.withColumn("tree", F.explode(F.array(*[F.lit(t) for t in live]))).withColumn("parent", F.lit(0).cast("long"))
    for _ in range(forest.depth() + 2):
        met = front.join(small(nodes, n), ["tree", "parent"]).where(mind2(forest.d, metric) <= F.col("r2"))
        front = met.select("query_id", *q, "r2", "tree", F.col("node").alias("parent"))
    return front.withColumnRenamed("parent", "node").distinct()


def _points_side(forest: Forest, trees: list[int], tombs: DataFrame | None) -> DataFrame:
    """(tree, node, leaf, point_id, gen, dead, c..) of the trees; tombstones are rows without coordinates."""
    d, p = forest.d, forest.points
    gen = F.col("gen") if "gen" in p.columns else F.lit(0)
    leaf = F.col("leaf") if "leaf" in p.columns else F.lit(0).cast("long")
    rows = p.where(F.col("tree").isin(trees)).select(F.col("tree").cast("int").alias("tree"), "node", leaf.alias("leaf"), "point_id", gen.cast("int").alias("gen"), F.lit(False).alias("dead"), *coords(d))
    if tombs is not None:
        gone = F.col("gen") if "gen" in tombs.columns else F.lit(0)
        rows = rows.unionByName(tombs.where(F.col("tree").isin(trees)).select(F.col("tree").cast("int").alias("tree"), "node", F.lit(0).cast("long").alias("leaf"), "point_id", gone.cast("int").alias("gen"), F.lit(True).alias("dead"), *[F.lit(None).cast("double").alias(c) for c in coords(d)]))
    return rows


def live_tree(rows: pa.Table, d: int, rule: str = "object", leaf: int = inside.LEAF) -> inside.CellTree:
    """The tree of a cell's rows (leaf, point_id, gen, dead, c..) without the dead ones; leaves are numbered anew if some row has none."""
    ids, gen, dead = rows.column("point_id").to_numpy(), rows.column("gen").to_numpy().astype(np.int64), rows.column("dead").to_numpy()
    keep = ~dead
    if dead.any():
        both = np.rec.fromarrays([ids, gen])
        keep &= ~np.isin(both, both[dead])
    x = np.column_stack([rows.column(c).to_numpy() for c in coords(d)])[keep]
    number = rows.column("leaf").to_numpy()[keep]
    if len(number) and number.min() < 1:
        number = inside.leaf_numbers(x, ids[keep], leaf, rule)
    heap = "tree" in rows.column_names and rows.num_rows and rows.column("tree")[0].as_py() < 0  # a buffer
    return inside.CellTree(x, ids[keep], number, "heap" if heap else "veb")


def _met(asked: DataFrame, points: DataFrame, cells: int) -> tuple[DataFrame, DataFrame]:
    """Queries and points dealt by cell, and only points of cells that are asked. Cells with many queries are searched in parts."""
    counts = asked.groupBy("tree", "node").agg(F.count("*").alias("n"))
    hot = counts.where(F.col("n") > QUERY_BLOCK).select("tree", "node", F.ceil(F.col("n") / QUERY_BLOCK).cast("int").alias("parts"))
    if not hot.isEmpty():
        hot = written(hot, "hot")
        part = F.pmod(F.xxhash64("query_id"), F.coalesce("parts", F.lit(1))).cast("int")
        asked = asked.join(F.broadcast(hot) if cells <= ALONG else hot, ["tree", "node"], "left").withColumn("part", part).drop("parts")
        each = F.explode(F.sequence(F.lit(0), F.coalesce("parts", F.lit(1)) - 1)).alias("part")
        points = points.join(F.broadcast(hot) if cells <= ALONG else hot, ["tree", "node"], "left").select(*points.columns, each)
    else:
        asked, points = asked.withColumn("part", F.lit(0)), points.withColumn("part", F.lit(0))
    touched = asked.select("tree", "node").distinct()
    return asked, points.join(F.broadcast(touched) if cells <= ALONG else touched, ["tree", "node"], "left_semi")


def search(queries: DataFrame, forest: Forest, k: int, metric: str = "euclid", trees: list[int] | None = None, exclude_self: bool = False, tombs: DataFrame | None = None, shared_bound: bool = True, homes: bool = True, fill: bool = True, meet: Callable[[DataFrame], DataFrame] | None = None) -> DataFrame:
    """(query_id, point_id, d2) of the k nearest live points in ``trees`` to each query (query_id, q0.., r2).

    Queries whose r2 is null get a bound from the boxes above the cells. With ``homes`` they first search the cell nearest to
    them, in the largest tree, whose k-th neighbour tightens it; then every other cell within the bound is searched.
    Ties are ordered by point_id. With ``shared_bound=False`` each tree has a bound of its own. ``fill=False``
    searches cells a query at a time, best node first. ``meet`` takes the queries (query_id, q0.., r2, tree, node) to the
    cells (tree, node) they search after their home, in place of the walk of each query. Queries that are null or
    repeated have no defined result; without live points there are no rows.
    """
    d, spark, q = forest.d, queries.sparkSession, coords(forest.d, "q")
    trees = [t for t in (forest.trees if trees is None else trees) if t in forest.trees]
    if not trees:
        return queries.select("query_id", F.lit(None).cast("long").alias("point_id"), F.lit(None).cast("double").alias("d2")).where("false")
    top, cells = forest.top(trees), len(forest.cells)
    points = _points_side(forest, trees, tombs)
    need = k + exclude_self
    along = cells <= ALONG
    roots = [top.largest()] if shared_bound else trees

    def started(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            at = np.column_stack([b.column(c).to_numpy() for c in q])
            given = b.column("r2").to_numpy(zero_copy_only=False).astype(np.float64)
            for t in roots:
                cell, bound = top.home(at, t, need, metric)
                r2 = np.where(np.isnan(given), bound, given)
                yield pa.RecordBatch.from_arrays([*b.columns[:-1], pa.array(r2), pa.array(top.tree[cell], pa.int32()), pa.array(top.node[cell], pa.int64())], ["query_id", *q, "r2", "tree", "node"])

    slim = queries.select("query_id", *q, "r2")
    home_schema = slim.select("*", F.lit(0).alias("tree"), F.lit(0).cast("long").alias("node")).schema
    asked = slim.mapInArrow(started, home_schema)

    def own_of(qs: pa.Table) -> np.ndarray | None:
        return qs.column("query_id").to_numpy() if exclude_self else None

    def answered(qs: pa.Table, ps: pa.Table):
        at = np.column_stack([qs.column(c).to_numpy() for c in q])
        return inside.nearest(live_tree(ps, d), at, qs.column("r2").to_numpy(), k, metric, own_of(qs), fill=fill)

    def first(qs: pa.Table, ps: pa.Table) -> pa.Table:
        n = qs.num_rows
        row, ids, d2 = answered(qs, ps) if n and ps.num_rows else (np.zeros(0, dtype=np.int64), np.zeros(0, dtype=np.int64), np.zeros(0))
        count = np.bincount(row, minlength=n)
        ends = np.cumsum(count)
        r2 = qs.column("r2").to_numpy().copy()
        full = count == k
        r2[full] = d2[ends[full] - 1]
        offsets = pa.array(np.concatenate([[0], ends]), pa.int32())
        lists = [pa.ListArray.from_arrays(offsets, pa.array(v)) for v in (ids, d2)]
        return pa.table([qs.column("query_id"), *(qs.column(c) for c in q), pa.array(r2), qs.column("tree"), qs.column("node"), *lists], names=["query_id", *q, "r2", "tree", "node", "ids", "d2s"])

    def later(qs: pa.Table, ps: pa.Table) -> pa.Table:
        row, ids, d2 = answered(qs, ps) if qs.num_rows and ps.num_rows else (np.zeros(0, dtype=np.int64), np.zeros(0, dtype=np.int64), np.zeros(0))
        return pa.table([qs.column("query_id").take(pa.array(row)), pa.array(ids, pa.int64()), pa.array(d2, pa.float64())], names=["query_id", "point_id", "d2"])

    key = ["tree", "node", "part"]
    found = None
    if homes:
        qs, ps = _met(asked, points, cells)
        schema = asked.select("*", F.lit(None).cast("array<long>").alias("ids"), F.lit(None).cast("array<double>").alias("d2s")).schema
        asked = written(qs.groupBy(*key).cogroup(ps.groupBy(*key)).applyInArrow(first, schema), "homes")
        pairs = F.explode(F.arrays_zip("ids", "d2s")).alias("p")
        found = asked.select("query_id", pairs).select("query_id", F.col("p.ids").alias("point_id"), F.col("p.d2s").alias("d2"))

    def others(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            at = np.column_stack([b.column(c).to_numpy() for c in q])
            tree, node, r2 = (b.column(c).to_numpy() for c in ("tree", "node", "r2"))
            for t in [None] if shared_bound else trees:
                mine = np.arange(len(r2)) if t is None else np.flatnonzero(tree == t)
                row, cell = top.within(at[mine], r2[mine], metric, trees if t is None else [t])
                row = mine[row]
                new = (not homes) | (top.tree[cell] != tree[row]) | (top.node[cell] != node[row])
                row, cell = row[new], cell[new]
                out = b.take(pa.array(row))
                yield pa.RecordBatch.from_arrays([*(out.column(c) for c in ("query_id", *q, "r2")), pa.array(top.tree[cell], pa.int32()), pa.array(top.node[cell], pa.int64())], ["query_id", *q, "r2", "tree", "node"])

    if meet is not None:
        rest = meet(asked.select("query_id", *q, "r2", "tree", "node"))
    elif along:
        rest = asked.select("query_id", *q, "r2", "tree", "node").mapInArrow(others, home_schema)
    else:
        was = asked.select("query_id", F.col("tree").alias("tree"), F.col("node").alias("node"))
        rest = candidate_cells(asked.select("query_id", *q, "r2"), forest, trees, metric)
        rest = rest.join(was, ["query_id", "tree", "node"], "left_anti").select("query_id", *q, "r2", "tree", "node") if homes else rest
    qs, ps = _met(written(rest, "asked"), points, cells)
    more = qs.groupBy(*key).cogroup(ps.groupBy(*key)).applyInArrow(later, "query_id long, point_id long, d2 double")
    out = more if found is None else found.unionByName(more)
    return top_k(out, k).select("query_id", "point_id", "d2")


def pruning(queries: DataFrame, forest: Forest, k: int, metric: str = "euclid") -> DataFrame:
    """A row per cell that queries (query_id, q0.., r2: their bounds) search: queries, nodes visited, dropped and taken whole, leaves opened, distances.

    Counts are summed from output rows, so tasks that run twice don't count twice.
    """
    d, q = forest.d, coords(forest.d, "q")
    asked, points = _met(candidate_cells(queries, forest, forest.trees, metric), _points_side(forest, forest.trees, None), len(forest.cells))

    def work(qs: pa.Table, ps: pa.Table) -> pa.Table:
        stats = inside.Stats()
        if qs.num_rows and ps.num_rows:
            inside.nearest(live_tree(ps, d), np.column_stack([qs.column(c).to_numpy() for c in q]), qs.column("r2").to_numpy(), k, metric, stats=stats)
        row = [ps.column("node")[0].as_py() if ps.num_rows else 0, qs.num_rows, *stats.values()]
        return pa.table([pa.array([v], pa.int64()) for v in row], names=["node", "queries", "visited", "dropped", "whole", "leaves", "distances"])

    key = ["tree", "node", "part"]
    return asked.groupBy(*key).cogroup(points.groupBy(*key)).applyInArrow(work, "node long, queries long, visited long, dropped long, whole long, leaves long, distances long")


def ranked(found: DataFrame, k: int) -> DataFrame:
    """(query_id, rank, point_id, d2), ranks from 1; fewer than k rows where there are fewer points."""
    return top_k(found.where("point_id IS NOT NULL"), k).select("query_id", "rank", "point_id", "d2")


def as_queries(points: DataFrame, d: int) -> DataFrame:
    """Points as queries without a bound."""
    return points.select(F.col("point_id").alias("query_id"), *[F.col(c).alias(f"q{j}") for j, c in enumerate(coords(d))], F.lit(None).cast("double").alias("r2"))


def matches(points: DataFrame, batch: DataFrame, d: int, key: str = "id") -> DataFrame:
    """Rows of ``points`` that a delete batch names: by "id", by "coords" (all equal points) or "id+coords"."""
    on = {"id": ["point_id"], "coords": coords(d), "id+coords": ["point_id", *coords(d)]}[key]
    return points.join(batch.select(*on).distinct(), on, "left_semi")


def erase(forest: Forest, named: DataFrame, n: int, key: str = "id", trees: list[int] | None = None) -> DataFrame:
    """(tree, node, point_id, gen): the points that a batch (tree or none, point_id, c0..) of ``n`` rows names.

    The batch is routed down each tree by its splits, and meets only the points of the cells it gets to. Ids
    without coordinates can't be routed and meet all points of the trees.
    """
    d = forest.d
    trees = forest.trees if trees is None else trees
    gen = F.col("gen") if "gen" in forest.points.columns else F.lit(0)
    points = forest.points.where(F.col("tree").isin(trees)).select("tree", "node", "point_id", gen.alias("gen"), *coords(d))
    if not set(coords(d)) <= set(named.columns):
        on = ["tree", "point_id"] if "tree" in named.columns else ["point_id"]
        keys = named.select(*on).distinct()
        return points.join(small(keys, n), on, "left_semi").select("tree", "node", "point_id", "gen")
    at = named if "tree" in named.columns else named.withColumn("tree", F.explode(F.array(*[F.lit(t) for t in trees])))
    if key == "coords":
        at = at.select("tree", *coords(d)).distinct()
    routed = route(at.withColumn("node", F.lit(1).cast("long")), [s for s in forest.splits if s[0] in set(trees)], d, both=key == "coords")
    on = {"id": ["point_id"], "coords": coords(d), "id+coords": ["point_id", *coords(d)]}[key]
    keys = routed.select("tree", "node", *on).distinct()
    if n * len(trees) <= BROADCAST_ROWS:
        return points.join(F.broadcast(keys), ["tree", "node", *on], "left_semi").select("tree", "node", "point_id", "gen")
    touched = routed.select("tree", "node").distinct()
    near = points.join(F.broadcast(touched) if len(forest.cells) <= ALONG else touched, ["tree", "node"], "left_semi")
    return near.join(keys.hint("merge"), ["tree", "node", *on], "left_semi").select("tree", "node", "point_id", "gen")


def erased(cells: list[dict], gone: dict[tuple[int, int], int]) -> list[dict]:
    """Cells with their counts less those ``gone`` by (tree, node), without empty ones; paths to these collapse in the ``TopTree``."""
    out = [c | {"n": c["n"] - gone.get((c["tree"], c["node"]), 0)} for c in cells]
    return [c for c in out if c["n"] > 0]


def collapse(live: dict[int, int], splits: set[int], node: int = 1) -> int | dict | None:
    """The tree left after deletions: None for an empty node, a cell's id, or {node: (left, right)}; a node with one nonempty child is that child."""
    if node not in splits:
        return node if live.get(node) else None
    left, right = collapse(live, splits, 2 * node), collapse(live, splits, 2 * node + 1)
    if left is None or right is None:
        return right if left is None else left
    return {node: (left, right)}
