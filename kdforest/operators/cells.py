"""kd-trees inside a cell, as arrays: built level by level, searched for all queries of the cell at once.

A tree is a leaf number per point (1 is the root, children 2i and 2i + 1), which is stored with the points; boxes,
ranges and child positions follow from the sorted numbers in one pass. Nodes lie in recursive order (static trees) or
in heap order (buffers). A search first fills a bound from the smallest node around a query that holds enough
points, then goes down level by level and drops nodes beyond the bound, takes whole those inside it and opens the rest.
Where that opens a good part of the cell, as in many dimensions, rounded distances to all its points come from a product of matrices instead.
"""

from __future__ import annotations

from dataclasses import dataclass, fields

import numpy as np

from kdforest.plans.veb import places

#: Points of a leaf.
LEAF = 16
MOST_DEPTH = 48
#: Distances computed at a time.
BLOCK = 1 << 20
#: Queries of a cell that go down its tree first, and the share of the cell opened from which the others meet all its points.
TRIED, OPENED = 64, 0.05


def combined(parts: list[np.ndarray], metric: str) -> np.ndarray:
    """As ``geometry.combined``: left to right, so equal to the bit."""
    out = np.abs(parts[0]) if metric != "euclid" else parts[0] * parts[0]
    for p in parts[1:]:
        if metric == "euclid":
            out = out + p * p
        elif metric == "l1":
            out = out + np.abs(p)
        elif metric == "linf":
            out = np.maximum(out, np.abs(p))
        else:
            raise ValueError(f"no such metric: {metric}")
    return out


def distance(q: np.ndarray, x: np.ndarray, metric: str) -> np.ndarray:
    return combined([q[:, j] - x[:, j] for j in range(q.shape[1])], metric)


def box_least(q: np.ndarray, lo: np.ndarray, hi: np.ndarray, metric: str) -> np.ndarray:
    return combined([np.maximum(np.maximum(lo[:, j] - q[:, j], 0.0), q[:, j] - hi[:, j]) for j in range(q.shape[1])], metric)


def box_most(q: np.ndarray, lo: np.ndarray, hi: np.ndarray, metric: str) -> np.ndarray:
    return combined([np.maximum(np.abs(q[:, j] - lo[:, j]), np.abs(q[:, j] - hi[:, j])) for j in range(q.shape[1])], metric)


def leaf_numbers(x: np.ndarray, ids: np.ndarray, leaf: int = LEAF, rule: str = "object") -> np.ndarray:
    """The leaf of each point: nodes of over ``leaf`` points are split, all of a level at once; equal points stay together."""
    n, d = x.shape
    number = np.ones(n, dtype=np.int64)
    rows = np.arange(n) if n > leaf else np.zeros(0, dtype=np.int64)
    for depth in range(MOST_DEPTH):
        rows = rows[np.argsort(number[rows], kind="stable")]
        own = number[rows]
        start = np.flatnonzero(np.concatenate([[True], own[1:] != own[:-1]])) if len(rows) else np.zeros(0, dtype=np.int64)
        size = np.diff(np.append(start, len(rows)))
        if not (size > leaf).any():
            break
        lo, hi = np.minimum.reduceat(x[rows], start, axis=0), np.maximum.reduceat(x[rows], start, axis=0)
        turn = (depth + np.arange(d)) % d
        wide = (lo < hi)[:, turn]
        dim = turn[wide.argmax(axis=1)]
        split = np.repeat((size > leaf) & wide.any(axis=1), size)
        group = np.repeat(np.arange(len(start)), size)[split]
        rows = rows[split]
        if not len(rows):
            break
        value = x[rows, dim[group]]
        if rule == "object":
            order = np.lexsort((ids[rows], value, group))
            rows, group = rows[order], group[order]
            first = np.searchsorted(group, group)
            right = np.arange(len(rows)) - first >= size[group] // 2
        else:
            low, high = lo[group, dim[group]], hi[group, dim[group]]
            middle = (low + high) / 2
            right = value >= np.where(low < middle, middle, high)
        number[rows] = 2 * number[rows] + right
    return number


@dataclass
class Stats:
    """Nodes looked at, dropped, taken whole; leaves opened and distances computed."""

    visited: int = 0
    dropped: int = 0
    whole: int = 0
    leaves: int = 0
    distances: int = 0

    def values(self) -> list[int]:
        return [getattr(self, f.name) for f in fields(self)]


class CellTree:
    """Points of one cell in the order of their leaves, with the boxes and ranges of all nodes; a node with one child is that child."""

    def __init__(self, x: np.ndarray, ids: np.ndarray, leaf_no: np.ndarray, layout: str = "veb"):
        depth = _depth(leaf_no)
        most = int(depth.max(initial=0))
        key = leaf_no << (most - depth)
        order = np.lexsort((ids, key))
        self.x, self.ids, key = x[order], ids[order], key[order]
        level, numbers = np.unique(leaf_no), [np.unique(leaf_no)]
        while len(level := np.unique(level[level > 1] >> 1)):
            numbers.append(level)
        number = np.unique(np.concatenate(numbers))
        if layout == "veb":
            number = number[np.argsort(places(number, most + 1), kind="stable")]
        self.number = number
        up = most - _depth(number)
        self.begin, self.end = np.searchsorted(key, number << up), np.searchsorted(key, (number + 1) << up)
        by = np.argsort(number)
        found = lambda child: np.where(number[by[np.minimum(np.searchsorted(number, child, sorter=by), len(by) - 1)]] == child, by[np.minimum(np.searchsorted(number, child, sorter=by), len(by) - 1)], -1)
        self.left, self.right = found(2 * number), found(2 * number + 1)
        d = x.shape[1]
        self.lo, self.hi = np.empty((len(number), d)), np.empty((len(number), d))
        is_leaf = (self.left < 0) & (self.right < 0)
        at = np.flatnonzero(is_leaf)
        at = at[np.argsort(self.begin[at])]
        if len(at):
            self.lo[at] = np.minimum.reduceat(self.x, self.begin[at], axis=0)
            self.hi[at] = np.maximum.reduceat(self.x, self.begin[at], axis=0)
        real = np.arange(len(number))
        deep = _depth(number)
        for level_no in range(most - 1, -1, -1):
            at = np.flatnonzero((deep == level_no) & ~is_leaf)
            l, r = np.where(self.left[at] >= 0, self.left[at], self.right[at]), np.where(self.right[at] >= 0, self.right[at], self.left[at])
            self.lo[at], self.hi[at] = np.minimum(self.lo[l], self.lo[r]), np.maximum(self.hi[l], self.hi[r])
            real[at] = np.where(l == r, real[l], at)
            self.left[at], self.right[at] = real[l], real[r]
        self.root = int(real[np.flatnonzero(number == 1)[0]]) if len(number) else -1
        self.flat = (self.lo == self.hi).all(axis=1)

    def leaf(self, at: np.ndarray) -> np.ndarray:
        return self.left[at] < 0


def _depth(number: np.ndarray) -> np.ndarray:
    """Levels above each node; exact for numbers below 2**53."""
    return np.frexp(number.astype(np.float64))[1].astype(np.int64) - 1


def _opened(t: CellTree, row: np.ndarray, node: np.ndarray, q: np.ndarray, own: np.ndarray | None, r2: np.ndarray, k: int, metric: str, stats: Stats):
    """Blocks of (row, point, d2) of the nodes' points within the bound; of equal points the first k (and one's own)."""
    begin = t.begin[node]
    size = np.where(t.flat[node], np.minimum(t.end[node] - begin, k + 1), t.end[node] - begin)
    cut = np.searchsorted(np.cumsum(size), np.arange(0, int(size.sum()) + 1, BLOCK))
    edges = np.unique(np.append(cut, len(size)))
    for lo, hi in zip(np.concatenate([[0], edges]), edges, strict=False):
        if lo == hi:
            continue
        s, b = size[lo:hi], begin[lo:hi]
        rows = np.repeat(row[lo:hi], s)
        at = np.arange(int(s.sum())) - np.repeat(np.cumsum(s) - s, s) + np.repeat(b, s)
        d2 = distance(q[rows], t.x[at], metric)
        stats.distances += len(at)
        keep = d2 <= r2[rows]
        if own is not None:
            keep &= t.ids[at] != own[rows]
        yield rows[keep], t.ids[at[keep]], d2[keep]


def smallest(row: np.ndarray, ids: np.ndarray, d2: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """The k first (d2, id) of each row."""
    order = np.lexsort((ids, d2, row))
    row, ids, d2 = row[order], ids[order], d2[order]
    keep = np.arange(len(row)) - np.searchsorted(row, row) < k
    return row[keep], ids[keep], d2[keep]


def nearest(t: CellTree, q: np.ndarray, r2: np.ndarray, k: int, metric: str = "euclid", own: np.ndarray | None = None, stats: Stats | None = None, fill: bool = True):
    """(row, id, d2) of the k nearest points of the cell to each query within its bound ``r2``; exact, ties by id.

    ``own``: ids that a query must not find. With ``fill=False`` each query is searched by itself, best node first.
    """
    none = np.zeros(0, dtype=np.int64), np.zeros(0, dtype=np.int64), np.zeros(0)
    if not len(t.ids) or not len(q):
        return none
    if stats is None and fill and metric == "euclid" and len(q) > TRIED:
        tried = Stats()
        first = nearest(t, q[:TRIED], r2[:TRIED], k, metric, None if own is None else own[:TRIED], tried)
        rest = all_pairs(t, q[TRIED:], r2[TRIED:], k, None if own is None else own[TRIED:]) if tried.distances > OPENED * TRIED * len(t.ids) else None
        if rest is not None:
            return np.concatenate([first[0], rest[0] + TRIED]), np.concatenate([first[1], rest[1]]), np.concatenate([first[2], rest[2]])
    stats = stats or Stats()
    if not fill:
        got = [canonical(t, q[i], float(r2[i]), k, metric, None if own is None else int(own[i]), stats) for i in range(len(q))]
        row = np.repeat(np.arange(len(q)), [len(g) for g in got])
        flat = [p for g in got for p in g]
        return row, np.array([p[1] for p in flat], dtype=np.int64), np.array([p[0] for p in flat], dtype=np.float64)
    need = k + (own is not None)
    r2 = np.array(r2, dtype=np.float64)
    at = np.full(len(q), t.root)
    count = t.end - t.begin
    enough = np.where(count[at] >= need, at, -1)
    down = np.arange(len(q))
    while len(down := down[~t.leaf(at[down])]):  # to a leaf, then up to the smallest node with enough points
        l, r = t.left[at[down]], t.right[at[down]]
        nearer = box_least(q[down], t.lo[l], t.hi[l], metric) <= box_least(q[down], t.lo[r], t.hi[r], metric)
        at[down] = np.where(nearer, l, r)
        enough[down] = np.where(count[at[down]] >= need, at[down], enough[down])
    some = np.flatnonzero(enough >= 0)
    if len(some):
        held = [smallest(*b, k) for b in _opened(t, some, enough[some], q, own, r2, k, metric, stats)]
        row, ids, d2 = smallest(*(np.concatenate(c) for c in zip(*held, strict=True)), k) if held else none
        full = np.flatnonzero(np.bincount(row, minlength=len(q)) == k)
        last = np.searchsorted(row, full, side="right") - 1
        r2[full] = d2[last]
    found = []
    for lo in range(0, len(q), 4096):
        row = np.arange(lo, min(lo + 4096, len(q)))
        node = np.full(len(row), t.root)
        opened_row, opened_node = [], []
        while len(row):
            stats.visited += len(row)
            near = box_least(q[row], t.lo[node], t.hi[node], metric) <= r2[row]
            stats.dropped += int((~near).sum())
            row, node = row[near], node[near]
            leaf = t.leaf(node)
            whole = ~leaf & (box_most(q[row], t.lo[node], t.hi[node], metric) <= r2[row])
            stats.whole += int(whole.sum())
            stats.leaves += int(leaf.sum())
            done = leaf | whole
            opened_row.append(row[done])
            opened_node.append(node[done])
            row, node = np.repeat(row[~done], 2), np.column_stack([t.left[node[~done]], t.right[node[~done]]]).ravel()
        found += [smallest(*b, k) for b in _opened(t, np.concatenate(opened_row), np.concatenate(opened_node), q, own, r2, k, metric, stats)]
    return smallest(*(np.concatenate(c) for c in zip(*found, strict=True)), k) if found else none


def all_pairs(t: CellTree, q: np.ndarray, r2: np.ndarray, k: int, own: np.ndarray | None = None):
    """As ``nearest`` (euclid): distances to all points, rounded to 32 bits, tell which may be within the bound, and these are computed in full. None if coordinates are too far apart to round.

    The margin is twice the largest error of the rounded sums, so no point within the bound is left out.
    """
    n, d = t.x.shape
    with np.errstate(over="ignore", invalid="ignore"):
        middle = t.x.mean(axis=0)
        x, at = t.x - middle, q - middle
        scale = max(np.abs(x).max(initial=0.0), np.abs(at).max(initial=0.0))
    if not 1e-140 < scale < 1e140:
        return None
    scale = 2.0 ** np.ceil(np.log2(scale))
    x, at = x / scale, at / scale
    xx, qq = (x * x).sum(axis=1), (at * at).sum(axis=1)
    right = np.vstack([-2 * x.T, xx, np.ones(n)]).astype(np.float32)
    margin = 4 * (d + 6) * 2.0**-24 * (qq + xx.max()) + 1e-30
    need, few = k + (own is not None), slice(None, None, 8 if n >= 64 * (k + 1) else 1)
    up = lambda v: np.nextafter(v.astype(np.float32), np.float32(np.inf))
    found, step = [], max(1, BLOCK // n)
    for lo in range(0, len(q), step):
        part = slice(lo, lo + step)
        d2 = np.column_stack([at[part], np.ones(len(at[part])), qq[part]]).astype(np.float32) @ right
        near = d2 <= up(np.minimum(r2[part] / scale / scale + margin[part], 3e38))[:, None]
        if n >= need and np.count_nonzero(near) > near.size >> 6:
            most = np.partition(d2[:, few], need - 1, axis=1)[:, need - 1] + 2 * margin[part]
            near &= d2 <= up(most)[:, None]
        row, col = np.divmod(np.flatnonzero(near), n)
        row += lo
        exact = distance(q[row], t.x[col], "euclid")
        keep = exact <= r2[row]
        if own is not None:
            keep &= t.ids[col] != own[row]
        found.append(smallest(row[keep], t.ids[col[keep]], exact[keep], k))
    return tuple(np.concatenate(c) for c in zip(*found, strict=True))


class KnnBuffer:
    """Up to 2k candidates; at 2k the k smallest stay, which costs a constant per candidate on average."""

    def __init__(self, k: int, bound: float = np.inf):
        self.k, self.bound, self.held = k, bound, []

    def add(self, d2: np.ndarray, ids: np.ndarray) -> None:
        for pair in zip(d2.tolist(), ids.tolist(), strict=True):
            if pair[0] <= self.bound:
                self.held.append(pair)
                if len(self.held) >= 2 * self.k:
                    self.cut()

    def cut(self) -> None:
        self.held = sorted(self.held)[: self.k]
        if len(self.held) == self.k:
            self.bound = min(self.bound, self.held[-1][0])

    def result(self) -> list[tuple[float, int]]:
        self.cut()
        return self.held


def canonical(t: CellTree, q: np.ndarray, r2: float, k: int, metric: str, own: int | None, stats: Stats) -> list[tuple[float, int]]:
    """One query, nearer child first, each node tested against the bound when it is reached."""
    buffer, todo, one = KnnBuffer(k, r2), [t.root], q[None, :]
    while todo:
        node = np.array([todo.pop()])
        stats.visited += 1
        if box_least(one, t.lo[node], t.hi[node], metric)[0] > buffer.bound:
            stats.dropped += 1
            continue
        if t.leaf(node)[0]:
            lo, hi = int(t.begin[node[0]]), int(t.end[node[0]])
            hi = min(hi, lo + k + 1) if t.flat[node[0]] else hi
            ids = t.ids[lo:hi]
            d2 = distance(np.broadcast_to(q, (hi - lo, len(q))), t.x[lo:hi], metric)
            stats.leaves += 1
            stats.distances += hi - lo
            keep = ids != own if own is not None else slice(None)
            buffer.add(d2[keep], ids[keep])
            if len(buffer.held) >= k:
                buffer.cut()
            continue
        pair = np.array([t.left[node[0]], t.right[node[0]]])
        gap = box_least(np.repeat(one, 2, axis=0), t.lo[pair], t.hi[pair], metric)
        todo += [int(pair[1]), int(pair[0])] if gap[0] <= gap[1] else [int(pair[0]), int(pair[1])]
    return buffer.result()
