"""Positions of a complete binary tree's nodes in the recursive (van Emde Boas) order."""

from __future__ import annotations

from functools import cache

import numpy as np


def next_pow2(x: int) -> int:
    return 1 << max(0, (x - 1).bit_length())


def split_levels(levels: int) -> tuple[int, int]:
    """(top, bottom) levels; the bottom is the power of two at or above half, rounded down first."""
    bottom = next_pow2((levels + 1) // 2)
    return levels - bottom, bottom


@cache
def positions(levels: int) -> tuple[int, ...]:
    """Position of the heap nodes 1, 2, .. of a tree with ``levels`` levels: the top part, then the bottom ones side by side."""
    if levels == 1:
        return (0,)
    top, bottom = split_levels(levels)
    out = [0] * (1 << levels)
    head, below = positions(top), positions(bottom)
    size = (1 << bottom) - 1
    out[1 : 1 << top] = head
    for j in range(1 << top):
        root = (1 << top) + j
        for k, p in enumerate(below, start=1):
            depth = k.bit_length() - 1
            out[(root << depth) + (k - (1 << depth))] = (1 << top) - 1 + j * size + p
    return tuple(out[1:])


def places(nodes: np.ndarray, levels: int) -> np.ndarray:
    """Position of each heap node in ``nodes`` in a complete tree of ``levels`` levels: ``positions`` without the whole tree."""
    if levels <= 1 or not len(nodes):
        return np.zeros(len(nodes), dtype=np.int64)
    top, bottom = split_levels(levels)
    depth = np.frexp(nodes.astype(np.float64))[1].astype(np.int64) - 1
    above = depth < top
    out = np.empty(len(nodes), dtype=np.int64)
    out[above] = places(nodes[above], top)
    low, down = nodes[~above], depth[~above] - top
    own = (1 << down) | (low & ((1 << down) - 1))
    out[~above] = (1 << top) - 1 + ((low >> down) - (1 << top)) * ((1 << bottom) - 1) + places(own, bottom)
    return out


def levels_for(n: int, leaf_cap: int = 1) -> int:
    """Levels of a tree over ``n`` points with leaves of about ``leaf_cap``."""
    if n <= leaf_cap:
        return 1
    if leaf_cap == 1:
        return n.bit_length()
    leaves = -(-n // leaf_cap)
    levels = leaves.bit_length()
    return levels + (-(-n // (1 << (levels - 1))) > leaf_cap)
