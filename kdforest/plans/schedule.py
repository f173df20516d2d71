"""Which static trees vanish and appear in an update: arithmetic on the mask of nonempty trees."""

from __future__ import annotations

from dataclasses import dataclass


@dataclass(frozen=True)
class MergePlan:
    mask: int
    buffer: int
    vanish: tuple[int, ...]
    appear: tuple[int, ...]
    flushed: int
    from_batch: int


def bits(mask: int) -> tuple[int, ...]:
    return tuple(i for i in range(mask.bit_length()) if mask >> i & 1)


def plan_insert(mask: int, buffered: int, x: int, batch: int) -> MergePlan:
    """A batch adds its whole multiples of ``x`` to the mask; the rest goes to the buffer, which adds one when full."""
    whole, rest = divmod(batch, x)
    held, flushed = buffered + rest, 0
    if held >= x:
        held, whole, flushed = held - x, whole + 1, x
    after = mask + whole
    return MergePlan(after, held, bits(mask & ~after), bits(after & ~mask), flushed, batch - rest)


def shares(total: int, capacities: list[int]) -> list[int]:
    """Cut points of ``total`` ranked points over trees, in proportion to their capacities."""
    out, so_far = [0], 0
    for c in capacities:
        so_far += c
        out.append(total * so_far // sum(capacities))
    return out
