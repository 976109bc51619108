"""The domain tree: heap-numbered nodes over ranks padded to a power of two.

The node of level j above rank k (from 1) is ``(1 << j) | ((k - 1) >> (height - j))``.  A key
interval's cover is the set of topmost nodes inside it; of an object's path at most one node is
in a cover, the topmost that lies inside the interval.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F


def height_of(size: int) -> int:
    """Levels below the root for a domain of ``size`` values."""
    return max(0, (max(1, size) - 1).bit_length())


def path_nodes(rank: Column, height: int) -> Column:
    """The height + 1 nodes above a rank, root first."""
    levels = F.array(*[F.lit(j) for j in range(height + 1)])
    zero = rank.cast("int") - 1
    shift = lambda j: F.call_function("shiftright", zero, F.lit(height) - j)
    return F.transform(levels, lambda j: F.call_function("shiftleft", F.lit(1), j).bitwiseOR(shift(j)))


def span(node: int, height: int) -> tuple[int, int]:
    """First and last rank under a node."""
    level = node.bit_length() - 1
    width = 1 << (height - level)
    first = (node - (1 << level)) * width + 1
    return first, first + width - 1


def cover(low: int, high: int, height: int) -> list[int]:
    """The least set of nodes whose ranks are exactly ``low..high`` (from 1, clipped to the tree)."""
    low, high = max(1, low), min(1 << height, high)
    if low > high:
        return []
    a, b = low - 1 + (1 << height), high - 1 + (1 << height)
    left, right = [], []
    while a <= b:
        if a & 1:
            left.append(a)
            a += 1
        if not b & 1:
            right.append(b)
            b -= 1
        a, b = a >> 1, b >> 1
    return left + right[::-1]


def cover_nodes(low: Column, high: Column, height: int) -> Column:
    """``cover`` as a column: at each level up to two nodes, those whose parent is not inside."""
    zero_low, zero_high = F.greatest(low.cast("int"), F.lit(1)) - 1, F.least(high.cast("int"), F.lit(1 << height)) - 1
    none = F.array().cast("array<int>")

    def whole(level: int) -> tuple[Column, Column]:
        """First and last node of a level that lie inside, by their place in the level."""
        width = 1 << (height - level)
        return F.floor((zero_low + (width - 1)) / width).cast("int"), F.floor((zero_high + 1) / width).cast("int") - 1

    def chosen(level: int) -> Column:
        first, last = whole(level)
        if not level:
            return F.when(first <= last, F.array(F.lit(1))).otherwise(none)
        up_first, up_last = whole(level - 1)
        ends = F.array_distinct(F.array(first, last))
        alone = F.filter(ends, lambda i: (up_first > up_last) | (F.floor(i / 2) < up_first) | (F.floor(i / 2) > up_last))
        return F.when(first <= last, F.transform(alone, lambda i: (i + F.lit(1 << level)).cast("int"))).otherwise(none)

    return F.when(zero_low <= zero_high, F.concat(*[chosen(j) for j in range(height + 1)])).otherwise(none)


def levels_of(keys: np.ndarray, nodes: list[int], height: int) -> np.ndarray:
    """For each rank the level of its node among ``nodes``, -1 where none holds it."""
    out = np.full(len(keys), -1)
    for n in nodes:
        a, b = span(n, height)
        out[(keys >= a) & (keys <= b)] = n.bit_length() - 1
    return out
