"""Interval predicates: the four atoms, their masks, Allen's relations, and their plans as boxes.

Atoms, with inclusive bounds (object interval ``[l, r]``, query interval ``[lq, rq]``)::

    1  l <= lq <= r <= rq      2  l <= lq and rq <= r
    3  lq <= l <= rq <= r      4  lq <= l and r <= rq

A mask is a set of atoms as bits 1, 2, 4, 8.  A box is a version bound and a key interval in one
orientation; every mask is the union of at most two boxes.
"""

from __future__ import annotations

from dataclasses import dataclass
from functools import reduce

from pyspark.sql import Column
from pyspark.sql import functions as F

ATOMS = (1, 2, 3, 4)
ALL_MASKS = tuple(range(1, 16))
#: Orientation: version attribute and its order, key attribute.
#: LU: versions by rising l; RD: versions by falling r; LD: versions by falling l.
ORIENTATIONS = {"LU": ("l", 1, "r"), "RD": ("r", -1, "l"), "LD": ("l", -1, "r")}


@dataclass(frozen=True)
class Box:
    """One search: ``version`` bounds the version attribute, ``low``/``high`` the key; each is "lq", "rq" or None (open).

    The strict flags are for Allen's relations; ``residual`` is an equality left to check.
    """

    orient: str
    version: str | None
    low: str | None
    high: str | None
    version_strict: bool = False
    low_strict: bool = False
    high_strict: bool = False
    residual: str | None = None


#: Fixed table: masks as sets of atoms, and their boxes.
_PLANS = {
    (1,): [Box("LU", "lq", "lq", "rq")],
    (2,): [Box("LU", "lq", "rq", None)],
    (3,): [Box("RD", "rq", "lq", "rq")],
    (4,): [Box("LD", "lq", None, "rq")],
    (1, 2): [Box("LU", "lq", "lq", None)],
    (1, 3): [Box("LU", "lq", "lq", "rq"), Box("RD", "rq", "lq", "rq")],
    (1, 4): [Box("LU", None, "lq", "rq")],
    (2, 3): [Box("RD", "rq", None, "rq")],
    (2, 4): [Box("LU", "lq", "rq", None), Box("LD", "lq", None, "rq")],
    (3, 4): [Box("RD", None, "lq", "rq")],
    (1, 2, 3): [Box("LU", "lq", "lq", None), Box("RD", "rq", "lq", "rq")],
    (1, 2, 4): [Box("LU", None, "lq", "rq"), Box("LU", "lq", "rq", None)],
    (1, 3, 4): [Box("LU", "lq", "lq", "rq"), Box("RD", None, "lq", "rq")],
    (2, 3, 4): [Box("RD", None, "lq", "rq"), Box("RD", "rq", None, "lq")],
    (1, 2, 3, 4): [Box("LU", "rq", "lq", None)],
}

#: Fixed table: Allen's relation of the object to the query, as one box.
_ALLEN = {
    "before": Box("LU", None, None, "lq", high_strict=True),
    "meets": Box("LU", "lq", "lq", "lq", version_strict=True),
    "overlaps": Box("LU", "lq", "lq", "rq", version_strict=True, low_strict=True, high_strict=True),
    "finished_by": Box("LU", "lq", "rq", "rq", version_strict=True),
    "contains": Box("LU", "lq", "rq", None, version_strict=True, low_strict=True),
    "after": Box("RD", None, "rq", None, low_strict=True),
    "met_by": Box("RD", "rq", "rq", "rq", version_strict=True),
    "overlapped_by": Box("RD", "rq", "lq", "rq", version_strict=True, low_strict=True, high_strict=True),
    "started_by": Box("RD", "rq", "lq", "lq", version_strict=True),
    "during": Box("LD", "lq", None, "rq", version_strict=True, high_strict=True),
    "finishes": Box("LD", "lq", "rq", "rq", version_strict=True),
    "starts": Box("LD", "lq", None, "rq", high_strict=True, residual="l = lq"),
    "equals": Box("LU", "lq", "rq", "rq", residual="l = lq"),
}
ALLEN = tuple(_ALLEN)


def atoms_of(mask: int) -> tuple[int, ...]:
    if not isinstance(mask, int) or not 1 <= mask <= 15:
        raise ValueError(f"a mask has 1 to 4 of four bits, not {mask!r}")
    return tuple(a for a in ATOMS if mask >> (a - 1) & 1)


def plan(mask: int) -> list[Box]:
    """At most two boxes whose union is the mask."""
    return _PLANS[atoms_of(mask)]


def atomic_plan(mask: int) -> list[Box]:
    """A box an atom: the plan without rewriting."""
    return [_PLANS[(a,)][0] for a in atoms_of(mask)]


def allen_plan(name: str) -> Box:
    return _ALLEN[name]


def atom_expr(atom: int, left: Column, right: Column, lq: Column, rq: Column) -> Column:
    return {
        1: (left <= lq) & (lq <= right) & (right <= rq),
        2: (left <= lq) & (rq <= right),
        3: (lq <= left) & (left <= rq) & (rq <= right),
        4: (lq <= left) & (right <= rq),
    }[atom]


def mask_expr(mask: int, left: Column, right: Column, lq: Column, rq: Column) -> Column:
    """The mask as a disjunction of atoms: the definition that all plans are tested against."""
    return reduce(lambda a, b: a | b, [atom_expr(i, left, right, lq, rq) for i in atoms_of(mask)])


def box_expr(box: Box, left: Column, right: Column, lq: Column, rq: Column) -> Column:
    """A box as a conjunction of comparisons, fit for pushing to a scan."""
    ends = {"lq": lq, "rq": rq}
    attribute, order, key = ORIENTATIONS[box.orient]
    of = {"l": left, "r": right}
    terms = []
    if box.version:
        v, e = of[attribute], ends[box.version]
        terms.append((v < e if box.version_strict else v <= e) if order > 0 else (v > e if box.version_strict else v >= e))
    if box.low:
        terms.append(of[key] > ends[box.low] if box.low_strict else of[key] >= ends[box.low])
    if box.high:
        terms.append(of[key] < ends[box.high] if box.high_strict else of[key] <= ends[box.high])
    if box.residual:
        terms.append(left == lq)
    return reduce(lambda a, b: a & b, terms, F.lit(True))


def boxes_expr(boxes: list[Box], left: Column, right: Column, lq: Column, rq: Column) -> Column:
    return reduce(lambda a, b: a | b, [box_expr(b, left, right, lq, rq) for b in boxes])


def allen_expr(name: str, left: Column, right: Column, lq: Column, rq: Column) -> Column:
    """Allen's relation by its definition on end points."""
    return {
        "before": right < lq,
        "meets": (right == lq) & (left < lq),
        "overlaps": (left < lq) & (lq < right) & (right < rq),
        "finished_by": (left < lq) & (right == rq),
        "contains": (left < lq) & (rq < right),
        "starts": (left == lq) & (right < rq),
        "equals": (left == lq) & (right == rq),
        "started_by": (left == lq) & (rq < right),
        "during": (lq < left) & (right < rq),
        "finishes": (lq < left) & (right == rq),
        "overlapped_by": (lq < left) & (left < rq) & (rq < right),
        "met_by": (left == rq) & (rq < right),
        "after": left > rq,
    }[name]
