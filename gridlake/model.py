"""Data model: axes, grids, cuts and boxes.

A *grid* is a set of *chunks*; each chunk holds the same variables over the same axes.
One axis may *span* chunks (every chunk holds its own piece of it), the others repeat in
full.  A chunk is stored as *tiles*: dense row-major arrays, one column for each variable.

A *cut* is a place between values: ``(0, value, 0)`` just before a value, ``(0, value, 1)``
just after it, BELOW and ABOVE beyond all.  Cuts are totally ordered, so ranges that are
open or closed on either side are half-open ranges of cuts.  A *box* is one half-open range
per axis: positions on axes that don't span, cuts on those that do.
"""

from __future__ import annotations

from bisect import bisect_left, bisect_right
from dataclasses import dataclass, field, replace
from typing import Any

BELOW, ABOVE = (-1, 0, 0), (1, 0, 0)
Cut = tuple[int, Any, int]
Range = tuple[Any, Any]
Box = tuple[Range, ...]


def before(value: Any) -> Cut:
    return (0, value, 0)


def after(value: Any) -> Cut:
    return (0, value, 1)


@dataclass(frozen=True)
class Axis:
    """``values`` are known for axes that don't span; a spanning axis has them per chunk."""

    name: str
    spans: bool = False
    dtype: str = "double"
    values: tuple = ()

    @property
    def ix(self) -> str:
        return f"{self.name}_ix"

    @property
    def descending(self) -> bool:
        return len(self.values) > 1 and self.values[0] > self.values[-1]


@dataclass(frozen=True)
class GridSpec:
    """What a reader must know of a grid; axes go from the slowest to the fastest."""

    name: str
    path: str
    axes: tuple[Axis, ...]
    variables: tuple[tuple[str, str], ...]
    #: SQL expression over a spanning value that gives its chunk key, for pruning.
    chunk_of: str = ""
    #: Whether a chunk's name is its key.
    keyed: bool = True

    def axis(self, name: str) -> Axis:
        return next(a for a in self.axes if a.name == name)

    @property
    def spanning(self) -> Axis | None:
        return next((a for a in self.axes if a.spans), None)

    @property
    def inner(self) -> tuple[Axis, ...]:
        return tuple(a for a in self.axes if not a.spans)

    @property
    def variable_names(self) -> list[str]:
        return [n for n, _ in self.variables]


@dataclass(frozen=True)
class ScanOptions:
    """Every optimisation can be switched off."""

    prune_rows: bool = True
    prune_columns: bool = True
    cover: str = "sweep"  # or "grid", or "none": overlapping boxes then give duplicates
    residual: bool = True
    include_fill: bool = False
    max_clauses: int = 4096
    #: Cells of one lookup at most (the fastest axis stays whole); 0 leaves lookups uncut, as
    #: tiles bound them already.
    lookup_cells: int = 0
    #: More boxes than this become a broadcast table instead of literals in the plan.
    inline_boxes: int = 64

    def but(self, **changes) -> ScanOptions:
        return replace(self, **changes)


@dataclass
class Clause:
    """One conjunction: a range of cuts for each axis it restricts."""

    ranges: dict[str, Range] = field(default_factory=dict)

    def cut(self, axis: str, lo: Cut, hi: Cut) -> Clause:
        a, b = self.ranges.get(axis, (BELOW, ABOVE))
        return Clause(self.ranges | {axis: (max(a, lo), min(b, hi))})

    @property
    def empty(self) -> bool:
        return any(lo >= hi for lo, hi in self.ranges.values())


def axis_span(values, lo: Cut = BELOW, hi: Cut = ABOVE) -> tuple[int, int]:
    """Positions ``[start, stop)`` of the values between two cuts on a monotone axis.

    A descending axis is searched through its mirror image.  No filter gives the whole
    axis; an empty answer is ``(0, 0)``.
    """
    n = len(values)
    if n > 1 and values[0] > values[-1]:
        start, stop = axis_span(values[::-1], lo, hi)
        return (n - stop, n - start) if start < stop else (0, 0)

    def place(cut: Cut) -> int:
        rank, value, side = cut
        if rank:
            return 0 if rank < 0 else n
        return (bisect_right if side else bisect_left)(values, value)

    start, stop = place(lo), place(hi)
    return (start, stop) if start < stop else (0, 0)


def axis_spans_in(values, items, negate: bool = False) -> list[tuple[int, int]]:
    """Runs of positions of an IN list, neighbours fused; with ``negate`` of the others."""
    hit = sorted({p for v in items for p in range(*axis_span(values, before(v), after(v)))})
    if negate:
        taken = set(hit)
        hit = [p for p in range(len(values)) if p not in taken]
    runs: list[list[int]] = []
    for p in hit:
        if runs and runs[-1][1] == p:
            runs[-1][1] = p + 1
        else:
            runs.append([p, p + 1])
    return [tuple(r) for r in runs]
