"""Disjoint covers of overlapping boxes, box arithmetic and the box workloads.

Axes of a box go from the slowest to the fastest.  Both covers give the same canonical
boxes: maximal runs along each axis of equal cross-sections in the faster axes.
"""

from __future__ import annotations

import math
import random
import time
from collections import Counter, defaultdict
from dataclasses import dataclass
from itertools import product

from gridlake.model import Box


@dataclass(frozen=True)
class CoverStats:
    pieces: int
    removed: int
    distinct: int
    merged: int
    peak_live: int
    seconds: float


@dataclass(frozen=True)
class CoverResult:
    boxes: tuple[Box, ...]
    stats: CoverStats


def union_1d(intervals) -> list[tuple]:
    """The union of half-open intervals as maximal ones; touching ones are joined."""
    out: list[list] = []
    for lo, hi in sorted(intervals):
        if lo >= hi:
            continue
        if out and lo <= out[-1][1]:
            out[-1][1] = max(out[-1][1], hi)
        else:
            out.append([lo, hi])
    return [tuple(x) for x in out]


def fuse(boxes, axis: int) -> list[Box]:
    """Joins boxes that touch along ``axis`` and agree on all others."""
    lines = defaultdict(list)
    for b in boxes:
        lines[b[:axis] + b[axis + 1 :]].append(b[axis])
    return [rest[:axis] + (run,) + rest[axis:] for rest, own in lines.items() for run in union_1d(own)]


def pieces_of(boxes) -> Counter:
    """Every box cut at every bound of any box, with how often each piece comes up."""
    if not boxes:
        return Counter()
    cuts = [sorted({x for b in boxes for x in b[k]}) for k in range(len(boxes[0]))]
    where = [{x: i for i, x in enumerate(c)} for c in cuts]
    found: Counter = Counter()
    for b in boxes:
        sides = []
        for k, (lo, hi) in enumerate(b):
            own = cuts[k][where[k][lo] : where[k][hi] + 1]
            sides.append(list(zip(own, own[1:], strict=False)))
        found.update(product(*sides))
    return found


def predicted_pieces(boxes) -> int:
    """How many pieces the full split would make, without making them."""
    if not boxes:
        return 0
    cuts = [sorted({x for b in boxes for x in b[k]}) for k in range(len(boxes[0]))]
    where = [{x: i for i, x in enumerate(c)} for c in cuts]
    return sum(math.prod(where[k][hi] - where[k][lo] for k, (lo, hi) in enumerate(b)) for b in boxes)


def cover_grid(boxes) -> CoverResult:
    """Full split: cut at all bounds, drop equal pieces, fuse the fastest axis first."""
    began = time.perf_counter()
    boxes = [b for b in boxes if all(lo < hi for lo, hi in b)]
    found = pieces_of(boxes)
    live = list(found)
    for axis in reversed(range(len(boxes[0]) if boxes else 0)):
        live = fuse(live, axis)
    total = sum(found.values())
    return CoverResult(tuple(sorted(live)), CoverStats(total, total - len(found), len(found), len(live), len(found), time.perf_counter() - began))


class _Sweep:
    """Goes along the slowest axis from bound to bound.

    Cross-sections of the boxes that are active form a smaller cover; each of its boxes
    stays open as long as the next cross-section holds it too, and is closed when not.
    """

    def __init__(self):
        self.pieces = self.live = self.peak = 0

    def cover(self, boxes: list[Box]) -> list[Box]:
        if len(boxes[0]) == 1:
            self.pieces += len(boxes)
            return [(run,) for run in union_1d(b[0] for b in boxes)]
        opening, closing = defaultdict(list), defaultdict(list)
        for (lo, hi), *rest in boxes:
            opening[lo].append(tuple(rest))
            closing[hi].append(tuple(rest))
        active: Counter = Counter()
        running: dict[Box, object] = {}
        done: list[Box] = []
        for at in sorted(opening.keys() | closing.keys()):
            active.subtract(closing[at])
            active.update(opening[at])
            active = +active
            section = set(self.cover(list(active))) if active else set()
            for gone in [s for s in running if s not in section]:
                done.append(((running.pop(gone), at), *gone))
            for s in section:
                running.setdefault(s, at)
            self.live = len(done) + len(running)
            self.peak = max(self.peak, self.live)
        return done


def cover_sweep(boxes) -> CoverResult:
    """Sweep, the default: only the boxes active in a slab are ever looked at together."""
    began = time.perf_counter()
    boxes = [b for b in boxes if all(lo < hi for lo, hi in b)]
    sweep = _Sweep()
    done = sweep.cover(list(dict.fromkeys(boxes))) if boxes else []
    return CoverResult(tuple(sorted(done)), CoverStats(sweep.pieces, 0, sweep.pieces, len(done), max(sweep.peak, len(done)), time.perf_counter() - began))


COVERS = {"grid": cover_grid, "sweep": cover_sweep}


def multiplicity(boxes) -> dict[int, int]:
    """How many pieces come up how often."""
    return dict(Counter(pieces_of(boxes).values()))


def volume(box: Box) -> int:
    return math.prod(hi - lo for lo, hi in box)


def hull(boxes) -> Box | None:
    """The least box around all; None around nothing."""
    return tuple((min(b[k][0] for b in boxes), max(b[k][1] for b in boxes)) for k in range(len(boxes[0]))) if boxes else None


def split_lookups(box: Box, bytes_per_cell: int, budget: int, allow_fastest: bool = False) -> list[Box]:
    """Pieces of a lookup that fit into ``budget`` bytes each.

    Slow axes are cut first and the fastest one stays whole, so reads stay sequential; only
    with ``allow_fastest`` is it cut too, where a single run of it exceeds the budget.
    """
    lens = [hi - lo for lo, hi in box]
    room = max(1, budget // bytes_per_cell)
    steps = list(lens)
    for k in range(len(lens)):
        inner = math.prod(lens[k + 1 :])
        steps[k] = lens[k] if k == len(lens) - 1 and not allow_fastest else max(1, min(lens[k], room // max(1, inner)))
        if steps[k] > 1 or math.prod(steps[: k + 1]) * inner <= room:
            break
    parts = [[(s, min(s + step, hi)) for s in range(lo, hi, step)] for (lo, hi), step in zip(box, steps, strict=True)]
    return [tuple(p) for p in product(*parts)]


# --- workloads: closed form (for oracles) and seeded (for the bench) -----------------


def _aligned_start(i: int) -> int:
    return 18 * (i // 2) + 8 * (i % 2)


def aligned(n: int, d: int) -> list[Box]:
    """Boxes in a row on axis 0, equal on the others; every other pair overlaps."""
    return [((_aligned_start(i), _aligned_start(i) + 10), *(((0, 10),) * (d - 1))) for i in range(n)]


def misaligned(n: int, d: int) -> list[Box]:
    """As aligned, but shifted by half an extent on other axes, by the bits of the number."""
    return [((_aligned_start(i), _aligned_start(i) + 10), *((5 * (i >> (k - 1) & 1), 5 * (i >> (k - 1) & 1) + 10) for k in range(1, d))) for i in range(n)]


def diagonal(n: int, d: int) -> list[Box]:
    """Boxes on the diagonal inside one large box, with gaps, so all bounds differ."""
    return [((0, 4 * n),) * d] + [((4 * (j - 1) + 1, 4 * (j - 1) + 3),) * d for j in range(1, n)]


def centred(n: int, d: int) -> list[Box]:
    """Boxes around one centre, each longer on axis 0 and shorter on the others."""
    return [((-2 * (i + 1), 2 * (i + 1)), *(((-2 * (n - i), 2 * (n - i)),) * (d - 1))) for i in range(n)]


def random_rows(n: int, d: int, shifted: bool, seed: int = 7) -> list[Box]:
    """Boxes in a row whose overlaps, and shifts if asked for, are coin flips."""
    coin, at, out = random.Random(seed), 0, []
    for _ in range(n):
        out.append(((at, at + 10), *(((s, s + 10) for s in (5 * coin.randrange(2) if shifted else 0 for _ in range(d - 1))))))
        at += 8 if coin.random() < 0.5 else 10
    return out


WORKLOADS = {"aligned": aligned, "misaligned": misaligned, "diagonal": diagonal, "centred": centred}
