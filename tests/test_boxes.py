"""Covers: worked example, workloads, invariants."""

import math
import random
from itertools import product

import pytest

from gridlake.operators import boxes as bx
from gridlake.operators.cover_df import cover_df
from gridlake.queries.methods import cover_times

EXAMPLE = [((361, 721), (360, 1440)), ((0, 360), (360, 1440)), ((0, 721), (360, 652)), ((0, 721), (656, 1440))]
# Pieces, distinct pieces and cover of aligned, misaligned, diagonal, centred.
EXPECTED = {
    (4, 1): [(8, 6, 1), (8, 6, 1), (10, 7, 1), (16, 7, 1)], (4, 2): [(8, 6, 1), (16, 14, 6), (52, 49, 1), (44, 25, 7)],
    (4, 3): [(8, 6, 1), (32, 28, 6), (346, 343, 1), (176, 119, 7)], (8, 2): [(16, 12, 1), (32, 28, 12), (232, 225, 1), (344, 113, 15)],
    (16, 2): [(32, 24, 1), (64, 56, 24), (976, 961, 1), (2736, 481, 31)], (8, 3): [(16, 12, 1), (64, 56, 12), (3382, 3375, 1), (2752, 1135, 15)],
}


def random_boxes(rng, d, n, reach=6):
    def side():
        a, b = sorted((rng.randint(0, reach), rng.randint(0, reach)))
        return (a, b + 1)

    return [tuple(side() for _ in range(d)) for _ in range(n)]


def test_worked_example():
    got = bx.cover_grid(EXAMPLE)
    assert (got.stats.pieces, got.stats.removed, got.stats.distinct, len(got.boxes)) == (12, 4, 8, 4)
    assert got.boxes == (((0, 360), (360, 1440)), ((360, 361), (360, 652)), ((360, 361), (656, 1440)), ((361, 721), (360, 1440)))
    assert bx.cover_sweep(EXAMPLE).boxes == got.boxes


@pytest.mark.parametrize("size", EXPECTED)
def test_workloads(size):
    for make, want in zip(bx.WORKLOADS.values(), EXPECTED[size], strict=True):
        got = bx.cover_grid(make(*size))
        assert (got.stats.pieces, got.stats.distinct, len(got.boxes)) == want
        assert bx.cover_sweep(make(*size)).boxes == got.boxes
        assert bx.predicted_pieces(make(*size)) == got.stats.pieces


def test_invariants():
    rng = random.Random(1)
    for _ in range(400):
        d, n = rng.randint(1, 3), rng.randint(0, 6)
        boxes = random_boxes(rng, d, n)
        got = bx.cover_sweep(boxes).boxes
        assert got == bx.cover_grid(boxes).boxes
        lattice = {p for b in boxes for p in product(*[range(*s) for s in b])}
        cells = [p for b in got for p in product(*[range(*s) for s in b])]
        assert len(cells) == len(set(cells)) and set(cells) == lattice
        assert sum(map(bx.volume, got)) == len(lattice)
        assert bx.cover_sweep(got).boxes == got
        shuffled = boxes[:]
        rng.shuffle(shuffled)
        assert bx.cover_sweep(shuffled).boxes == got
        assert len(bx.fuse(got, d - 1)) == len(got) if got else True
        if n:
            assert bx.cover_grid(boxes).stats.pieces <= n * (2 * n - 1) ** d


@pytest.mark.parametrize("d", [1, 2, 3])
def test_cover_of_data(spark, d):
    """By group, with empty and turned boxes; the fastest of several axes is not cut."""
    rng, axes = random.Random(d), [f"a{k}" for k in range(d)]
    groups = {g: random_boxes(rng, d, 12) + [((0, 9),) * (d - 1) + (end,) for end in ((3, 3), (5, 2))] for g in range(6)}
    rows = [(g, *(x for side in b for x in side)) for g, boxes in groups.items() for b in boxes]
    got = cover_df(spark.createDataFrame(rows, "grp int, " + ", ".join(f"{a}_lo int, {a}_hi int" for a in axes)), axes, ["grp"])
    assert sorted(map(tuple, got.collect())) == sorted((g, *(x for side in b for x in side)) for g, boxes in groups.items() for b in bx.cover_sweep(boxes).boxes)
    assert (f"explode(array({axes[-1]}_lo" in got._jdf.queryExecution().optimizedPlan().toString()) == (d == 1)


def test_sweep_keeps_less():
    assert bx.cover_sweep(bx.diagonal(16, 2)).stats.peak_live < bx.cover_grid(bx.diagonal(16, 2)).stats.peak_live


def test_split_lookups():
    box = ((0, 1), (119, 280), (0, 1440))
    for budget in (8, 8 * 1440, 8 * 1440 * 50, 10**9):
        parts = bx.split_lookups(box, 8, budget)
        assert sum(map(bx.volume, parts)) == bx.volume(box)
        assert all(p[2] == (0, 1440) for p in parts)
    tight = bx.split_lookups(box, 8, 8 * 100, allow_fastest=True)
    assert max(map(bx.volume, tight)) <= 100 and sum(map(bx.volume, tight)) == bx.volume(box)
    assert math.prod(len(range(*s)) for s in box) == bx.volume(box)


def test_bench_keeps_the_sweep():
    """Too many pieces for the full split stop the full split only."""
    rows = {(n, way): pieces for _, _, n, way, _, pieces, _ in cover_times("diagonal", 3, (4, 64))}
    assert rows[64, "grid"] is None and rows[4, "grid"] and rows[4, "sweep"] and rows[64, "sweep"]
