"""Axis search, parsing, normal forms."""

import random
from itertools import product

from gridlake.model import Axis, GridSpec, after, axis_span, axis_spans_in, before
from gridlake.plans import predicate as pr
from gridlake.plans.rewrite import rewrite_global

LAT = tuple(90 - i * 0.25 for i in range(721))
LON = tuple(i * 0.25 for i in range(1440))
SPEC = GridSpec("x", "", (Axis("t", True, "timestamp_ntz"), Axis("lat", values=LAT), Axis("lon", values=LON)), (("sp", "double"),))
SMALL = GridSpec("y", "", (Axis("a", values=(5.0, 4.0, 3.0, 2.0, 1.0)), Axis("b", values=(0.0, 0.1, 0.2, 0.3))), (("v", "double"),))


def test_axis_span():
    assert axis_span(LAT, after(20.2), before(60.5)) == (119, 280)
    assert axis_span(LON) == (0, 1440)
    assert axis_span(LON, before(90.0)) == (360, 1440)
    assert axis_span(LON, after(10.1), before(10.2)) == (0, 0)
    assert axis_span((), before(1)) == (0, 0)
    assert axis_spans_in(LAT, [90, 89.75, 0, 999]) == [(0, 2), (360, 361)]
    assert axis_spans_in((1.0, 2.0, 3.0), [2], negate=True) == [(0, 1), (2, 3)]


def test_span_matches_filter():
    rng = random.Random(2)
    for _ in range(500):
        values = tuple(sorted(rng.sample(range(20), rng.randint(1, 8)), reverse=rng.random() < 0.5))
        lo, hi = (rng.choice((before, after))(rng.randint(-1, 21)) for _ in range(2))
        start, stop = axis_span(values, lo, hi)
        inside = [i for i, v in enumerate(values) if lo <= (0, v, 0.5) < hi or lo < (0, v, 0.5) < hi]
        assert list(range(start, stop)) == inside


def test_example_has_four_clauses():
    tree = pr.parse_predicate("lon >= 90.0 AND NOT (lat == 0.0 AND lon >= 163.0 AND lon <= 163.75)", SPEC)
    assert len(pr.to_dnf(pr.split_equalities(tree))) == 4
    boxes = rewrite_global(SPEC, pr.clauses_of(tree))
    assert [b[1:] for b in boxes] == [((361, 721), (360, 1440)), ((0, 360), (360, 1440)), ((0, 721), (360, 652)), ((0, 721), (656, 1440))]


def test_tighten():
    clauses = pr.clauses_of(pr.parse_predicate("lon >= 90 AND lon > 163.75", SPEC))
    assert clauses[0].ranges["lon"][0] == after(163.75)
    assert pr.clauses_of(pr.parse_predicate("lon > 5 AND lon < 3", SPEC)) == []


def random_predicate(rng, depth=3):
    if depth == 0 or rng.random() < 0.3:
        axis, values = rng.choice((("a", (1.0, 2.0, 2.5, 5.0, 9.0)), ("b", (0.0, 0.1, 0.15, 0.3))))
        kind = rng.randrange(4)
        if kind == 0:
            return f"{axis} {rng.choice(('NOT ', ''))}IN ({', '.join(map(str, rng.sample(values, 2)))})"
        if kind == 1:
            return f"{axis} {rng.choice(('NOT ', ''))}BETWEEN {rng.choice(values)} AND {rng.choice(values)}"
        return f"{axis} {rng.choice(('<', '<=', '>', '>=', '=', '<>'))} {rng.choice(values)}"
    parts = [random_predicate(rng, depth - 1) for _ in range(rng.randint(1, 3))]
    return f"{rng.choice(('NOT ', ''))}({f' {rng.choice(('AND', 'OR'))} '.join(parts)})"


def as_python(text):
    import re

    text = re.sub(r"(\w) BETWEEN ([\d.]+) AND ([\d.]+)", r"(\2 <= \1 <= \3)", re.sub(r"(\w) NOT BETWEEN ([\d.]+) AND ([\d.]+)", r"(not \2 <= \1 <= \3)", text))
    return text.replace("NOT IN", "not in").replace("IN", "in").replace("AND", "and").replace("OR", "or").replace("NOT", "not").replace("<>", "!=").replace(" = ", " == ")


def test_boxes_equal_brute_force():
    rng = random.Random(3)
    for _ in range(300):
        text = random_predicate(rng)
        boxes = rewrite_global(SMALL, pr.clauses_of(pr.parse_predicate(text, SMALL)))
        got = {p for b in boxes for p in product(*[range(*s) for s in b])}
        want = {(i, j) for i, a in enumerate(SMALL.axes[0].values) for j, b in enumerate(SMALL.axes[1].values) if eval(as_python(text), {}, {"a": a, "b": b})}
        assert got == want, text


def test_guard_gives_the_hull():
    text = "(a = 1 OR b = 0.1) AND (a = 2 OR b = 0.2) AND a <= 2"
    tree = pr.parse_predicate(text, SMALL)
    assert len(pr.clauses_of(tree, max_clauses=2)) == 1
    assert pr.clauses_of(tree, max_clauses=2)[0].ranges["a"][1] == after(2.0)


def test_opaque_parts_widen_only():
    tree = pr.parse_predicate("v > 3 OR a = 1", SMALL)
    assert rewrite_global(SMALL, pr.clauses_of(tree))[0] == ((0, 5), (0, 4))
    assert pr.to_sql(tree) == "((v > 3) OR (a = CAST(1.0 AS DOUBLE)))"
