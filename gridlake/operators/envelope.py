"""Envelopes: per-chunk bounds of the selective side of a join, carried to the other side."""

from __future__ import annotations

from datetime import datetime

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from gridlake.model import ScanOptions, after, before
from gridlake.operators import boxes as bx
from gridlake.plans.scan import Grid

#: Bounds that are told to the plan as literals, at most.
MAX_BOXES = 256
#: Joins in which rows of S without a partner in R don't appear, so S may be pruned.
PRUNES_S = ("inner", "left", "left_outer", "leftouter", "left_semi", "semi", "left_anti", "anti")


def envelope_bounds(df: DataFrame, *dims: str, by: str = "chunk") -> DataFrame:
    """Tight lower and upper bounds of the dimensions, one row for each chunk."""
    return df.groupBy(by).agg(*[f(d).alias(f"{d}_{e}") for d in dims for f, e in ((F.min, "lo"), (F.max, "hi"))])


def collected(df: DataFrame, dims: tuple[str, ...], by: str, max_boxes: int) -> list[tuple]:
    """Closed bounds per chunk as tuples of (lo, hi), coarsened on the way.

    More chunks than ``max_boxes`` are merged by ranges of the first dimension (its least
    bounds' quantiles) before anything reaches the driver, so what is merged lies close.
    """
    bounds = envelope_bounds(df, *dims, by=by)
    n = bounds.count()
    if n > max_boxes:
        first = F.col(f"{dims[0]}_lo")
        place = F.unix_micros(first.cast("timestamp")) if bounds.schema[f"{dims[0]}_lo"].dataType.typeName().startswith(("timestamp", "date")) else first
        place = place.cast("double")
        cuts = bounds.agg(F.percentile_approx(place, [k / max_boxes for k in range(1, max_boxes)], 10_000).alias("q")).first().q
        bounds = bounds.withColumn("__g", F.size(F.filter(F.lit(sorted(set(cuts))), lambda q: q <= place)))
        bounds = bounds.groupBy("__g").agg(*[f(f"{d}_{e}").alias(f"{d}_{e}") for d in dims for f, e in ((F.min, "lo"), (F.max, "hi"))])
    return [tuple((r[f"{d}_lo"], r[f"{d}_hi"]) for d in dims) for r in bounds.collect() if all(r[f"{d}_lo"] is not None for d in dims)]


def coarsen(bounds: list[tuple], max_boxes: int = MAX_BOXES) -> list[tuple]:
    """Disjoint half-open boxes of cuts around the bounds; the hull where they stay too many."""
    half = [tuple((before(lo), after(hi)) for lo, hi in b) for b in bounds]
    if not half:
        return []
    cover = list(bx.cover_sweep(half).boxes)
    return cover if len(cover) <= max_boxes else [bx.hull(half)]


def _literal(value) -> Column:
    return F.lit(value).cast("timestamp_ntz") if isinstance(value, datetime) else F.lit(value)


def box_test(dims: tuple[str, ...], box: tuple) -> Column:
    """Whether a row lies in a box of cuts; only comparisons of a column with a literal."""
    test = F.lit(True)
    for d, (lo, hi) in zip(dims, box, strict=True):
        if not lo[0]:
            test &= F.col(d) > _literal(lo[1]) if lo[2] else F.col(d) >= _literal(lo[1])
        if not hi[0]:
            test &= F.col(d) <= _literal(hi[1]) if hi[2] else F.col(d) < _literal(hi[1])
    return test


def envelope(df: DataFrame, *dims: str, by: str = "chunk", max_boxes: int = MAX_BOXES) -> DataFrame:
    """``df`` under a filter that removes nothing: the hull of its chunks' bounds.

    The hull is a conjunction of single-column ranges, which the optimiser carries over an
    equi-join by itself.
    """
    return df.where(envelope_test(df, *dims, by=by, max_boxes=max_boxes))


def envelope_test(df: DataFrame, *dims: str, by: str = "chunk", max_boxes: int = MAX_BOXES) -> Column:
    """The hull of ``df``'s chunks' bounds as a test; always true where there are no rows."""
    bounds = collected(df, dims, by, max_boxes)
    if not bounds:
        return F.lit(True)
    return box_test(dims, bx.hull([tuple((before(lo), after(hi)) for lo, hi in b) for b in bounds]))


def predicate_sql(dims: tuple[str, ...], boxes: list[tuple]) -> str:
    """A grid predicate for boxes of cuts."""

    def text(value) -> str:
        return f"'{value}'" if isinstance(value, datetime | str) else repr(value)

    def one(box) -> str:
        tests = []
        for d, (lo, hi) in zip(dims, box, strict=True):
            if not lo[0]:
                tests.append(f"{d} {'>' if lo[2] else '>='} {text(lo[1])}")
            if not hi[0]:
                tests.append(f"{d} {'<=' if hi[2] else '<'} {text(hi[1])}")
        return "(" + " AND ".join(tests) + ")"

    return " OR ".join(map(one, boxes))


def pruned(s: Grid | DataFrame, dims: tuple[str, ...], boxes: list[tuple], columns: list[str] | None = None) -> DataFrame:
    """S cut to the boxes: through the box planner for a grid, else by a filter."""
    if isinstance(s, Grid):
        own = {a.name for a in s.spec.axes}
        keep = [k for k, d in enumerate(dims) if d in own]
        cut = [tuple(b[k] for k in keep) for b in boxes]
        return s.scan(columns, predicate_sql(tuple(dims[k] for k in keep), cut), ScanOptions(max_clauses=max(4096, len(cut))))
    test = F.lit(False)
    for b in boxes:
        test |= box_test(dims, b)
    return s.where(test)


def envelope_join(r: DataFrame, s: Grid | DataFrame, on: list[str], how: str = "inner", mode: str = "hull", columns: list[str] | None = None, by: str = "chunk", max_boxes: int = MAX_BOXES) -> DataFrame:
    """R joined with S, where R's envelope limits what is read of S.

    ``hull``: one box.  ``boxes``: the per-chunk bounds as disjoint boxes.  ``off``: nothing.
    Joins that keep rows of S without a partner are never pruned.
    """
    dims = tuple(on)
    left = r.drop(by) if by not in on else r
    if mode == "off" or how not in PRUNES_S:
        return left.join(s.scan(columns) if isinstance(s, Grid) else s, on, how)
    bounds = collected(r, dims, by, max_boxes)
    if not bounds:
        return left.join((s.scan(columns) if isinstance(s, Grid) else s).limit(0), on, how)
    half = [tuple((before(lo), after(hi)) for lo, hi in b) for b in bounds]
    boxes = [bx.hull(half)] if mode == "hull" else coarsen(bounds, max_boxes)
    return left.where(box_test(dims, bx.hull(half))).join(pruned(s, dims, boxes, columns), on, how)
