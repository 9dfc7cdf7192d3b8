"""Distributed cover of boxes that come from data.

``boxes`` has ``box_id`` and, per axis, ``<axis>_lo`` and ``<axis>_hi`` (half-open integers);
axes go from the slowest to the fastest.  Bounds on all but the fastest cut the boxes into
slabs, equal pieces fall together, and one islands pass per axis, the fastest first, fuses what
touches or overlaps.
Each axis costs one shuffle.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


#: Boxes beyond which the first axis is cut into bins, and the least width of one.
BIN_BOXES, BIN_WIDTH = 4096, 64


def elementary(boxes: DataFrame, axis: str, group: list[str]) -> DataFrame:
    """Boxes cut at every bound of the axis inside their group, which has the bounds as an array."""
    lo, hi = f"{axis}_lo", f"{axis}_hi"
    bounds = boxes.select(*group, F.explode(F.array(lo, hi)).alias("at")).groupBy(*group).agg(F.array_sort(F.collect_set("at")).alias("__bounds"))
    own = F.filter("__bounds", lambda x: (x >= F.col(lo)) & (x <= F.col(hi)))
    pairs = F.arrays_zip(F.slice(own, 1, F.size(own) - 1).alias("a"), F.slice(own, 2, F.size(own) - 1).alias("b"))
    return boxes.join(bounds, group).withColumn("__p", F.explode(pairs)).withColumn(lo, F.col("__p.a")).withColumn(hi, F.col("__p.b")).drop("__bounds", "__p")


def binned(boxes: DataFrame, axis: str, most: int = BIN_BOXES) -> DataFrame:
    """Boxes cut at the borders of equal bins of an axis, with their ``__bin``: a bin has no
    more bounds than it has positions, however many boxes there are.  Fusing joins the
    slabs of neighbouring bins again."""
    lo, hi = f"{axis}_lo", f"{axis}_hi"
    size = boxes.agg(F.count("*").alias("n"), F.min(lo).alias("lo"), F.max(hi).alias("hi")).first()
    width = max(BIN_WIDTH, -(-((size.hi or 0) - (size.lo or 0)) * most // max(1, size.n)), 1)
    at = F.sequence(F.floor(F.col(lo) / width), F.floor((F.col(hi) - 1) / width))
    cut = boxes.where(F.col(lo) < F.col(hi)).withColumn("__bin", F.explode(at))
    kind = boxes.schema[lo].dataType
    return cut.withColumn(lo, F.greatest(F.col(lo), F.col("__bin") * width).cast(kind)).withColumn(hi, F.least(F.col(hi), (F.col("__bin") + 1) * width).cast(kind))


def islands(rows: DataFrame, lo: str, hi: str, group: list[str]) -> DataFrame:
    """Maximal runs of touching or overlapping intervals within each group."""
    ordered = Window.partitionBy(*group).orderBy(lo)
    reach = F.max(hi).over(ordered.rowsBetween(Window.unboundedPreceding, -1))
    fresh = F.when(reach.isNull() | (F.col(lo) > reach), 1).otherwise(0)
    marked = rows.withColumn("__new", fresh).withColumn("__run", F.sum("__new").over(ordered.rowsBetween(Window.unboundedPreceding, 0)))
    return marked.groupBy(*group, "__run").agg(F.min(lo).alias(lo), F.max(hi).alias(hi)).drop("__run")


def cover_df(boxes: DataFrame, axes: list[str], by: list[str] | None = None) -> DataFrame:
    """Disjoint boxes with the same union, in the canonical form of the driver's covers; with
    ``by`` for each value of these columns, which are not null.  Empty boxes are left out.

    Slabs are cut on all axes but the fastest, whose intervals need no cuts to be united.
    Fusing goes through all axes, the fastest first; cells of different slabs that were cut
    at different places are first cut at all bounds that their group has in common.
    """
    by = by or []
    boxes = boxes.where(" AND ".join(f"{a}_lo < {a}_hi" for a in axes))
    sides = by + [f"{a}_{e}" for a in axes for e in ("lo", "hi")]
    cells = elementary(binned(boxes.select(*sides).distinct(), axes[0]), axes[0], [*by, "__bin"]).drop("__bin").distinct()
    for k, axis in enumerate(axes[1:-1], 1):
        group = by + [f"{a}_{e}" for a in axes[:k] for e in ("lo", "hi")]
        cells = elementary(cells, axis, group).distinct()
    for axis in reversed(axes):
        cells = islands(cells, f"{axis}_lo", f"{axis}_hi", [s for s in sides if s not in (f"{axis}_lo", f"{axis}_hi")])
    return cells.select(*sides)
