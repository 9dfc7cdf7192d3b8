"""Range and as-of joins that equi-joins and windows carry."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def range_join(points: DataFrame, boxes: DataFrame, axes: list[str], width: int) -> DataFrame:
    """Points in half-open boxes ``<axis>_lo/_hi``: equi-join on bins of the last axis, then
    the exact test.  A box is sent to each bin it touches, a point to one."""
    fast = axes[-1]
    binned = boxes.withColumn("__bin", F.explode(F.sequence(F.floor(F.col(f"{fast}_lo") / width), F.floor((F.col(f"{fast}_hi") - 1) / width))))
    inside = F.lit(True)
    for a in axes:
        inside &= (F.col(a) >= F.col(f"{a}_lo")) & (F.col(a) < F.col(f"{a}_hi"))
    return points.withColumn("__bin", F.floor(F.col(fast) / width)).join(binned, "__bin").where(inside).drop("__bin")


def overlap_join(boxes: DataFrame, axes: list[str], width: int) -> DataFrame:
    """Pairs ``a < b`` of boxes that overlap.  Both go to the bins they touch; a pair counts in
    the first bin they share."""
    fast = axes[-1]
    low, high = F.floor(F.col(f"{fast}_lo") / width), F.floor((F.col(f"{fast}_hi") - 1) / width)
    binned = boxes.withColumn("__first", low).withColumn("__bin", F.explode(F.sequence(low, high)))
    x, y = binned.alias("x"), binned.alias("y")
    test = (F.col("x.__bin") == F.col("y.__bin")) & (F.col("x.box_id") < F.col("y.box_id")) & (F.col("x.__bin") == F.greatest("x.__first", "y.__first"))
    for a in axes:
        test &= (F.col(f"x.{a}_lo") < F.col(f"y.{a}_hi")) & (F.col(f"y.{a}_lo") < F.col(f"x.{a}_hi"))
    return x.join(y, test).select(F.col("x.box_id").alias("a"), F.col("y.box_id").alias("b"))


def asof_join(left: DataFrame, right: DataFrame, at: str, by: list[str], value: str) -> DataFrame:
    """``left`` with the latest ``value`` of ``right`` at or before each row's time."""
    both = left.select(*by, at, F.lit(None).cast(right.schema[value].dataType).alias(value), F.lit(1).alias("__side")).unionByName(right.select(*by, at, value, F.lit(0).alias("__side")))
    order = Window.partitionBy(*by).orderBy(at, "__side").rowsBetween(Window.unboundedPreceding, 0)
    return both.withColumn(value, F.last(value, True).over(order)).where("__side = 1").drop("__side")
