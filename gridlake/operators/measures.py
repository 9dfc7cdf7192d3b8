"""Cost and correctness measures."""

from __future__ import annotations

import time

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from gridlake.model import ScanOptions
from gridlake.operators import boxes as bx
from gridlake.plans.scan import Grid, ScanPlan


def cells_loaded(grid: Grid, plan: ScanPlan) -> DataFrame:
    """``cells, chunks, lookups``: the volume of all lookups."""
    at = grid.local_boxes(plan)
    volume = F.lit(1)
    for a in grid.spec.axes:
        volume = volume * (F.col(f"{a.name}_stop") - F.col(f"{a.name}_start"))
    return at.agg(F.coalesce(F.sum(volume), F.lit(0)).cast("long").alias("cells"), F.countDistinct("chunk").alias("chunks"), F.count("*").alias("lookups"))


def measure(grid: Grid, predicate: str, options: ScanOptions = ScanOptions()) -> DataFrame:
    """``metric, value`` of a query: cells and chunks loaded, lookups, cells that qualify and
    the read amplification."""
    plan = grid.plan(predicate, options)
    got = grid.scan(predicate=predicate, options=options).agg(F.count("*").alias("qualifying"))
    both = cells_loaded(grid, plan).crossJoin(got)
    pairs = [("cells_loaded", "cells"), ("chunks_touched", "chunks"), ("lookups", "lookups"), ("cells_qualifying", "qualifying")]
    values = [F.struct(F.lit(n).alias("metric"), F.col(c).cast("double").alias("value")) for n, c in pairs]
    values.append(F.struct(F.lit("read_amplification").alias("metric"), F.try_divide(F.col("cells").cast("double"), F.col("qualifying").cast("double")).alias("value")))
    return both.select(F.explode(F.array(*values)).alias("m")).select("m.metric", "m.value")


def diff(left: DataFrame, right: DataFrame) -> tuple[int, int]:
    """Rows of the left that are missing on the right, and the other way round."""
    return left.exceptAll(right).count(), right.exceptAll(left).count()


def multiplicity(spark, boxes) -> DataFrame:
    """``copies, pieces``: how many pieces of the full split come up how often."""
    rows = sorted(bx.multiplicity(boxes).items())
    return spark.createDataFrame(rows, "copies long, pieces long")


def scan_metrics(df: DataFrame) -> dict[str, int]:
    """Runs ``df`` and sums the metrics of its file scans: files, bytes of files and rows read."""
    out = {"numFiles": 0, "filesSize": 0, "numOutputRows": 0}
    df.agg(F.count(F.struct("*"))).collect() if False else df.toArrow()
    plan = df._jdf.queryExecution().executedPlan()

    def walk(node) -> None:
        kind = node.getClass().getSimpleName()
        if kind == "AdaptiveSparkPlanExec":
            walk(node.executedPlan())
            return
        if kind.endswith("QueryStageExec"):
            walk(node.plan())
            return
        if kind.endswith("ScanExec"):
            metrics = node.metrics()
            for name in out:
                if metrics.contains(name):
                    out[name] += metrics.apply(name).value()
        children = node.children()
        for k in range(children.size()):
            walk(children.apply(k))

    walk(plan)
    return out


def timed(fn, repeats: int = 1) -> float:
    """Mean wall seconds of ``fn``."""
    began = time.perf_counter()
    for _ in range(repeats):
        fn()
    return (time.perf_counter() - began) / repeats
