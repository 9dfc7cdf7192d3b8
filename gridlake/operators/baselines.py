"""What the engine is compared with."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from gridlake.model import ScanOptions
from gridlake.operators import boxes as bx
from gridlake.plans.scan import Grid


def full_scan(grid: Grid, columns: list[str] | None, predicate: str) -> DataFrame:
    """All optimisations off: every cell and variable is read before anything is dropped."""
    return grid.scan(columns, predicate, ScanOptions(prune_rows=False, prune_columns=False))


def hull_scan(grid: Grid, columns: list[str] | None, predicate: str) -> DataFrame:
    """One enclosing box, then a filter."""
    plan = grid.plan(predicate)
    around = bx.hull(list(plan.boxes))
    one = type(plan)(plan.spec, (around,) if around else (), plan.clauses, plan.stats, plan.residual)
    out = grid.emit(one, ScanOptions()).where(predicate)
    return out.select(*columns) if columns else out


def no_elimination(grid: Grid, columns: list[str] | None, predicate: str) -> DataFrame:
    """Every conjunction looked up by itself, so cells in several of them come back repeatedly."""
    return grid.scan(columns, predicate, ScanOptions(cover="none", residual=False))


def long_rows(grid: Grid, variables: list[str], predicate: str | None = None) -> DataFrame:
    """The indexed long-format pipeline: one row for each variable and cell of one box."""
    axes = [a.name for a in grid.spec.axes]
    cells = grid.scan([*axes, *variables], predicate)
    names = ", ".join(f"'{v}', CAST({v} AS DOUBLE)" for v in variables)
    return cells.select(*axes, F.expr(f"stack({len(variables)}, {names}) AS (variable, value)")).select("variable", *axes, "value")


def wide_by_selfjoin(rows: DataFrame, axes: list[str], variables: list[str]) -> DataFrame:
    """Variables side by side again, one self-join for each further one."""
    out = None
    for v in variables:
        own = rows.where(F.col("variable") == v).select(*axes, F.col("value").alias(v))
        out = own if out is None else out.join(own, axes)
    return out


def wide_by_pivot(rows: DataFrame, axes: list[str], variables: list[str]) -> DataFrame:
    return rows.groupBy(*axes).pivot("variable", variables).agg(F.first("value"))


class ChunkIndex:
    """A pre-built index: the bounds of every chunk's axes in a table that queries join with."""

    def __init__(self, grid: Grid):
        span = grid.spec.spanning
        self.grid = grid
        self.table = grid.headers().select("chunk", F.array_min(f"{span.name}_values").alias("lo"), F.array_max(f"{span.name}_values").alias("hi"))

    def chunks(self, lo: str, hi: str) -> DataFrame:
        """Chunks whose spanning axis meets a closed range."""
        kind = self.grid.spec.spanning.dtype
        return self.table.where((F.col("hi") >= F.lit(lo).cast(kind)) & (F.col("lo") <= F.lit(hi).cast(kind))).select("chunk")

    def scan(self, columns: list[str], lo: str, hi: str) -> DataFrame:
        span = self.grid.spec.spanning.name
        rows = self.grid.scan(["chunk", span, *[c for c in columns if c not in ("chunk", span)]])
        return rows.join(F.broadcast(self.chunks(lo, hi)), "chunk", "left_semi").where(F.col(span).between(F.lit(lo).cast("timestamp_ntz"), F.lit(hi).cast("timestamp_ntz"))).select(*columns)
