"""Value-to-position rewriting in two phases.

The global phase runs once: axes that don't span are searched in the first chunk's axis
arrays, and a predicate becomes half-boxes (positions, and cuts on the spanning axis).
The local phase runs for each chunk where the data is: the cuts of the spanning axis become
positions in that chunk's own array, and boxes without any are dropped.
"""

from __future__ import annotations

from collections.abc import Iterable

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from gridlake.model import ABOVE, BELOW, Box, Clause, Cut, GridSpec, axis_span


def rewrite_global(spec: GridSpec, clauses: Iterable[Clause]) -> list[Box]:
    """Half-boxes of the clauses, empty ones left out; equal clauses give equal boxes."""
    out = []
    for clause in clauses:
        sides = []
        for a in spec.axes:
            lo, hi = clause.ranges.get(a.name, (BELOW, ABOVE))
            if a.spans:
                sides.append((lo, hi))
                continue
            start, stop = axis_span(a.values, lo, hi)
            first, last = axis_span(range(len(a.values)), *clause.ranges.get(a.ix, (BELOW, ABOVE)))
            sides.append((max(start, first), min(stop, last)))
        if all(lo < hi for lo, hi in sides):
            out.append(tuple(sides))
    return out


def beyond(value: Column, cut_value: Column, cut_side: Column) -> Column:
    """Whether a value lies behind a cut."""
    return (value > cut_value) | ((value == cut_value) & (cut_side == 0))


def local_span(values: Column, lo: tuple[Column, Column], hi: tuple[Column, Column]) -> tuple[Column, Column]:
    """Positions ``[start, stop)`` of an ascending array between two cuts; a null cut value
    means no bound."""
    start = F.when(lo[0].isNull(), 0).otherwise(F.size(F.filter(values, lambda v: ~beyond(v, *lo))))
    stop = F.when(hi[0].isNull(), F.size(values)).otherwise(F.size(F.filter(values, lambda v: ~beyond(v, *hi))))
    return start, stop


def cut_literals(cut: Cut, dtype: str) -> tuple[Column, Column]:
    rank, value, side = cut
    return (F.lit(None).cast(dtype), F.lit(0)) if rank else (F.lit(value).cast(dtype), F.lit(side))


def box_table(spark, spec: GridSpec, boxes: list[Box]) -> DataFrame:
    """Boxes as rows: ``box_id``, ``<axis>_lo/_hi``, and value and side of spanning cuts."""
    fields, rows = [T.StructField("box_id", T.IntegerType())], []
    for a in spec.axes:
        if a.spans:
            kind = T._parse_datatype_string(a.dtype)
            for end in ("lo", "hi"):
                fields += [T.StructField(f"{a.name}_{end}", kind), T.StructField(f"{a.name}_{end}_side", T.IntegerType())]
        else:
            fields += [T.StructField(f"{a.name}_lo", T.IntegerType()), T.StructField(f"{a.name}_hi", T.IntegerType())]
    for k, box in enumerate(boxes):
        row: list = [k]
        for a, (lo, hi) in zip(spec.axes, box, strict=True):
            if a.spans:
                for rank, value, side in (lo, hi):
                    row += [None, 0] if rank else [int(value) if a.dtype in ("int", "bigint") else value, side]
            else:
                row += [lo, hi]
        rows.append(tuple(row))
    return spark.createDataFrame(rows, T.StructType(fields))


def rewrite_local(headers: DataFrame, spec: GridSpec, boxes: DataFrame) -> DataFrame:
    """``chunk, box_id, <axis>_start, <axis>_stop``: positional boxes of every chunk.

    The boxes are a driver's list and broadcast; headers are never collected.
    """
    span = spec.spanning
    both = headers.crossJoin(F.broadcast(boxes))
    start, stop = local_span(F.col(f"{span.name}_values"), (F.col(f"{span.name}_lo"), F.col(f"{span.name}_lo_side")), (F.col(f"{span.name}_hi"), F.col(f"{span.name}_hi_side")))
    sides = [F.col(f"{a.name}_lo").alias(f"{a.name}_start") for a in spec.inner] + [F.col(f"{a.name}_hi").alias(f"{a.name}_stop") for a in spec.inner]
    return both.select("chunk_key", "chunk", "box_id", start.cast("int").alias(f"{span.name}_start"), stop.cast("int").alias(f"{span.name}_stop"), *sides).where(F.col(f"{span.name}_start") < F.col(f"{span.name}_stop"))
