"""A Python data source over the tile store: ``spark.read.format("gridtiles")``.

A secondary surface.  The engine hands it single comparisons only, so it pushes down convex
predicates on axes; each tile file is a partition, and rows come as Arrow batches.
"""

from __future__ import annotations

import json

import numpy as np
import pyarrow as pa
from pyspark.sql.datasource import DataSource, DataSourceReader, EqualTo, GreaterThan, GreaterThanOrEqual, InputPartition, LessThan, LessThanOrEqual

from gridlake.model import ABOVE, BELOW, GridSpec, after, axis_span, before

_ARROW = {"double": pa.float64(), "bigint": pa.int64(), "float": pa.float32(), "int": pa.int32()}


class TilePartition(InputPartition):
    def __init__(self, rows: list[dict]):
        self.rows = rows


class TileReader(DataSourceReader):
    def __init__(self, tiles: list[dict], axes: list[dict], variables: list[list[str]]):
        self.tiles, self.axes, self.variables, self.ranges = tiles, axes, variables, {}

    def pushFilters(self, filters):
        for f in filters:
            name = f.attribute[0] if hasattr(f, "attribute") and len(f.attribute) == 1 else None
            if name in {a["name"] for a in self.axes} and isinstance(f, EqualTo | GreaterThan | GreaterThanOrEqual | LessThan | LessThanOrEqual):
                lo, hi = self.ranges.get(name, (BELOW, ABOVE))
                if isinstance(f, GreaterThan | GreaterThanOrEqual | EqualTo):
                    lo = max(lo, after(f.value) if isinstance(f, GreaterThan) else before(f.value))
                if isinstance(f, LessThan | LessThanOrEqual | EqualTo):
                    hi = min(hi, before(f.value) if isinstance(f, LessThan) else after(f.value))
                self.ranges[name] = (lo, hi)
            yield f  # the rows are tested again

    def partitions(self):
        spans = {a["name"]: axis_span(a["values"], *self.ranges.get(a["name"], (BELOW, ABOVE))) for a in self.axes}
        keep = [t for t in self.tiles if all(t[f"o_{n}"] < hi and t[f"o_{n}"] + t[f"n_{n}"] > lo for n, (lo, hi) in spans.items())]
        return [TilePartition(keep[k : k + 64]) for k in range(0, len(keep), 64)] or [TilePartition([])]

    def read(self, partition):
        names = [a["name"] for a in self.axes]
        for t in partition.rows:
            shape = [t[f"n_{n}"] for n in names]
            grids = np.meshgrid(*[np.arange(t[f"o_{n}"], t[f"o_{n}"] + t[f"n_{n}"]) for n in names], indexing="ij")
            columns = [pa.array([t["chunk"]] * int(np.prod(shape)), pa.string())]
            columns += [pa.array(np.array(a["values"], float)[g.ravel()]) for a, g in zip(self.axes, grids, strict=True)]
            columns += [pa.array(t[v], _ARROW[kind]) for v, kind in self.variables]
            yield pa.RecordBatch.from_arrays(columns, ["chunk", *names, *[v for v, _ in self.variables]])


class GridTiles(DataSource):
    """Options: ``tiles`` and ``spec`` as JSON, made by ``options_for``."""

    @classmethod
    def name(cls):
        return "gridtiles"

    def schema(self):
        spec = json.loads(self.options["spec"])
        return ", ".join(["chunk string", *[f"{a['name']} double" for a in spec["axes"]], *[f"{v} {k}" for v, k in spec["variables"]]])

    def reader(self, schema):
        spec = json.loads(self.options["spec"])
        return TileReader(json.loads(self.options["tiles"]), spec["axes"], spec["variables"])


def options_for(grid, chunks: list[str], variables: list[str]) -> dict[str, str]:
    """The tiles of a stated list of chunks as options; the list bounds what is collected."""
    spec: GridSpec = grid.spec
    from pyspark.sql import functions as F

    keep = grid.tiles().where(F.col("chunk").isin(chunks)).select("chunk", *[f"{e}_{a.name}" for a in spec.inner for e in ("o", "n")], *variables)
    axes = [{"name": a.name, "values": list(a.values)} for a in spec.inner]
    return {"tiles": json.dumps([r.asDict() for r in keep.collect()]), "spec": json.dumps({"axes": axes, "variables": [list(v) for v in spec.variables if v[0] in variables]})}
