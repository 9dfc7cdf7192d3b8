"""Planning and running scans of a grid.

``Grid.scan`` turns a predicate into disjoint boxes on the driver and returns a lazy
DataFrame: a filter on the chunk key prunes directories, overlap tests prune tiles, and only
the positions inside a box are exploded from a tile's arrays.  Each variable is a Parquet
column of its own and read by ``get``, so unused ones are never read.  There is no shuffle.
"""

from __future__ import annotations

import re
import uuid
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from gridlake.model import Box, GridSpec, ScanOptions
from gridlake.operators import boxes as bx
from gridlake.plans import predicate as pr
from gridlake.plans import rewrite
from gridlake.sources import store


@dataclass(frozen=True)
class ScanPlan:
    """What a scan will look up: half-boxes, the residual test and the cover's statistics."""

    spec: GridSpec
    boxes: tuple[Box, ...]
    clauses: int
    stats: bx.CoverStats | None
    residual: str | None


class Grid:
    """A registered grid."""

    def __init__(self, spark: SparkSession, spec: GridSpec):
        self.spark, self.spec = spark, spec

    def tiles(self) -> DataFrame:
        return store.read_tiles(self.spark, self.spec.path)

    def headers(self) -> DataFrame:
        return store.read_headers(self.spark, self.spec.path)

    # --- planning ---------------------------------------------------------------

    def plan(self, predicate=None, options: ScanOptions = ScanOptions()) -> ScanPlan:
        """``predicate`` is a WHERE text or a tree of it."""
        spec = self.spec
        tree = pr.parse_predicate(predicate, spec) if isinstance(predicate, str) else predicate or pr.And(())
        clauses = pr.clauses_of(tree, options.max_clauses) if options.prune_rows else [pr.Clause()]
        boxes = rewrite.rewrite_global(spec, clauses)
        stats = None
        if options.cover in bx.COVERS and len(boxes) > 1:
            result = bx.COVERS[options.cover](boxes)
            boxes, stats = list(result.boxes), result.stats
        # boxes that are exact need no further test of the rows
        exact = options.prune_rows and options.cover in bx.COVERS and len(clauses) <= options.max_clauses and pr.decided(tree, options.max_clauses)
        residual = pr.to_sql(tree) if predicate and options.residual and not exact else None
        return ScanPlan(spec, tuple(boxes), len(clauses), stats, residual)

    def local_boxes(self, plan: ScanPlan) -> DataFrame:
        """Positional boxes of every chunk that has any."""
        return rewrite.rewrite_local(self._chunks(self.headers(), plan.boxes), self.spec, rewrite.box_table(self.spark, self.spec, list(plan.boxes)))

    def lookups(self, plan: ScanPlan) -> DataFrame:
        """Origin and length of every lookup, axes from the slowest to the fastest."""
        at = self.local_boxes(plan)
        origin = F.array(*[F.col(f"{a.name}_start") for a in self.spec.axes]).alias("origin")
        length = F.array(*[F.col(f"{a.name}_stop") - F.col(f"{a.name}_start") for a in self.spec.axes]).alias("length")
        return at.select("chunk", "box_id", origin, length)

    def _chunks(self, rows: DataFrame, boxes) -> DataFrame:
        """Chunks that any box can touch, by the chunk key alone."""
        span = self.spec.spanning
        at = [a.spans for a in self.spec.axes].index(True)
        tests = []
        for lo, hi in bx.union_1d(b[at] for b in boxes):
            test = F.lit(True)
            for (rank, value, _), lower in ((lo, True), (hi, False)):
                if not rank and self.spec.chunk_of:
                    key = F.expr(self.spec.chunk_of.format(f"CAST('{value if not isinstance(value, float) else int(value // 1)}' AS {span.dtype})"))
                    test &= F.col("chunk_key") >= key if lower else F.col("chunk_key") <= key
            tests.append(test)
        keep = F.lit(False)
        for t in tests:
            keep |= t
        return rows.where(keep)

    # --- rows -------------------------------------------------------------------

    def scan(self, columns: list[str] | None = None, predicate=None, options: ScanOptions = ScanOptions()) -> DataFrame:
        """The selected columns of the cells that satisfy the predicate."""
        plan = self.plan(predicate, options)
        out = self.emit(plan, options)
        if plan.residual:
            out = out.where(plan.residual)
        return out.select(*columns) if columns else out

    def rows(self, include_fill: bool = False) -> DataFrame:
        """Every cell as a row: chunk, spanning value, value and position per axis, variables."""
        return self.scan(options=ScanOptions(include_fill=include_fill))

    def emit(self, plan: ScanPlan, options: ScanOptions, tiles: DataFrame | None = None) -> DataFrame:
        """The cells of the plan's boxes; ``tiles`` are those of known chunks, else all are looked through."""
        spec, span = self.spec, self.spec.spanning
        if tiles is None:
            tiles = self._chunks(self.tiles(), plan.boxes) if options.prune_rows else self.tiles()
        around = bx.hull([b for b in plan.boxes]) if plan.boxes and options.prune_rows else None
        for a, (lo, hi) in zip(spec.axes, around or (), strict=False):
            if not a.spans and (lo, hi) != (0, len(a.values)):  # the first half reaches Parquet's statistics
                tiles = tiles.where((F.col(f"o_{a.name}") < hi) & (F.col(f"o_{a.name}") + F.col(f"n_{a.name}") > lo))
        if len(plan.boxes) <= options.inline_boxes:
            inside = [self._inside(dict(zip((a.name for a in spec.axes), b, strict=True))) for b in plan.boxes]
            if not inside:
                tiles, inside = tiles.limit(0), [self._inside({})]
            found = F.filter(F.array(*inside), self._touches)
        else:
            table = rewrite.box_table(self.spark, spec, list(plan.boxes))
            near = F.lit(True)
            for a in spec.inner:
                near &= (F.col(f"{a.name}_lo") < F.col(f"o_{a.name}") + F.col(f"n_{a.name}")) & (F.col(f"o_{a.name}") < F.col(f"{a.name}_hi"))
            tiles = tiles.join(F.broadcast(table), near)
            found = F.filter(F.array(self._inside(None)), self._touches)
        if options.lookup_cells:
            found = self._split(found, options.lookup_cells)
        tiles = tiles.withColumn("__at", F.explode(found)).withColumn("__lin", F.explode(self._offsets(0, F.lit(0))))
        ix, stride = {}, F.lit(1)
        for a in reversed(spec.axes):
            n = F.col(f"n_{a.name}")
            ix[a.name] = (F.col(f"o_{a.name}") + F.pmod(F.floor(F.col("__lin") / stride), n)).cast("int")
            stride = stride * n
        columns = [F.col("chunk")]
        for a in spec.axes:
            if a.spans:
                columns.append(F.get(f"{span.name}_values", ix[a.name]).alias(a.name))
            else:
                columns += [F.get(F.lit(list(a.values)), ix[a.name]).alias(a.name), ix[a.name].alias(a.ix)]
        variables = [F.get(v, F.col("__lin")).alias(v) for v in spec.variable_names]
        out = tiles.select(*columns, *variables)
        if not options.prune_columns:  # a test that no optimiser can see through keeps every variable read
            out = out.where(F.pmod(F.xxhash64(*spec.variable_names), F.lit(1_000_003)) >= 0)
        if not options.include_fill:
            out = out.where(F.col(spec.variable_names[0]).isNotNull())
        return out

    def _inside(self, box: dict | None) -> Column:
        """A box cut to the tile, as positions in the chunk; without a box, the joined one."""
        sides = []
        for a in self.spec.axes:
            if a.spans and box is not None and isinstance(box.get(a.name, (None,))[0], int):
                lo, hi = map(F.lit, box[a.name])
            elif a.spans:
                ends = [rewrite.cut_literals(c, a.dtype) for c in box.get(a.name, (rewrite.BELOW, rewrite.ABOVE))] if box is not None else [(F.col(f"{a.name}_{e}"), F.col(f"{a.name}_{e}_side")) for e in ("lo", "hi")]
                lo, hi = rewrite.local_span(F.col(f"{a.name}_values"), *ends)
            elif box is None:
                lo, hi = F.col(f"{a.name}_lo"), F.col(f"{a.name}_hi")
            else:
                lo, hi = map(F.lit, box.get(a.name, (0, len(a.values))))
            origin = F.col(f"o_{a.name}")
            sides += [F.greatest(lo.cast("int"), origin).alias(f"{a.name}_lo"), F.least(hi.cast("int"), origin + F.col(f"n_{a.name}")).alias(f"{a.name}_hi")]
        return F.struct(*sides)

    def _split(self, found: Column, cells: int) -> Column:
        """Lookups cut so that each has at most ``cells``: the slowest axes first, the fastest
        one stays whole."""
        names = [a.name for a in self.spec.axes]

        def length(b: Column, name: str) -> Column:
            return b[f"{name}_hi"] - b[f"{name}_lo"]

        def cut(k: int):
            def parts(b: Column) -> Column:
                own, inner = names[k], store.product([length(b, n).cast("long") for n in names[k + 1 :]])
                step = F.greatest(F.lit(1), F.floor(F.lit(cells) / inner).cast("int"))

                def part(at: Column) -> Column:
                    sides = {f"{own}_lo": at, f"{own}_hi": F.least(at + step, b[f"{own}_hi"])}
                    return F.struct(*[sides.get(f"{n}_{e}", b[f"{n}_{e}"]).cast("int").alias(f"{n}_{e}") for n in names for e in ("lo", "hi")])

                return F.transform(F.sequence(b[f"{own}_lo"], b[f"{own}_hi"] - 1, F.least(step, length(b, own))), part)

            return parts

        for k in range(len(names) - 1):
            found = F.flatten(F.transform(found, cut(k)))
        return found

    def _touches(self, b: Column) -> Column:
        test = F.lit(True)
        for a in self.spec.axes:
            test &= b[f"{a.name}_lo"] < b[f"{a.name}_hi"]
        return test

    def _offsets(self, k: int, base: Column) -> Column:
        """Linear offsets of a box inside its tile, row by row along the fastest axis."""
        a = self.spec.axes[k]
        lo, hi = F.col(f"__at.{a.name}_lo") - F.col(f"o_{a.name}"), F.col(f"__at.{a.name}_hi") - F.col(f"o_{a.name}")
        if k == len(self.spec.axes) - 1:
            return F.sequence(base + lo, base + hi - 1)
        stride = store.product([F.col(f"n_{x.name}") for x in self.spec.axes[k + 1 :]])
        return F.flatten(F.transform(F.sequence(lo, hi - 1), lambda p: self._offsets(k + 1, base + p * stride)))

    def lookup(self, chunk: str, variable: str, origin: list[int], length: list[int]) -> DataFrame:
        """One dense sub-array of one variable of one chunk, by positions only: a box of one
        chunk's tiles, so nothing else is read."""
        tiles = self.tiles().where(F.col("chunk") == chunk)
        if self.spec.keyed:
            tiles = tiles.where(F.col("chunk_key") == chunk)
        box = tuple((o, o + n) for o, n in zip(origin, length, strict=True))
        rows = self.emit(ScanPlan(self.spec, (box,), 1, None, None), ScanOptions(include_fill=True), tiles)
        return rows.select(*[a.ix for a in self.spec.inner], F.col(variable).alias("value"))


def register_grid(spark: SparkSession, name: str, path: str, spans: dict[str, bool], spec: GridSpec | None = None, envelope_dims: list[str] | None = None) -> Grid:
    """Connects a dataset: infers what it holds, unless told, and registers the row view.

    Queries on the view alone read whole chunks; ``plans.catalog`` plans any SQL with boxes.
    """
    grid = Grid(spark, spec or store.infer_grid(spark, name, path, spans))
    rows = grid.rows()
    if envelope_dims:
        from gridlake.operators.envelope import envelope

        rows = envelope(rows, *envelope_dims)
    rows.createOrReplaceTempView(name)
    return grid


_SELECT = re.compile(r"^\s*(SELECT\s+.+?)\s+FROM\s+(\w+)\s*(?:WHERE\s+(.+?))?\s*((?:GROUP\s+BY|ORDER\s+BY|HAVING|LIMIT)\b.*)?$", re.I | re.S)


def grid_sql(spark: SparkSession, grids: dict[str, Grid], text: str) -> DataFrame:
    """A SELECT over one grid whose WHERE goes through the box planner."""
    m = _SELECT.match(text)
    if not m:
        raise ValueError("only SELECT ... FROM grid [WHERE ...] [GROUP BY ...] is read")
    select, name, where, rest = m.groups()
    view = f"gridlake_{uuid.uuid4().hex}"
    grids[name].scan(predicate=where).createOrReplaceTempView(view)
    return spark.sql(f"{select} FROM {view} {rest or ''}")
