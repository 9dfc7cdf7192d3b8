"""Plain SQL over registered grids, planned with boxes.

A registered grid stands in a query as a leaf that holds its columns and no rows, so that
the optimiser can be asked what it would filter there: it pushes every conjunct down to
the leaf, derives more of them over joins and knows nothing yet of the tiles.  What it
finds at the leaves becomes the predicate of one scan for each grid (several occurrences are
joined by OR), and the same text runs over those scans.  A row that no occurrence asks for
can't change the answer, as every filter is applied again by the query itself.

An envelope of a registered grid is a filter on its leaf that removes nothing.  The
optimiser carries it over equi-joins to the other grids' leaves.
"""

from __future__ import annotations

import threading
import uuid
from datetime import datetime, timedelta

from pyspark.sql import DataFrame, SparkSession

from gridlake.model import ScanOptions
from gridlake.plans import predicate as pr
from gridlake.plans.scan import Grid
from gridlake.sources.store import shared_dir

_COMPARE = {"EqualTo": "=", "EqualNullSafe": "=", "LessThan": "<", "LessThanOrEqual": "<=", "GreaterThan": ">", "GreaterThanOrEqual": ">="}
_views = threading.RLock()


def _seq(xs) -> list:
    return [xs.apply(k) for k in range(xs.size())]


def _kind(node) -> str:
    return node.getClass().getSimpleName()


def _value(literal, axis_type: str):
    """A literal as the axis' type; ValueError where boxes can't use it."""
    value, kind = literal.value(), literal.dataType().simpleString()
    if value is None:
        raise ValueError("null")
    if kind == "timestamp_ntz" and axis_type == kind:
        return datetime(1970, 1, 1) + timedelta(microseconds=int(value))
    if kind in ("double", "float", "int", "bigint", "smallint", "tinyint") and not axis_type.startswith(("timestamp", "date", "string")):
        return float(value)
    if kind.startswith("decimal") and not axis_type.startswith(("timestamp", "date", "string")):
        return float(value.toString())
    if kind == "string" and axis_type == "string":
        return value.toString()
    raise ValueError(kind)


def tree_of(e, types: dict[str, str], negated: bool = False):
    """An optimised condition as a predicate tree; what positions can't decide is opaque."""
    kind = _kind(e)
    if kind in ("And", "Or"):
        make = pr.And if (kind == "And") != negated else pr.Or
        return make((tree_of(e.left(), types, negated), tree_of(e.right(), types, negated)))
    if kind == "Not":
        return tree_of(e.child(), types, not negated)
    try:
        if kind in _COMPARE:
            left, right, op = e.left(), e.right(), _COMPARE[kind]
            if _kind(left) == "Literal":
                left, right, op = right, left, pr.MIRROR[op]
            if _kind(left) == "AttributeReference" and _kind(right) == "Literal" and left.name() in types:
                return pr.atom(left.name(), op, _value(right, types[left.name()]), negated)
        if kind == "In" and _kind(e.value()) == "AttributeReference" and e.value().name() in types:
            items = [pr.atom(e.value().name(), "=", _value(x, types[e.value().name()]), negated) for x in _seq(e.list()) if _kind(x) == "Literal"]
            if len(items) == e.list().size():
                return (pr.And if negated else pr.Or)(tuple(items))
    except ValueError:
        pass
    return pr.Opaque(e.sql(), negated)


class Catalog:
    """Registered grids and the SQL over them."""

    def __init__(self, spark: SparkSession):
        self.spark = spark
        self.grids: dict[str, Grid] = {}
        self.leaves: dict[str, tuple[str, DataFrame]] = {}

    def register(self, name: str, grid: Grid, envelope_dims: tuple[str, ...] = (), rows: DataFrame | None = None) -> None:
        """Makes a grid known, if asked for with its hull over some axes as an envelope.

        ``rows`` narrows what the envelope bounds, e.g. to a selective part of the grid.
        """
        path = f"{shared_dir(self.spark)}/gridlake-leaf-{uuid.uuid4().hex}"
        schema = grid.rows().schema
        self.spark.createDataFrame([], schema).write.parquet(path)
        leaf = self.spark.read.schema(schema).parquet(path)
        if envelope_dims:
            from gridlake.operators.envelope import envelope_test

            leaf = leaf.where(envelope_test(grid.rows() if rows is None else rows, *envelope_dims))
        self.grids[name], self.leaves[name] = grid, (path, leaf)

    # --- planning -----------------------------------------------------------------

    def _wanted(self, plan, types: dict[str, dict[str, str]], found: dict[str, list], above=()) -> None:
        """Adds the filter right above every leaf to ``found``."""
        kind = _kind(plan)
        if kind == "LogicalRelation":
            where = plan.relation().location().rootPaths().mkString(",")
            for name, (path, _) in self.leaves.items():
                if path.rsplit("/", 1)[-1] in where:
                    found[name].append(pr.And(tuple(tree_of(c, types[name]) for c in above)))
        for child in _seq(plan.children()):
            self._wanted(child, types, found, (*above, plan.condition()) if kind == "Filter" else ())
        for sub in _seq(plan.subqueries()):
            self._wanted(sub, types, found)

    def predicates(self, text: str) -> dict[str, object]:
        """For every grid that a text reads, the tree its scan is planned with."""
        types = {n: {a.name: a.dtype for a in g.spec.axes} | {a.ix: "int" for a in g.spec.inner} for n, g in self.grids.items()}
        found: dict[str, list] = {n: [] for n in self.grids}
        with _views:
            for name, (_, leaf) in self.leaves.items():
                leaf.createOrReplaceTempView(name)
            asked = self.spark.sql(text)
        self._wanted(asked._jdf.queryExecution().optimizedPlan(), types, found)
        return {n: trees[0] if len(trees) == 1 else pr.Or(tuple(trees)) for n, trees in found.items() if trees}

    def sql(self, text: str, options: ScanOptions = ScanOptions()) -> DataFrame:
        """Any SELECT over the registered grids and the session's other tables."""
        trees = self.predicates(text)
        with _views:
            for name, grid in self.grids.items():
                rows = grid.scan(options=options.but(residual=False), predicate=trees[name]) if name in trees else grid.rows()
                rows.createOrReplaceTempView(name)
            return self.spark.sql(text)

