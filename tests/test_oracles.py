"""A choice of queries against DuckDB on the smallest tables, and plan and envelope checks."""

import duckdb
import pytest
from pyspark.sql import functions as F

import gridlake.queries as gq

from gridlake.operators import baselines as bl
from gridlake.operators import boxes as bx
from gridlake.operators.measures import diff
from gridlake.plans.scan import Grid
from gridlake.queries import methods
from gridlake.queries.methods import CELL, OVERLAPPING, Q1, Q2
from gridlake.queries.registry import Context
from gridlake.sources.derived import grid_spec

SF = "/root/testdata/sf0.001"
CHOICE = [
    "q_convex", "q_nonconvex", "q_two_regions", "pred_mixed", "pred_with_variable", "local_partial_chunk", "cover_from_data", "env_join_boxes", "env_join_left",
    "w_env_hull", "w_hist_qty_20", "b_dup_rows", "b_long_speed_max", "measures_q1", "interval_union", "join_asof", "pds_convex", "st_tumbling",
]
TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


@pytest.fixture(scope="module")
def duck():
    con = duckdb.connect()
    for t in TABLES:
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{SF}/{t}.parquet'")
    return con


def plain(rows, columns):
    order = sorted(range(len(columns)), key=columns.__getitem__)
    return sorted(tuple(f"{r[i]:.9g}" if isinstance(r[i], float) else str(r[i]) for i in order) for r in rows)


@pytest.mark.parametrize("name", CHOICE)
def test_query(spark, duck, name):
    got = gq.queries()[name](spark, SF)
    want = duck.execute(gq.oracle_sql()[name])
    columns = [d[0] for d in want.description]
    assert sorted(got.columns) == sorted(columns)
    assert plain(got.collect(), got.columns) == plain(want.fetchall(), columns)


def test_scan_prunes(spark):
    grid = Grid(spark, grid_spec(spark, SF, "g3"))
    plan = grid.scan(["chunk", "price_sum"], Q1)._jdf.queryExecution().executedPlan().toString()
    assert "price_max" not in plan and "Exchange" not in plan and "PartitionFilters: [isnotnull(chunk_key" in plan


def test_baselines_agree(spark):
    grid = Grid(spark, grid_spec(spark, SF, "g3"))
    planned = grid.scan(CELL, OVERLAPPING)
    assert diff(planned, bl.full_scan(grid, CELL, OVERLAPPING)) == (0, 0)
    assert diff(planned, bl.hull_scan(grid, CELL, OVERLAPPING)) == (0, 0)
    assert bl.no_elimination(grid, CELL, OVERLAPPING).count() > planned.count()
    assert planned.distinct().count() == planned.count()
    assert grid.scan(CELL, Q2).where(f"NOT ({Q2})").agg(F.count("*")).first()[0] == 0


@pytest.mark.parametrize("name", ["ge_rows", "local_partial_chunk", "ge_user_rows", "local_partial_users"])
def test_event_queries(spark, name):
    """With more users than remainders of their ids."""
    more = SF.replace("0.001", "0.01")
    want = duckdb.execute(gq.oracle_sql()[name].replace("FROM events", f"FROM '{more}/events.parquet' events"))
    columns = [d[0] for d in want.description]
    got = gq.queries()[name](spark, more)
    assert sorted(got.columns) == sorted(columns)
    assert plain(got.collect(), got.columns) == plain(want.fetchall(), columns) != []


def test_event_users_are_kept(spark):
    more = SF.replace("0.001", "0.01")
    want = duckdb.execute(f"SELECT COUNT(DISTINCT (date_trunc('hour', ts), user_id, event_type)), COUNT(DISTINCT user_id) FROM '{more}/events.parquet'").fetchone()
    events = Grid(spark, grid_spec(spark, more, "ge")).rows()
    assert (events.count(), events.select("user").distinct().count()) == want


@pytest.mark.parametrize("name", ["axis_span_asc", "axis_span_desc", "axis_spans_in", *[f"cover_{w}{k}" for w in ("", "grid_") for k in ("aligned", "misaligned", "diagonal", "centred")]])
def test_axes_and_boxes_come_from_the_table(spark, duck, name):
    got = gq.queries()[name](spark, SF)
    assert [f for f in got.inputFiles() if f.endswith(("lineitem.parquet", "customer.parquet"))]
    want = duck.execute(gq.oracle_sql()[name])
    columns = [d[0] for d in want.description]
    assert got.columns == columns
    assert plain(got.collect(), columns) == plain(want.fetchall(), columns) != []


def test_bench_boxes_come_from_the_table():
    rows = [methods.cover_times("aligned", 2, (8,), shifts) for shifts in ((0,), (0, 3, 1))]
    assert rows[0][0][6] != rows[1][0][6] and rows[1][0][6] == rows[1][1][6]


def test_bench_runs_in_tasks(spark):
    """The same rows as on the driver but for the seconds, from a plan that reads the table."""
    got = methods.bench_times(Context(spark, SF), (2, 8))
    assert [f for f in got.inputFiles() if f.endswith("customer.parquet")]
    shifts = [v for (v,) in duckdb.execute(f"SELECT CAST(floor(abs(c_acctbal)) AS BIGINT) % 4 FROM '{SF}/customer.parquet' ORDER BY c_custkey").fetchall()]
    want = [r for kind in bx.WORKLOADS for d in (1, 2, 3, 4) for r in methods.cover_times(kind, d, (2, 8), shifts)]
    assert sorted((*r[:4], *r[5:]) for r in got.collect()) == sorted((*r[:4], *r[5:]) for r in want)
