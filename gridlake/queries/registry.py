"""How queries are declared: a name, a function of the context and, where SQL can say it, SQL."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession

from gridlake.plans.scan import Grid
from gridlake.sources.derived import grid_spec

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLES: dict[str, str] = {}


@dataclass(frozen=True)
class Context:
    spark: SparkSession
    sf: str

    def table(self, name: str) -> DataFrame:
        return self.spark.read.parquet(f"{self.sf}/{name}.parquet")

    def grid(self, name: str) -> Grid:
        return Grid(self.spark, grid_spec(self.spark, self.sf, name))


def add(name: str, build: Callable[[Context], DataFrame], sql: str | None = None) -> None:
    if name in QUERIES:
        raise ValueError(f"query {name} is declared twice")
    QUERIES[name] = lambda spark, sf: build(Context(spark, sf))
    if sql:
        ORACLES[name] = sql


def query(name: str, sql: str | None = None):
    def put(build):
        add(name, build, sql)
        return build

    return put


_SUM = "CAST(SUM(CAST({0} AS DECIMAL(18,2))) AS DOUBLE)"
_PRICE = f"{_SUM.format('l_extendedprice')} AS price_sum, {_SUM.format('l_extendedprice')} / COUNT(*) AS price_avg, MAX(l_extendedprice) AS price_max"
_LINE = "strftime(l_shipdate, '%Y-%m') AS chunk, date_trunc('month', l_shipdate) AS ship_month"
_INNER = "l_quantity AS qty, CAST(50 - l_quantity AS INTEGER) AS qty_ix, l_discount AS disc, CAST(round(l_discount * 100) AS INTEGER) AS disc_ix"
#: The grids over the base tables, as common table expressions.
G3 = f"g3 AS (SELECT {_LINE}, {_INNER}, COUNT(*) AS n_lines, {_PRICE}, {_SUM.format('l_tax')} / COUNT(*) AS tax_avg, CAST(SUM(CASE WHEN l_returnflag = 'R' THEN 1 ELSE 0 END) AS BIGINT) AS n_returned FROM lineitem GROUP BY ALL)"
G4 = f"g4 AS (SELECT {_LINE}, l_tax AS level, CAST(round(l_tax * 100) AS INTEGER) AS level_ix, {_INNER}, COUNT(*) AS n_lines, {_PRICE}, MIN(l_partkey) AS part_min, COUNT(DISTINCT l_suppkey) AS supp_cnt FROM lineitem GROUP BY ALL)"
GP = f"gp AS (SELECT strftime(o_orderdate, '%Y-%m') AS chunk, date_trunc('month', o_orderdate) AS order_month, CAST(c_nationkey AS DOUBLE) AS nation, c_nationkey AS nation_ix, CAST(p.k AS DOUBLE) AS prio, p.k AS prio_ix, COUNT(*) AS n_orders, {_SUM.format('o_totalprice')} AS price_sum, MAX(o_totalprice) AS price_max FROM orders JOIN customer ON o_custkey = c_custkey JOIN (SELECT o_orderpriority AS name, CAST(row_number() OVER (ORDER BY o_orderpriority) - 1 AS INTEGER) AS k FROM (SELECT DISTINCT o_orderpriority FROM orders)) p ON p.name = o_orderpriority GROUP BY ALL)"
GE = f"ge AS (SELECT strftime(ts, '%Y-%m-%d') AS chunk, date_trunc('hour', ts) AS hour, CAST(user_id % 100 AS DOUBLE) AS \"user\", CAST(user_id % 100 AS INTEGER) AS user_ix, CAST(t.k AS DOUBLE) AS etype, t.k AS etype_ix, COUNT(*) AS n_events, {_SUM.format('value')} AS value_sum, MAX(value) AS value_max FROM events JOIN (SELECT event_type AS name, CAST(row_number() OVER (ORDER BY event_type) - 1 AS INTEGER) AS k FROM (SELECT DISTINCT event_type FROM events)) t ON t.name = event_type GROUP BY ALL)"
#: The event grid itself; GE is its users grouped by the remainder of their ids.
GU = f"gu AS (SELECT strftime(ts, '%Y-%m-%d') AS chunk, date_trunc('hour', ts) AS hour, CAST(u.user_id AS DOUBLE) AS \"user\", u.k AS user_ix, CAST(t.k AS DOUBLE) AS etype, t.k AS etype_ix, COUNT(*) AS n_events, {_SUM.format('value')} AS value_sum, MAX(value) AS value_max FROM events JOIN (SELECT user_id, CAST(row_number() OVER (ORDER BY user_id) - 1 AS INTEGER) AS k FROM (SELECT DISTINCT user_id FROM events WHERE user_id IS NOT NULL)) u ON u.user_id = events.user_id JOIN (SELECT event_type AS name, CAST(row_number() OVER (ORDER BY event_type) - 1 AS INTEGER) AS k FROM (SELECT DISTINCT event_type FROM events)) t ON t.name = event_type GROUP BY ALL)"
