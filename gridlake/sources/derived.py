"""Grids derived from the tables: stand-ins for the three subsets of a climate archive.

g3  lineitem by month, quantity (stored 50 to 1) and discount
g4  the same with tax as a level axis
gp  orders and customers by month, nation and priority
ge  events by day chunk: hours (several in a chunk, with gaps), user, event type
gv  embeddings: one vector in a chunk, natively dense
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from gridlake.model import Axis, GridSpec
from gridlake.sources import store

#: Users in a tile of the event grid: the grid grows with them, a tile doesn't.
USER_TILE = 64

QTY = Axis("qty", values=tuple(float(v) for v in range(50, 0, -1)))
DISC = Axis("disc", values=tuple(i / 100 for i in range(11)))
LEVEL = Axis("level", values=tuple(i / 100 for i in range(9)))
MONTH = "date_format({0}, 'yyyy-MM')"
#: Ids as text in the order of the ids, negative ones included.
VECTOR_KEY = "lpad(cast(cast({0} as decimal(20,0)) + 9223372036854775808 as string), 20, '0')"


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def money(column: str) -> Column:
    """An exact sum, as a double."""
    return F.sum(F.col(column).cast("decimal(18,2)")).cast("double")


def month(column: str) -> Column:
    return F.date_trunc("month", F.col(column)).cast("timestamp_ntz")


def _lineitem(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "lineitem").select(
        F.expr(MONTH.format("l_shipdate")).alias("chunk_key"), month("l_shipdate").alias("ship_month"),
        (50 - F.col("l_quantity")).cast("int").alias("qty_ix"), F.round(F.col("l_discount") * 100).cast("int").alias("disc_ix"), F.round(F.col("l_tax") * 100).cast("int").alias("level_ix"),
        "l_extendedprice", "l_tax", "l_returnflag", "l_partkey", "l_suppkey",
    )


def g3_cells(spark: SparkSession, sf_dir: str) -> DataFrame:
    n = F.count("*")
    return _lineitem(spark, sf_dir).groupBy("chunk_key", "ship_month", "qty_ix", "disc_ix").agg(
        n.alias("n_lines"), money("l_extendedprice").alias("price_sum"), (money("l_extendedprice") / n).alias("price_avg"), F.max("l_extendedprice").alias("price_max"),
        (money("l_tax") / n).alias("tax_avg"), F.count_if(F.col("l_returnflag") == "R").alias("n_returned"),
    )


def g4_cells(spark: SparkSession, sf_dir: str) -> DataFrame:
    n = F.count("*")
    return _lineitem(spark, sf_dir).groupBy("chunk_key", "ship_month", "level_ix", "qty_ix", "disc_ix").agg(
        n.alias("n_lines"), money("l_extendedprice").alias("price_sum"), (money("l_extendedprice") / n).alias("price_avg"), F.max("l_extendedprice").alias("price_max"),
        F.min("l_partkey").alias("part_min"), F.countDistinct("l_suppkey").alias("supp_cnt"),
    )


PRIORITIES = ("1-URGENT", "2-HIGH", "3-MEDIUM", "4-NOT SPECIFIED", "5-LOW")
EVENT_TYPES = ("cart", "click", "purchase", "search", "view")


def code(column: str, names: tuple[str, ...]) -> Column:
    """Rank of a string among the names, from 0."""
    return (F.array_position(F.lit(list(names)), F.col(column)) - 1).cast("int")


def gp_cells(spark: SparkSession, sf_dir: str, priorities: tuple[str, ...] = PRIORITIES) -> DataFrame:
    both = table(spark, sf_dir, "orders").join(table(spark, sf_dir, "customer").select("c_custkey", "c_nationkey"), F.col("o_custkey") == F.col("c_custkey"))
    return both.groupBy(F.expr(MONTH.format("o_orderdate")).alias("chunk_key"), month("o_orderdate").alias("order_month"), F.col("c_nationkey").alias("nation_ix"), code("o_orderpriority", priorities).alias("prio_ix")).agg(
        F.count("*").alias("n_orders"), money("o_totalprice").alias("price_sum"), F.max("o_totalprice").alias("price_max"),
    )


def ge_cells(spark: SparkSession, sf_dir: str, users: tuple[int, ...], types: tuple[str, ...] = EVENT_TYPES) -> DataFrame:
    hour = F.date_trunc("hour", F.col("ts")).cast("timestamp_ntz")
    ranks = spark.createDataFrame([(u, k) for k, u in enumerate(users)], "user_id long, user_ix int")
    return table(spark, sf_dir, "events").join(ranks, "user_id").groupBy(F.expr("date_format(ts, 'yyyy-MM-dd')").alias("chunk_key"), hour.alias("hour"), "user_ix", code("event_type", types).alias("etype_ix")).agg(
        F.count("*").alias("n_events"), money("value").alias("value_sum"), F.max("value").alias("value_max"),
    )


def _names(spark: SparkSession, sf_dir: str, name: str, column: str) -> tuple:
    """The values of a coded axis: the column's distinct values in order."""
    return tuple(r[0] for r in table(spark, sf_dir, name).select(column).dropna().distinct().orderBy(column).collect())


def _ingest(spark: SparkSession, sf_dir: str, name: str, path: str) -> GridSpec:
    span, chunk_of, lens = "ship_month", MONTH, {}
    if name == "g3":
        cells, inner, lens = g3_cells(spark, sf_dir), (QTY, DISC), {"qty": 10}
        axes = (Axis("ship_month", True, "timestamp_ntz"), *inner)
    elif name == "g4":
        cells, lens = g4_cells(spark, sf_dir), {"level": 3}
        axes = (Axis("ship_month", True, "timestamp_ntz"), LEVEL, QTY, DISC)
    elif name == "gp":
        names, span = _names(spark, sf_dir, "orders", "o_orderpriority"), "order_month"
        cells = gp_cells(spark, sf_dir, names)
        axes = (Axis(span, True, "timestamp_ntz"), Axis("nation", values=tuple(map(float, range(25)))), Axis("prio", values=tuple(map(float, range(len(names))))))
    elif name == "ge":
        names, span, chunk_of, lens = _names(spark, sf_dir, "events", "event_type"), "hour", "date_format({0}, 'yyyy-MM-dd')", {"hour": 6, "user": USER_TILE}
        users = _names(spark, sf_dir, "events", "user_id")
        cells = ge_cells(spark, sf_dir, users, names)
        axes = (Axis(span, True, "timestamp_ntz"), Axis("user", values=tuple(map(float, users))), Axis("etype", values=tuple(map(float, range(len(names))))))
    else:
        return _vectors(spark, sf_dir, path)
    variables = tuple((f.name, f.dataType.simpleString()) for f in cells.schema.fields if f.name not in ("chunk_key", span) and not f.name.endswith("_ix"))
    store.write_grid(*store.build_tiles(cells, axes, variables, lens), path)
    return store.infer_grid(spark, name, path, {span: True}, chunk_of)


def _vectors(spark: SparkSession, sf_dir: str, path: str) -> GridSpec:
    """Embeddings are dense arrays already: a tile is a row of the table."""
    vectors = table(spark, sf_dir, "embeddings").where("vec_id IS NOT NULL AND embedding IS NOT NULL")
    length = vectors.select(F.max(F.size("embedding"))).first()[0] or 0
    key = F.expr(VECTOR_KEY.format("vec_id")).alias("chunk_key")
    zero, one = F.lit(0), F.lit(1)
    tiles = vectors.select(key, F.col("vec_id").cast("string").alias("chunk"), F.array("vec_id").alias("vec_id_values"), zero.alias("o_vec_id"), zero.alias("o_comp"), one.alias("n_vec_id"), F.size("embedding").alias("n_comp"), F.col("embedding").alias("x"))
    headers = vectors.select(key, F.col("vec_id").cast("string").alias("chunk"), F.array("vec_id").alias("vec_id_values"), F.lit([float(i) for i in range(length)]).alias("comp_values"))
    store.write_grid(tiles, headers, path, partition=False)
    return store.infer_grid(spark, "gv", path, {"vec_id": True}, VECTOR_KEY, keyed=False)


def grid_spec(spark: SparkSession, sf_dir: str, name: str) -> GridSpec:
    return store.cached(spark, sf_dir, name, lambda path: _ingest(spark, sf_dir, name, path))
