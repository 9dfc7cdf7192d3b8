"""The SQL surface around the grids: each operator once, on a grid or a table."""

from __future__ import annotations

import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from gridlake.functions.science import histogram, speed
from gridlake.operators.cover_df import islands
from gridlake.operators.joins import asof_join, overlap_join, range_join
from gridlake.plans.scan import grid_sql
from gridlake.queries.methods import CELL, CELLS, EXACT, exact_sum, pairs
from gridlake.queries.registry import G3, G4, GE, GP, Context, add, query
from gridlake.sources.datasource import GridTiles, options_for
from gridlake.sources.store import shared_dir
from gridlake.streaming import ops as st


def g3(c: Context, test: str | None = None, columns: list[str] | None = CELL) -> DataFrame:
    return c.grid("g3").scan(columns, test)


def grid_query(name: str, build, sql: str, grids: str = G3) -> None:
    """``build`` gets the context; ``sql`` goes behind the grids' definitions."""
    add(name, build, f"WITH {grids}{sql}" if sql.startswith(",") else f"WITH {grids} {sql}")


# --- sources and sinks --------------------------------------------------------------


def roundtrip(c: Context, kind: str) -> DataFrame:
    path = f"{shared_dir(c.spark)}/gridlake-roundtrip-{kind}-{abs(hash(c.sf))}"
    rows = g3(c, "qty <= 10")
    if kind == "flat":
        rows.repartition("chunk").sortWithinPartitions("chunk", "qty_ix", "disc_ix").write.mode("overwrite").parquet(path)
        return c.spark.read.schema(rows.schema).parquet(path)
    rows.write.mode("overwrite").format(kind).save(path)
    return c.spark.read.schema(rows.schema).format(kind).load(path)


for name, kind in {"flat_roundtrip": "flat", "csv_roundtrip": "csv", "json_roundtrip": "json", "orc_roundtrip": "orc"}.items():
    grid_query(name, lambda c, kind=kind: roundtrip(c, kind), f"SELECT {CELLS} FROM g3 WHERE qty <= 10")
grid_query("tile_roundtrip", lambda c: c.grid("g3").tiles().groupBy("chunk").agg(F.sum(F.size("n_lines")).alias("cells"), F.sum(F.size(F.filter("n_lines", lambda x: x.isNotNull()))).alias("filled")), "SELECT chunk, CAST(550 AS BIGINT) AS cells, COUNT(*) AS filled FROM g3 GROUP BY chunk")


def python_source(c: Context) -> DataFrame:
    c.spark.dataSource.register(GridTiles)
    c.spark.conf.set("spark.sql.python.filterPushdown.enabled", "true")  # a session setting, off by default
    read = c.spark.read.format("gridtiles").options(**options_for(c.grid("g3"), ["1997-03", "1997-04"], ["n_lines", "price_max"])).load()
    return read.where("qty > 20.2 AND qty < 35.5 AND n_lines IS NOT NULL")


grid_query("pds_convex", python_source, "SELECT chunk, qty, disc, n_lines, price_max FROM g3 WHERE chunk IN ('1997-03', '1997-04') AND qty > 20.2 AND qty < 35.5")


def sql_view(c: Context) -> DataFrame:
    g3(c).createOrReplaceTempView("g3_cells")
    return c.spark.sql("SELECT chunk, SUM(n_lines) AS n FROM g3_cells GROUP BY chunk HAVING SUM(n_lines) > 3")


grid_query("sql_view", sql_view, "SELECT chunk, CAST(SUM(n_lines) AS BIGINT) AS n FROM g3 GROUP BY chunk HAVING SUM(n_lines) > 3")
grid_query("rows_per_chunk", lambda c: g3(c).groupBy("chunk").agg(F.count("*").alias("n")), "SELECT chunk, COUNT(*) AS n FROM g3 GROUP BY chunk")
grid_query("grid_sql_q", lambda c: grid_sql(c.spark, {"g3": c.grid("g3")}, "SELECT disc_ix, COUNT(*) AS n FROM g3 WHERE qty > 20 OR disc = 0.1 GROUP BY disc_ix"), "SELECT disc_ix, COUNT(*) AS n FROM g3 WHERE qty > 20 OR disc = 0.1 GROUP BY disc_ix")

# --- projections and filters --------------------------------------------------------

grid_query("proj_basic", lambda c: g3(c).select(F.col("chunk").alias("file"), (F.col("price_sum") / F.col("n_lines")).alias("mean"), "qty"), "SELECT chunk AS file, price_sum / n_lines AS mean, qty FROM g3")
for name, test in {
    "cmp": "qty >= 10 AND qty <= 40 AND disc <> 0.05 AND disc > 0.01 AND disc < 0.09",
    "between": "qty BETWEEN 11 AND 13",
    "in": "disc IN (0.01, 0.1)",
    "not_in": "qty NOT IN (1, 2, 3)",
    "nested": "NOT (qty > 10 AND (disc < 0.05 OR NOT (qty < 45))) OR disc = 0.02",
    "variable": "n_lines >= 2 AND qty < 20",
}.items():
    grid_query(f"filter_{name}", lambda c, test=test: g3(c, test), f"SELECT {CELLS} FROM g3 WHERE {test}")
grid_query("filter_time", lambda c: g3(c, "ship_month >= '1998-01-01' AND ship_month < '1998-04-01' AND qty < 5"), f"SELECT {CELLS} FROM g3 WHERE ship_month >= TIMESTAMP '1998-01-01' AND ship_month < TIMESTAMP '1998-04-01' AND qty < 5")
grid_query("filter_null", lambda c: c.grid("g3").rows(include_fill=True).groupBy("chunk").agg(F.count_if(F.col("n_lines").isNull()).alias("fill"), F.count_if(F.col("n_lines").isNotNull()).alias("filled")), "SELECT chunk, 550 - COUNT(*) AS fill, COUNT(*) AS filled FROM g3 GROUP BY chunk")
grid_query("filter_like", lambda c: g3(c).where("chunk LIKE '1997-%' AND chunk RLIKE '-(03|04)$'"), f"SELECT {CELLS} FROM g3 WHERE chunk LIKE '1997-%' AND regexp_matches(chunk, '-(03|04)$')")
grid_query("case_when", lambda c: g3(c).select("chunk", "qty", "disc", F.when(F.col("qty") > 25, "high").when(F.col("qty") > 10, "mid").otherwise("low").alias("band"), F.coalesce(F.nullif(F.col("n_lines"), F.lit(1)), F.lit(0)).alias("more")), "SELECT chunk, qty, disc, CASE WHEN qty > 25 THEN 'high' WHEN qty > 10 THEN 'mid' ELSE 'low' END AS band, COALESCE(NULLIF(n_lines, 1), 0) AS more FROM g3")
grid_query("distinct_rows", lambda c: g3(c).select("qty", "n_lines").distinct(), "SELECT DISTINCT qty, n_lines FROM g3")
add("sample_rows", lambda c: g3(c).sample(0.1, 7))

# --- joins --------------------------------------------------------------------------

KEY = ["chunk", "qty", "disc"]


def g4(c: Context, *columns: str) -> DataFrame:
    return c.grid("g4").scan([*KEY, "level", *columns])


def joined(c: Context, hint: str | None = None, how: str = "inner") -> DataFrame:
    left = g3(c, "qty <= 20", [*KEY, "price_max"])
    right = g4(c, "part_min").where("qty >= 15")
    return left.join(right.hint(hint) if hint else right, KEY, how)


_J = "SELECT {0} FROM (SELECT chunk, qty, disc, price_max FROM g3 WHERE qty <= 20) a {1} JOIN (SELECT chunk, qty, disc, level, part_min FROM g4 WHERE qty >= 15) b ON a.chunk = b.chunk AND a.qty = b.qty AND a.disc = b.disc"
_JALL = "COALESCE(a.chunk, b.chunk) AS chunk, COALESCE(a.qty, b.qty) AS qty, COALESCE(a.disc, b.disc) AS disc, price_max, level, part_min"
for name, hint in {"join_g3_g4": None, "join_broadcast": "broadcast", "join_merge": "merge", "join_shuffle_hash": "shuffle_hash"}.items():
    grid_query(name, lambda c, hint=hint: joined(c, hint), _J.format(_JALL, ""), f"{G3}, {G4}")
for how in ("left", "right", "full"):
    grid_query(f"join_{how}", lambda c, how=how: joined(c, how=how), _J.format(_JALL, how.upper()), f"{G3}, {G4}")
grid_query("join_semi", lambda c: joined(c, how="left_semi"), _J.format("a.chunk, a.qty, a.disc, price_max", "SEMI"), f"{G3}, {G4}")
grid_query("join_anti", lambda c: joined(c, how="left_anti"), _J.format("a.chunk, a.qty, a.disc, price_max", "ANTI"), f"{G3}, {G4}")
grid_query("join_self", lambda c: g3(c, "disc = 0.01", ["chunk", "qty", "n_lines"]).alias("a").join(g3(c, "disc = 0.02", ["chunk", "qty", "n_lines"]).alias("b"), ["chunk", "qty"]).select("chunk", "qty", F.col("a.n_lines").alias("one"), F.col("b.n_lines").alias("two")), "SELECT a.chunk, a.qty, a.n_lines AS one, b.n_lines AS two FROM g3 a JOIN g3 b ON a.chunk = b.chunk AND a.qty = b.qty WHERE a.disc = 0.01 AND b.disc = 0.02")
add("join_theta", lambda c: c.table("region").join(c.table("nation"), F.col("n_regionkey") > F.col("r_regionkey")).select("r_name", "n_name"), "SELECT r_name, n_name FROM region JOIN nation ON n_regionkey > r_regionkey")
add("join_cross", lambda c: c.table("region").select("r_name").crossJoin(F.broadcast(c.table("nation").select("n_name"))), "SELECT r_name, n_name FROM region CROSS JOIN nation")
_BOXES = "SELECT CAST(range AS INTEGER) AS box_id, CAST(range * 4 % 40 AS INTEGER) AS qty_lo, CAST(range * 4 % 40 + 9 AS INTEGER) AS qty_hi, CAST(range % 7 AS INTEGER) AS disc_ix_lo, CAST(range % 7 + 3 AS INTEGER) AS disc_ix_hi FROM range(40)"


def some_boxes(c: Context) -> DataFrame:
    k = F.col("id").cast("int")
    return c.spark.range(40).select(k.alias("box_id"), (k * 4 % 40).alias("qty_lo"), (k * 4 % 40 + 9).alias("qty_hi"), (k % 7).alias("disc_ix_lo"), (k % 7 + 3).alias("disc_ix_hi"))


grid_query("join_range_box", lambda c: range_join(g3(c, None, ["chunk", "qty", "disc_ix", "n_lines"]), some_boxes(c), ["qty", "disc_ix"], 4).groupBy("box_id").agg(F.count("*").alias("cells"), F.sum("n_lines").alias("lines")), f", b AS ({_BOXES}) SELECT box_id, COUNT(*) AS cells, CAST(SUM(n_lines) AS BIGINT) AS lines FROM g3 JOIN b ON qty >= qty_lo AND qty < qty_hi AND disc_ix >= disc_ix_lo AND disc_ix < disc_ix_hi GROUP BY box_id")
add("join_box_overlap", lambda c: overlap_join(some_boxes(c), ["qty", "disc_ix"], 4), f"WITH b AS ({_BOXES}) SELECT x.box_id AS a, y.box_id AS b FROM b x JOIN b y ON x.box_id < y.box_id AND x.qty_lo < y.qty_hi AND y.qty_lo < x.qty_hi AND x.disc_ix_lo < y.disc_ix_hi AND y.disc_ix_lo < x.disc_ix_hi")


def asof(c: Context) -> DataFrame:
    e = c.table("events")
    clicks = e.where("event_type = 'click'").select("user_id", "ts", "event_id")
    buys = e.where("event_type = 'purchase'").select("user_id", "ts", F.col("event_id").alias("last_purchase"))
    # event ids ride along as the times are unique for a user
    return asof_join(clicks, buys, "ts", ["user_id"], "last_purchase").select("user_id", "last_purchase", F.date_format("ts", "yyyy-MM-dd HH:mm:ss").alias("at"))


add("join_asof", asof, "SELECT c.user_id, p.event_id AS last_purchase, strftime(c.ts, '%Y-%m-%d %H:%M:%S') AS at FROM (SELECT * FROM events WHERE event_type = 'click') c ASOF LEFT JOIN (SELECT * FROM events WHERE event_type = 'purchase') p ON c.user_id = p.user_id AND c.ts >= p.ts")

# --- aggregates ---------------------------------------------------------------------

grid_query("agg_mean", lambda c: c.grid("g4").scan(["level", "price_max"]).groupBy("level").agg((exact_sum("price_max") / F.count("*")).alias("mean")), f"SELECT level, {EXACT.format('price_max')} / COUNT(*) AS mean FROM g4 GROUP BY level", G4)
grid_query("agg_basic", lambda c: g3(c, None, ["qty", "n_lines", "price_max"]).groupBy("qty").agg(F.count("*").alias("n"), F.sum("n_lines").alias("lines"), F.min("price_max").alias("low"), F.max("price_max").alias("high")), "SELECT qty, COUNT(*) AS n, CAST(SUM(n_lines) AS BIGINT) AS lines, MIN(price_max) AS low, MAX(price_max) AS high FROM g3 GROUP BY qty")
grid_query("agg_count_if", lambda c: g3(c).groupBy("disc").agg(F.count_if(F.col("n_lines") > 1).alias("n")), "SELECT disc, COUNT(*) FILTER (WHERE n_lines > 1) AS n FROM g3 GROUP BY disc")
grid_query("agg_hist", lambda c: histogram(g3(c), F.col("qty"), 5, 12), ", h AS (SELECT LEAST(11, CAST(floor(qty / 5) AS INTEGER)) AS bin, COUNT(*) AS n FROM g3 GROUP BY 1) SELECT CAST(b.range AS INTEGER) AS bin, COALESCE(h.n, 0) AS n FROM range(12) b LEFT JOIN h ON h.bin = b.range")
add("agg_distinct", lambda c: c.table("lineitem").agg(F.countDistinct("l_partkey").alias("parts"), F.countDistinct("l_suppkey", "l_returnflag").alias("both")), "SELECT COUNT(DISTINCT l_partkey) AS parts, COUNT(DISTINCT (l_suppkey, l_returnflag)) AS both FROM lineitem")
add("agg_approx_distinct", lambda c: c.table("lineitem").agg(F.approx_count_distinct("l_partkey", 0.02).alias("parts")))
add("agg_percentile", lambda c: c.table("lineitem").groupBy("l_returnflag").agg(F.percentile("l_quantity", 0.5).alias("median"), F.percentile_approx("l_quantity", 0.9, 100000).alias("p90")), "SELECT l_returnflag, quantile_cont(l_quantity, 0.5) AS median, quantile_disc(l_quantity, 0.9) AS p90 FROM lineitem GROUP BY l_returnflag")
add("agg_stats", lambda c: c.table("lineitem").agg(F.round(F.var_samp("l_quantity"), 6).alias("v"), F.round(F.stddev_samp("l_quantity"), 6).alias("s"), F.round(F.corr("l_quantity", "l_extendedprice"), 6).alias("r")), "SELECT round(var_samp(l_quantity), 6) AS v, round(stddev_samp(l_quantity), 6) AS s, round(corr(l_quantity, l_extendedprice), 6) AS r FROM lineitem")
grid_query("agg_max_by", lambda c: g3(c).groupBy("chunk").agg(F.max(F.struct("price_sum", "qty", "disc")).alias("m")).select("chunk", "m.price_sum", "m.qty", "m.disc"), "SELECT chunk, price_sum, qty, disc FROM (SELECT *, row_number() OVER (PARTITION BY chunk ORDER BY price_sum DESC, qty DESC, disc DESC) AS k FROM g3) WHERE k = 1")
grid_query("agg_collect", lambda c: g3(c, "qty = 7").groupBy("chunk").agg(F.array_join(F.transform(F.sort_array(F.collect_list("disc_ix")), lambda x: x.cast("string")), ",").alias("discs")), "SELECT chunk, string_agg(CAST(disc_ix AS VARCHAR), ',' ORDER BY disc_ix) AS discs FROM g3 WHERE qty = 7 GROUP BY chunk")
_CUBE = "SELECT qty, disc, CAST(SUM(n_lines) AS BIGINT) AS n FROM g3 WHERE qty <= 5 GROUP BY {}"
grid_query("agg_rollup", lambda c: g3(c, "qty <= 5").rollup("qty", "disc").agg(F.sum("n_lines").alias("n")), _CUBE.format("ROLLUP (qty, disc)"))
grid_query("agg_cube", lambda c: g3(c, "qty <= 5").cube("qty", "disc").agg(F.sum("n_lines").alias("n")), _CUBE.format("CUBE (qty, disc)"))
grid_query("agg_grouping_sets", lambda c: g3(c, "qty <= 5").groupingSets([["qty"], ["disc"]], "qty", "disc").agg(F.sum("n_lines").alias("n")), _CUBE.format("GROUPING SETS ((qty), (disc))"))
add("agg_pivot", lambda c: c.table("lineitem").groupBy("l_returnflag").pivot("l_linestatus", ["F", "O"]).agg(F.count(F.lit(1))), "SELECT l_returnflag, NULLIF(COUNT(*) FILTER (WHERE l_linestatus = 'F'), 0) AS F, NULLIF(COUNT(*) FILTER (WHERE l_linestatus = 'O'), 0) AS O FROM lineitem GROUP BY l_returnflag")
grid_query("agg_unpivot", lambda c: g3(c, "qty = 9", ["chunk", "disc", "price_avg", "price_max"]).unpivot(["chunk", "disc"], ["price_avg", "price_max"], "variable", "value"), "SELECT chunk, disc, 'price_avg' AS variable, price_avg AS value FROM g3 WHERE qty = 9 UNION ALL SELECT chunk, disc, 'price_max', price_max FROM g3 WHERE qty = 9")
grid_query("agg_having", lambda c: g3(c).groupBy("chunk").agg(F.sum("n_lines").alias("n")).where("n > 50"), "SELECT chunk, CAST(SUM(n_lines) AS BIGINT) AS n FROM g3 GROUP BY chunk HAVING SUM(n_lines) > 50")

# --- windows ------------------------------------------------------------------------



def best_first() -> Window:
    return Window.partitionBy("chunk").orderBy(F.desc("price_sum"), "qty", "disc")


OVER = "OVER (PARTITION BY chunk ORDER BY price_sum DESC, qty, disc)"
grid_query("win_rank", lambda c: g3(c).select("chunk", "qty", "disc", F.row_number().over(best_first()).alias("rn"), F.rank().over(best_first()).alias("rk"), F.dense_rank().over(best_first()).alias("dr"), F.ntile(4).over(best_first()).alias("nt"), F.percent_rank().over(best_first()).alias("pr")).where("rn <= 5"), f"SELECT * FROM (SELECT chunk, qty, disc, CAST(row_number() {OVER} AS INTEGER) AS rn, CAST(rank() {OVER} AS INTEGER) AS rk, CAST(dense_rank() {OVER} AS INTEGER) AS dr, CAST(ntile(4) {OVER} AS INTEGER) AS nt, percent_rank() {OVER} AS pr FROM g3) WHERE rn <= 5")


def cell_time() -> Window:
    return Window.partitionBy("qty", "disc").orderBy("chunk")


CELL_OVER = "OVER (PARTITION BY qty, disc ORDER BY chunk{})"
grid_query("win_lag_gaps", lambda c: c.grid("ge").scan(["hour"]).distinct().select("hour", F.lag("hour").over(Window.partitionBy(F.date_format("hour", "yyyy-MM-dd")).orderBy("hour")).alias("prev")).where("timestampdiff(HOUR, prev, hour) > 1").select(F.date_format("hour", "yyyy-MM-dd HH").alias("hour"), F.date_format("prev", "yyyy-MM-dd HH").alias("prev")), "SELECT strftime(hour, '%Y-%m-%d %H') AS hour, strftime(prev, '%Y-%m-%d %H') AS prev FROM (SELECT hour, LAG(hour) OVER (PARTITION BY CAST(hour AS DATE) ORDER BY hour) AS prev FROM (SELECT DISTINCT hour FROM ge)) WHERE date_diff('hour', prev, hour) > 1", GE)
grid_query("win_running", lambda c: g3(c, "qty <= 3").select(*KEY, F.sum("n_lines").over(cell_time().rowsBetween(Window.unboundedPreceding, 0)).alias("n")), f"SELECT chunk, qty, disc, CAST(SUM(n_lines) {CELL_OVER.format(' ROWS UNBOUNDED PRECEDING')} AS BIGINT) AS n FROM g3 WHERE qty <= 3")
grid_query("win_moving", lambda c: g3(c, "qty <= 3").select(*KEY, F.avg("n_lines").over(cell_time().rowsBetween(-2, 0)).alias("mean")), f"SELECT chunk, qty, disc, AVG(n_lines) {CELL_OVER.format(' ROWS BETWEEN 2 PRECEDING AND CURRENT ROW')} AS mean FROM g3 WHERE qty <= 3")
grid_query("win_range", lambda c: g3(c, "disc = 0.03").select("chunk", "qty_ix", F.sum("n_lines").over(Window.partitionBy("chunk").orderBy("qty_ix").rangeBetween(-2, 2)).alias("n")), "SELECT chunk, qty_ix, CAST(SUM(n_lines) OVER (PARTITION BY chunk ORDER BY qty_ix RANGE BETWEEN 2 PRECEDING AND 2 FOLLOWING) AS BIGINT) AS n FROM g3 WHERE disc = 0.03")
grid_query("win_fill", lambda c: c.grid("g3").rows(include_fill=True).where("qty = 9").select(*KEY, F.last("n_lines", True).over(cell_time().rowsBetween(Window.unboundedPreceding, 0)).alias("n")), ", m AS (SELECT DISTINCT chunk FROM g3), d AS (SELECT range / 100 AS disc FROM range(11)), f AS (SELECT m.chunk, 9.0::DOUBLE AS qty, d.disc, g3.n_lines FROM m CROSS JOIN d LEFT JOIN g3 ON g3.chunk = m.chunk AND g3.disc = d.disc AND g3.qty = 9) SELECT chunk, qty, disc, last_value(n_lines IGNORE NULLS) OVER (PARTITION BY disc ORDER BY chunk ROWS UNBOUNDED PRECEDING) AS n FROM f")

# --- order, limits, sets ------------------------------------------------------------

ORDER = ["price_sum", "chunk", "qty", "disc"]
grid_query("sort_nulls", lambda c: c.grid("g3").rows(include_fill=True).where("qty = 50").select(*KEY, "n_lines").orderBy(F.col("n_lines").asc_nulls_last(), *KEY), ", m AS (SELECT DISTINCT chunk FROM g3), d AS (SELECT range / 100 AS disc FROM range(11)) SELECT m.chunk, 50.0::DOUBLE AS qty, d.disc, g3.n_lines FROM m CROSS JOIN d LEFT JOIN g3 ON g3.chunk = m.chunk AND g3.disc = d.disc AND g3.qty = 50 ORDER BY n_lines NULLS LAST, chunk, qty, disc")
grid_query("sort_limit_offset", lambda c: g3(c).orderBy(*ORDER).offset(20).limit(30), f"SELECT {CELLS} FROM g3 ORDER BY price_sum, chunk, qty, disc LIMIT 30 OFFSET 20")
grid_query("topk_global", lambda c: g3(c).orderBy(F.desc("price_sum"), *KEY).limit(25), f"SELECT {CELLS} FROM g3 ORDER BY price_sum DESC, chunk, qty, disc LIMIT 25")
grid_query("topk_per_chunk", lambda c: g3(c).withColumn("k", F.row_number().over(best_first())).where("k <= 3").drop("k"), f"SELECT {CELLS} FROM (SELECT *, row_number() {OVER} AS k FROM g3) WHERE k <= 3")
A, B = "qty <= 20", "qty >= 15 AND disc <= 0.05"
for name, run, word in (
    ("set_union_all", lambda a, b: a.unionByName(b), "UNION ALL"), ("set_union", lambda a, b: a.unionByName(b).distinct(), "UNION"), ("set_intersect", lambda a, b: a.intersect(b), "INTERSECT"),
    ("set_intersect_all", lambda a, b: a.intersectAll(b), "INTERSECT ALL"), ("set_except", lambda a, b: a.subtract(b), "EXCEPT"), ("set_except_all", lambda a, b: a.exceptAll(b), "EXCEPT ALL"),
):
    grid_query(name, lambda c, run=run: run(g3(c, A, ["qty", "disc"]), g3(c, B, ["qty", "disc"])), f"SELECT qty, disc FROM g3 WHERE {A} {word} SELECT qty, disc FROM g3 WHERE {B}")

# --- scalar functions ---------------------------------------------------------------

grid_query("fn_math", lambda c: g3(c).select(*KEY, F.round(F.sqrt("price_sum") + F.log(F.col("qty")) + F.pow(F.col("disc"), F.lit(2)) + F.exp(F.col("disc")), 6).alias("m"), F.floor("price_sum").alias("f"), F.ceil("price_sum").alias("c"), F.abs(F.col("qty") - 25).alias("a"), F.greatest("qty", "n_lines").alias("g"), F.least("qty", "n_lines").alias("l"), F.try_divide(F.col("price_sum"), F.col("disc")).alias("d")), "SELECT chunk, qty, disc, round(sqrt(price_sum) + ln(qty) + pow(disc, 2) + exp(disc), 6) AS m, CAST(floor(price_sum) AS BIGINT) AS f, CAST(ceil(price_sum) AS BIGINT) AS c, abs(qty - 25) AS a, GREATEST(qty, n_lines) AS g, LEAST(qty, n_lines) AS l, CASE WHEN disc = 0 THEN NULL ELSE price_sum / disc END AS d FROM g3")
add("fn_date", lambda c: c.table("lineitem").select(F.year("l_shipdate").alias("y"), F.month("l_shipdate").alias("m"), F.dayofyear("l_shipdate").alias("d"), F.datediff("l_shipdate", F.lit("1992-01-01").cast("date")).alias("n"), F.date_format(F.add_months("l_shipdate", 2), "yyyy-MM-dd").alias("later")).distinct(), "SELECT DISTINCT CAST(year(l_shipdate) AS INTEGER) AS y, CAST(month(l_shipdate) AS INTEGER) AS m, CAST(dayofyear(l_shipdate) AS INTEGER) AS d, CAST(date_diff('day', DATE '1992-01-01', CAST(l_shipdate AS DATE)) AS INTEGER) AS n, strftime(l_shipdate + INTERVAL 2 MONTH, '%Y-%m-%d') AS later FROM lineitem")
add("fn_interval", lambda c: c.table("events").select("event_id", F.date_format(F.col("ts") + F.make_dt_interval(hours=F.lit(36)), "yyyy-MM-dd HH:mm:ss").alias("later")), "SELECT event_id, strftime(ts + INTERVAL 36 HOUR, '%Y-%m-%d %H:%M:%S') AS later FROM events")
add("fn_string", lambda c: c.table("part").select("p_partkey", F.upper("p_name").alias("u"), F.substring("p_type", 1, 4).alias("s"), F.concat_ws("/", "p_brand", "p_type").alias("c"), F.length("p_name").alias("n"), F.regexp_extract("p_brand", "([0-9]+)", 1).alias("r"), F.replace(F.col("p_name"), F.lit("a"), F.lit("_")).alias("x"), F.trim(F.concat(F.lit(" "), "p_brand")).alias("t")), "SELECT p_partkey, upper(p_name) AS u, substr(p_type, 1, 4) AS s, concat_ws('/', p_brand, p_type) AS c, CAST(length(p_name) AS INTEGER) AS n, regexp_extract(p_brand, '([0-9]+)', 1) AS r, replace(p_name, 'a', '_') AS x, trim(' ' || p_brand) AS t FROM part")
add("fn_array", lambda c: c.table("embeddings").select("vec_id", F.element_at("embedding", 3).alias("third"), F.size(F.slice("embedding", 11, 5)).alias("n"), F.size(F.filter("embedding", lambda x: x > 0)).alias("pos"), F.array_max("embedding").alias("top"), F.exists("embedding", lambda x: x > 0.4).alias("big")), "SELECT vec_id, embedding[3] AS third, CAST(len(embedding[11:15]) AS INTEGER) AS n, CAST(len(list_filter(embedding, lambda x: x > 0)) AS INTEGER) AS pos, list_max(embedding) AS top, len(list_filter(embedding, lambda x: x > 0.4)) > 0 AS big FROM embeddings")
grid_query("fn_map", lambda c: g3(c, "qty = 5", ["chunk", "disc", "price_avg", "price_max"]).withColumn("m", F.create_map(F.lit("avg"), "price_avg", F.lit("max"), "price_max")).select("chunk", "disc", F.explode(F.transform_values("m", lambda k, v: v * 2)).alias("k", "v")), "SELECT chunk, disc, 'avg' AS k, price_avg * 2 AS v FROM g3 WHERE qty = 5 UNION ALL SELECT chunk, disc, 'max', price_max * 2 FROM g3 WHERE qty = 5")
add("fn_json", lambda c: c.table("events").select("event_id", F.get_json_object("props", "$.k").cast("int").alias("k"), (F.from_json("props", "k int")["k"] + 1).alias("k1")), "SELECT event_id, CAST(json_extract_string(props, '$.k') AS INTEGER) AS k, CAST(json_extract_string(props, '$.k') AS INTEGER) + 1 AS k1 FROM events")
grid_query("fn_struct", lambda c: g3(c, "qty = 6").select(F.struct(F.struct("qty", "disc").alias("at"), "n_lines").alias("s"), "chunk").select("chunk", "s.at.disc", "s.n_lines"), "SELECT chunk, disc, n_lines FROM g3 WHERE qty = 6")
grid_query("fn_conditional", lambda c: c.grid("g3").rows(include_fill=True).where("qty = 4").select(*KEY, F.coalesce("n_lines", F.lit(-1)).alias("n"), F.col("n_lines").isNull().alias("fill")), ", m AS (SELECT DISTINCT chunk FROM g3), d AS (SELECT range / 100 AS disc FROM range(11)) SELECT m.chunk, 4.0::DOUBLE AS qty, d.disc, COALESCE(g3.n_lines, -1) AS n, g3.n_lines IS NULL AS fill FROM m CROSS JOIN d LEFT JOIN g3 ON g3.chunk = m.chunk AND g3.disc = d.disc AND g3.qty = 4")
grid_query("fn_cast", lambda c: g3(c).select(*KEY, F.col("qty").cast("int").alias("q"), F.col("price_sum").cast("decimal(18,2)").cast("string").alias("p"), F.col("n_lines").cast("double").alias("n")), "SELECT chunk, qty, disc, CAST(qty AS INTEGER) AS q, CAST(CAST(price_sum AS DECIMAL(18,2)) AS VARCHAR) AS p, CAST(n_lines AS DOUBLE) AS n FROM g3")

# --- subqueries ---------------------------------------------------------------------


def over_cells(text: str):
    def build(c: Context) -> DataFrame:
        g3(c).createOrReplaceTempView("g3_cells")
        c.grid("g4").scan(["chunk", "qty", "disc", "level"]).createOrReplaceTempView("g4_cells")
        return c.spark.sql(text.replace("g3 ", "g3_cells ").replace("g4 ", "g4_cells "))

    return build


for name, text in {
    "sub_scalar": "SELECT chunk, qty, disc FROM g3 WHERE n_lines = (SELECT MAX(n_lines) FROM g3 )",
    "sub_in": "SELECT chunk, qty, disc FROM g3 WHERE qty IN (SELECT qty FROM g4 WHERE level = 0.08) AND disc NOT IN (SELECT disc FROM g4 WHERE level = 0.01 AND qty = 3)",
    "sub_exists": "SELECT chunk, qty, disc FROM g3 a WHERE EXISTS (SELECT 1 FROM g4 b WHERE b.chunk = a.chunk AND b.qty = a.qty AND b.level = 0.02) AND NOT EXISTS (SELECT 1 FROM g4 b WHERE b.chunk = a.chunk AND b.disc = a.disc AND b.qty = 50)",
}.items():
    grid_query(name, over_cells(text), text, f"{G3}, {G4}")
grid_query("cte_chain", over_cells("WITH a AS (SELECT chunk, SUM(n_lines) AS n FROM g3 GROUP BY chunk), b AS (SELECT MAX(n) AS top FROM a) SELECT chunk, n FROM a, b WHERE n * 2 > top"), ", a AS (SELECT chunk, CAST(SUM(n_lines) AS BIGINT) AS n FROM g3 GROUP BY chunk), b AS (SELECT MAX(n) AS top FROM a) SELECT chunk, n FROM a, b WHERE n * 2 > top")

# --- functions of the user ----------------------------------------------------------

_SPEED = "SELECT chunk, qty, disc, round(sqrt(price_avg * price_avg + price_max * price_max), 6) AS speed FROM g3 WHERE qty <= 10"
UV = [*KEY, "price_avg", "price_max"]


def with_speed(rows: DataFrame, column) -> DataFrame:
    return rows.select(*KEY, F.round(column, 6).alias("speed"))


grid_query("udf_scalar", lambda c: with_speed(g3(c, "qty <= 10", UV), F.udf(lambda u, v: (u * u + v * v) ** 0.5, "double")("price_avg", "price_max")), _SPEED)
grid_query("udf_native", lambda c: with_speed(g3(c, "qty <= 10", UV), speed(F.col("price_avg"), F.col("price_max"))), _SPEED)


def pandas_speed(c: Context) -> DataFrame:
    @F.pandas_udf("double")
    def fast(u: pd.Series, v: pd.Series) -> pd.Series:
        return (u * u + v * v) ** 0.5

    return with_speed(g3(c, "qty <= 10", UV), fast("price_avg", "price_max"))


grid_query("udf_pandas", pandas_speed, _SPEED)


def sql_speed(c: Context) -> DataFrame:
    c.spark.udf.register("total_speed", lambda u, v: (u * u + v * v) ** 0.5, "double")
    g3(c, "qty <= 10", UV).createOrReplaceTempView("g3_uv")
    return c.spark.sql("SELECT chunk, qty, disc, round(total_speed(price_avg, price_max), 6) AS speed FROM g3_uv")


grid_query("udf_sql", sql_speed, _SPEED)


def map_arrow(c: Context) -> DataFrame:
    def lens(batches):
        for b in batches:
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array([len([x for x in v if x is not None]) for v in b.column(1).to_pylist()], pa.int64())], ["chunk", "filled"])

    return c.grid("g3").tiles().select("chunk", "n_lines").mapInArrow(lens, "chunk string, filled long").groupBy("chunk").agg(F.sum("filled").alias("filled"))


grid_query("udf_map_arrow", map_arrow, "SELECT chunk, COUNT(*) AS filled FROM g3 GROUP BY chunk")


def grouped_cover(c: Context) -> DataFrame:
    def union(key, t: pd.DataFrame) -> pd.DataFrame:
        runs: list[list[int]] = []
        for q in sorted(set(t["qty_ix"])):
            if runs and runs[-1][1] == q:
                runs[-1][1] = q + 1
            else:
                runs.append([q, q + 1])
        return pd.DataFrame([(key[0], *map(int, r)) for r in runs], columns=["chunk", "lo", "hi"])

    return g3(c, "disc = 0.03", ["chunk", "qty_ix"]).groupBy("chunk").applyInPandas(union, "chunk string, lo int, hi int")


_RUNS = ", f AS (SELECT chunk, qty_ix, qty_ix - row_number() OVER (PARTITION BY chunk ORDER BY qty_ix) AS k FROM g3 WHERE disc = 0.03) SELECT chunk, MIN(qty_ix) AS lo, MAX(qty_ix) + 1 AS hi FROM f GROUP BY chunk, k"
grid_query("udf_grouped", grouped_cover, _RUNS)
grid_query("islands_per_chunk", lambda c: islands(g3(c, "disc = 0.03", ["chunk", "qty_ix"]).select("chunk", F.col("qty_ix").alias("lo"), (F.col("qty_ix") + 1).alias("hi")), "lo", "hi", ["chunk"]), _RUNS)


def cogrouped(c: Context) -> DataFrame:
    def both(key, a: pd.DataFrame, b: pd.DataFrame) -> pd.DataFrame:
        m = a.merge(b, on=["chunk", "qty"])
        return pd.DataFrame({"chunk": [key[0]], "pairs": [len(m)]})

    one, two = (g3(c, f"disc = {d}", ["chunk", "qty"]) for d in (0.01, 0.02))
    return one.groupBy("chunk").cogroup(two.groupBy("chunk")).applyInPandas(both, "chunk string, pairs long")


grid_query("udf_cogroup", cogrouped, ", k AS (SELECT DISTINCT chunk FROM g3 WHERE disc IN (0.01, 0.02)), p AS (SELECT a.chunk, COUNT(*) AS n FROM g3 a JOIN g3 b ON a.chunk = b.chunk AND a.qty = b.qty WHERE a.disc = 0.01 AND b.disc = 0.02 GROUP BY a.chunk) SELECT k.chunk, COALESCE(p.n, 0) AS pairs FROM k LEFT JOIN p ON p.chunk = k.chunk")


def pandas_total(c: Context) -> DataFrame:
    @F.pandas_udf("long")
    def total(v: pd.Series) -> int:
        return int(v.sum())

    return g3(c).groupBy("qty").agg(total("n_lines").alias("n"))


grid_query("udaf_pandas", pandas_total, "SELECT qty, CAST(SUM(n_lines) AS BIGINT) AS n FROM g3 GROUP BY qty")


def table_function(c: Context) -> DataFrame:
    @F.udtf(returnType="i int, j int")
    class BoxCells:
        """Positions of a box."""

        def eval(self, o1: int, o2: int, n1: int, n2: int):
            for i in range(o1, o1 + n1):
                for j in range(o2, o2 + n2):
                    yield i, j

    return BoxCells(F.lit(3), F.lit(5), F.lit(4), F.lit(6))


add("udtf_cells", table_function, "SELECT CAST(i.range AS INTEGER) AS i, CAST(j.range AS INTEGER) AS j FROM range(3, 7) i CROSS JOIN range(5, 11) j")

# --- streams ------------------------------------------------------------------------


def stream(c: Context) -> DataFrame:
    return st.events(c.spark, f"{c.sf}/events.parquet")


def clock(rows: DataFrame, column: str = "start") -> DataFrame:
    return rows.withColumn(column, F.date_format(column, "yyyy-MM-dd HH:mm:ss"))


add("st_append_chunks", lambda c: st.append_chunks(c.spark, f"{c.sf}/events.parquet", f"{shared_dir(c.spark)}/gridlake-append-{abs(hash(c.sf))}").groupBy(F.col("chunk_key").cast("string").alias("chunk")).agg(F.count("*").alias("n")), "SELECT strftime(ts, '%Y-%m-%d') AS chunk, COUNT(*) AS n FROM events GROUP BY 1")
add("st_tumbling", lambda c: clock(st.drained(st.tumbling(stream(c)), "complete")), "SELECT strftime(date_trunc('hour', ts), '%Y-%m-%d %H:%M:%S') AS start, event_type, COUNT(*) AS n FROM events GROUP BY 1, 2")
add("st_sliding", lambda c: clock(st.drained(st.sliding(stream(c)), "complete")), "WITH w AS (SELECT date_trunc('hour', ts) - to_hours(k.range) AS start FROM events CROSS JOIN range(2) k) SELECT strftime(start, '%Y-%m-%d %H:%M:%S') AS start, COUNT(*) AS n FROM w GROUP BY start")
add("st_session", lambda c: clock(st.drained(st.sessions(stream(c)), "complete")), "WITH f AS (SELECT user_id, ts, CASE WHEN ts < LAG(ts) OVER (PARTITION BY user_id ORDER BY ts) + INTERVAL 30 MINUTE THEN 0 ELSE 1 END AS new FROM events), g AS (SELECT *, SUM(new) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS k FROM f) SELECT user_id, strftime(MIN(ts), '%Y-%m-%d %H:%M:%S') AS start, COUNT(*) AS n FROM g GROUP BY user_id, k")
add("st_dedup", lambda c: st.drained(st.deduplicated(stream(c))).select("user_id", "event_type"), "SELECT DISTINCT user_id, event_type FROM events")
add("st_interval_join", lambda c: st.drained(st.interval_join(stream(c), stream(c))), "SELECT a.event_id AS click_id, b.event_id AS purchase_id FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts >= a.ts AND b.ts <= a.ts + INTERVAL 10 MINUTE WHERE a.event_type = 'click' AND b.event_type = 'purchase'")
add("st_state_bounds", lambda c: st.drained(st.state_bounds(stream(c)), "update", ("chunk",)), "SELECT strftime(ts, '%Y-%m-%d') AS chunk, MIN(value) AS value_lo, MAX(value) AS value_hi FROM events GROUP BY 1")


def stream_envelope(c: Context) -> DataFrame:
    """A stream joined with a table, cut to the table's bounds before the join."""
    users = c.table("events").where("value > 90").groupBy("user_id").agg(F.count("*").alias("high"))
    lo, hi = users.agg(F.min("user_id"), F.max("user_id")).first()
    return st.drained(stream(c).where(F.col("user_id").between(lo, hi)).join(users, "user_id").select("event_id", "high"))


add("st_envelope_join", stream_envelope, "SELECT event_id, u.high FROM events JOIN (SELECT user_id, COUNT(*) AS high FROM events WHERE value > 90 GROUP BY user_id) u USING (user_id)")
