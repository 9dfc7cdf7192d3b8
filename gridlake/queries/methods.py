"""The methods and their variants, the baselines and the measures."""

from __future__ import annotations

from itertools import cycle, product

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from gridlake.functions.science import decode_time, rh_ice, speed
from gridlake.model import ScanOptions, after, axis_span, axis_spans_in, before
from gridlake.operators import baselines as bl
from gridlake.operators import boxes as bx
from gridlake.operators import measures as ms
from gridlake.operators.cover_df import cover_df, islands
from gridlake.operators.envelope import envelope, envelope_bounds, envelope_join
from gridlake.plans.catalog import Catalog
from gridlake.plans.scan import register_grid
from gridlake.queries.registry import G3, G4, GE, GP, GU, Context, add, query
from gridlake.sources.derived import money

Q1 = "ship_month > '1997-01-01 00:15' AND qty > 20.2 AND qty < 35.5"
Q1_SQL = "ship_month > TIMESTAMP '1997-01-01 00:15:00' AND qty > 20.2 AND qty < 35.5"
Q2 = "qty >= 20 AND NOT (disc = 0.05 AND qty BETWEEN 30 AND 33)"
REGIONS = "nation BETWEEN 2 AND 6 OR nation BETWEEN 14 AND 20"
OVERLAPPING = "(qty BETWEEN 10 AND 30 AND disc <= 0.05) OR (qty BETWEEN 20 AND 40 AND disc >= 0.03) OR qty = 25"
CELL = ["chunk", "qty", "qty_ix", "disc", "disc_ix", "n_lines", "price_sum"]
CELLS = ", ".join(CELL)
EXACT = "CAST(SUM(CAST({0} AS DECIMAL(18,2))) AS DOUBLE)"


def exact_sum(column: str):
    return F.sum(F.col(column).cast("decimal(18,2)")).cast("double")


def pairs(c: Context, rows: list[tuple], schema: str) -> DataFrame:
    return c.spark.createDataFrame(rows, schema)


# --- registration, schema, row view -------------------------------------------------


@query("register_rows", f"WITH {G3} SELECT COUNT(*) AS n, CAST(SUM(n_lines) AS BIGINT) AS lines FROM g3")
def register_rows(c: Context) -> DataFrame:
    register_grid(c.spark, "g3_view", c.grid("g3").spec.path, {"ship_month": True})
    return c.spark.sql("SELECT COUNT(*) AS n, SUM(n_lines) AS lines FROM g3_view")


def catalog(c: Context, *names: str) -> Catalog:
    known = Catalog(c.spark)
    for n in names:
        known.register(n, c.grid(n))
    return known


# plain SQL on registered grids: comparisons, OR, a join whose filters reach both sides, a
# subquery, the same grid twice
for name, text in {
    "register_sql": "SELECT chunk, CAST(SUM(n_lines) AS BIGINT) AS n FROM g3 WHERE ship_month > {t}'1997-05-02' AND (qty <= 10 OR disc = 0.1) GROUP BY chunk",
    "register_join": "SELECT g4.chunk, g4.level, g4.qty, g4.disc, g3.price_avg AS surface, g4.price_avg AS inside FROM g3 JOIN g4 ON g3.ship_month = g4.ship_month AND g3.qty = g4.qty AND g3.disc = g4.disc WHERE g3.ship_month >= {t}'1998-01-01' AND g3.ship_month <= {t}'1998-06-01' AND g3.qty BETWEEN 20 AND 30",
    "register_subquery": "SELECT chunk, qty, disc, n_lines FROM g3 WHERE qty > 44 AND ship_month IN (SELECT ship_month FROM g4 WHERE level = 0.03 AND qty < 3 AND ship_month < {t}'1993-01-01')",
    "register_self": "SELECT a.chunk, a.qty, a.disc, b.n_lines FROM g3 a JOIN g3 b ON a.chunk = b.chunk AND a.disc = b.disc AND a.qty = b.qty + 40 WHERE a.qty > 47 AND b.disc NOT IN (0.02, 0.05)",
}.items():
    add(name, lambda c, text=text: catalog(c, "g3", "g4").sql(text.replace("{t}", "TIMESTAMP_NTZ ")), f"WITH {G3}, {G4} {text.replace('{t}', 'TIMESTAMP ')}")


@query("register_reads", "SELECT * FROM (VALUES ('files', true), ('bytes', true), ('rows', true)) t(metric, fewer)")
def register_reads(c: Context) -> DataFrame:
    """Files, bytes and rows that registered SQL reads, against the same without pruning."""
    known, text = catalog(c, "g3"), "SELECT chunk, price_sum FROM g3 WHERE qty <= 10 AND ship_month > TIMESTAMP_NTZ '1998-01-01'"
    ours, whole = ms.scan_metrics(known.sql(text)), ms.scan_metrics(known.sql(text, ScanOptions(prune_rows=False, prune_columns=False)))
    return pairs(c, [(n, ours[k] < whole[k]) for n, k in (("files", "numFiles"), ("bytes", "filesSize"), ("rows", "numOutputRows"))], "metric string, fewer boolean")


@query(
    "infer_schema",
    "SELECT * FROM (VALUES ('ship_month', 'timestamp_ntz', 'spanning'), ('qty', 'double', 'axis'), ('disc', 'double', 'axis'), ('n_lines', 'bigint', 'variable'), ('price_sum', 'double', 'variable'), ('price_avg', 'double', 'variable'), ('price_max', 'double', 'variable'), ('tax_avg', 'double', 'variable'), ('n_returned', 'bigint', 'variable')) AS t(name, type, role)",
)
def infer_schema(c: Context) -> DataFrame:
    spec = c.grid("g3").spec
    return pairs(c, [(a.name, a.dtype, "spanning" if a.spans else "axis") for a in spec.axes] + [(*v, "variable") for v in spec.variables], "name string, type string, role string")


add("g3_rows", lambda c: c.grid("g3").rows().drop("ship_month"), f"WITH {G3} SELECT * EXCLUDE (ship_month) FROM g3")
add("g4_rows", lambda c: c.grid("g4").rows().drop("ship_month"), f"WITH {G4} SELECT * EXCLUDE (ship_month) FROM g4")
add("gp_rows", lambda c: c.grid("gp").rows().drop("order_month"), f"WITH {GP} SELECT * EXCLUDE (order_month) FROM gp")


def user_groups(cells: DataFrame) -> DataFrame:
    """Cells of the event grid put together by the last two digits of the user, as the SQL's ge has them."""
    return cells.withColumn("user", F.col("user") % 100).groupBy("chunk", "hour", "user", F.col("user").cast("int").alias("user_ix"), "etype", "etype_ix").agg(F.sum("n_events").alias("n_events"), money("value_sum").alias("value_sum"), F.max("value_max").alias("value_max"))


def hours_of(cells: DataFrame) -> DataFrame:
    return cells.withColumn("hour", F.date_format("hour", "yyyy-MM-dd HH"))


add("ge_user_rows", lambda c: hours_of(c.grid("ge").rows()), f"WITH {GU} SELECT * REPLACE (strftime(hour, '%Y-%m-%d %H') AS hour) FROM gu")
add("ge_rows", lambda c: hours_of(user_groups(c.grid("ge").rows())), f"WITH {GE} SELECT * REPLACE (strftime(hour, '%Y-%m-%d %H') AS hour) FROM ge")
GV = "SELECT vec_id, CAST(generate_subscripts(embedding, 1) - 1 AS INTEGER) AS comp_ix, CAST(unnest(embedding) AS DOUBLE) AS x FROM embeddings"
add("gv_rows", lambda c: c.grid("gv").rows().select("vec_id", "comp_ix", F.col("x").cast("double").alias("x")), GV)
add(
    "g3_fill_rows",
    lambda c: c.grid("g3").rows(include_fill=True).select("chunk", "qty", "disc", "n_lines"),
    f"WITH {G3}, m AS (SELECT DISTINCT chunk FROM g3), q AS (SELECT CAST(range AS DOUBLE) AS qty FROM range(1, 51)), d AS (SELECT range / 100 AS disc FROM range(0, 11)) SELECT m.chunk, q.qty, d.disc, g3.n_lines FROM m CROSS JOIN q CROSS JOIN d LEFT JOIN g3 ON g3.chunk = m.chunk AND g3.qty = q.qty AND g3.disc = d.disc",
)
add(
    "time_decode",
    lambda c: c.table("events").select("event_id", F.date_format(decode_time(F.floor(F.unix_seconds(F.col("ts").cast("timestamp")) / 3600) - 473352, "hours", "2024-01-01 00:00:00"), "yyyy-MM-dd HH:mm:ss").alias("at")),
    "SELECT event_id, strftime(date_trunc('hour', ts), '%Y-%m-%d %H:%M:%S') AS at FROM events",
)
add("ix_predicate", lambda c: c.grid("g3").scan(CELL, "qty_ix >= 10 AND qty_ix < 15 AND disc_ix IN (1, 2, 9)"), f"WITH {G3} SELECT {CELLS} FROM g3 WHERE qty_ix >= 10 AND qty_ix < 15 AND disc_ix IN (1, 2, 9)")

# --- lookups ------------------------------------------------------------------------

add(
    "lookup_vec",
    lambda c: c.grid("gv").scan(["vec_id", "comp_ix", "x"], "comp_ix >= 10 AND comp_ix < 15").withColumn("x", F.col("x").cast("double")),
    f"SELECT * FROM ({GV}) WHERE comp_ix >= 10 AND comp_ix < 15",
)
add("lookup_rows_read", lambda c: pairs(c, [(ms.scan_metrics(c.grid("g3").lookup("1997-03", "n_lines", [0, 15, 2], [1, 5, 4]))["numFiles"],)], "files long"), "SELECT CAST(1 AS BIGINT) AS files")
add("lookup_g3", lambda c: c.grid("g3").lookup("1997-03", "n_lines", [0, 15, 2], [1, 5, 4]), f"WITH {G3}, a AS (SELECT q.range AS qty_ix, d.range AS disc_ix FROM range(15, 20) q CROSS JOIN range(2, 6) d) SELECT CAST(a.qty_ix AS INTEGER) AS qty_ix, CAST(a.disc_ix AS INTEGER) AS disc_ix, g3.n_lines AS value FROM a LEFT JOIN g3 ON g3.chunk = '1997-03' AND g3.qty_ix = a.qty_ix AND g3.disc_ix = a.disc_ix")

# --- pruning ------------------------------------------------------------------------

SIX = ("price_max", "n_lines", "price_sum", "part_min", "supp_cnt", "price_avg")


def means(columns: tuple[str, ...], sql: bool):
    """Means whose sums don't depend on the order of the rows."""
    if sql:
        return ", ".join(f"round(AVG({v}), 4) AS {v}" if v == "price_avg" else f"{EXACT.format(v)} / COUNT(*) AS {v}" for v in columns)
    return [F.round(F.avg(v), 4).alias(v) if v == "price_avg" else (exact_sum(v) / F.count("*")).alias(v) for v in columns]


for k in range(1, 7):
    add(f"vertical_{k}", lambda c, k=k: c.grid("g4").scan(list(SIX[:k])).agg(*means(SIX[:k], False)), f"WITH {G4} SELECT {means(SIX[:k], True)} FROM g4")
for name, test in {"low": "qty <= 10", "mid": "qty > 20.2 AND qty < 35.5", "beyond": "qty > 60", "between": "qty > 20.2 AND qty < 20.8", "all": "qty > 0"}.items():
    add(f"horizontal_{name}", lambda c, test=test: c.grid("g3").scan(CELL, test), f"WITH {G3} SELECT {CELLS} FROM g3 WHERE {test}")
for name, test in {
    "in": "qty IN (3, 4, 5, 20, 77)",
    "not_in": "disc NOT IN (0.02, 0.05, 0.5)",
    "mixed": "NOT (qty IN (1, 2) OR disc >= 0.09) AND (qty < 5 OR qty > 45 OR NOT disc <> 0.03)",
    "left_literal": "20 <= qty AND 0.05 > disc AND qty <> 30",
}.items():
    add(f"pred_{name}", lambda c, test=test: c.grid("g3").scan(CELL, test), f"WITH {G3} SELECT {CELLS} FROM g3 WHERE {test}")
add("pred_with_variable", lambda c: c.grid("g3").scan(CELL, "(qty > 40 OR n_lines >= 3) AND NOT price_sum < 1000"), f"WITH {G3} SELECT {CELLS} FROM g3 WHERE (qty > 40 OR n_lines >= 3) AND NOT price_sum < 1000")


#: Axes from data: the days on which each supplier's lines were shipped.
_DAYS = "WITH d AS (SELECT DISTINCT l_suppkey AS supp, CAST(date_diff('day', DATE '1992-01-01', CAST(l_shipdate AS DATE)) AS INTEGER) AS v FROM lineitem WHERE l_suppkey IS NOT NULL AND l_shipdate IS NOT NULL), a AS (SELECT supp, v, row_number() OVER (PARTITION BY supp ORDER BY v{0}) - 1 AS ix FROM d)"
_PROBE = _DAYS + ", s AS (SELECT DISTINCT supp FROM d) SELECT s.supp, CAST(k AS INTEGER) AS k, CAST(COALESCE(MIN(ix), 0) AS INTEGER) AS start, CAST(COALESCE(MAX(ix) + 1, 0) AS INTEGER) AS stop FROM s CROSS JOIN (VALUES (0, 90.0, 163.0), (1, 20.25, 60.5), (2, 5000.0, 6000.0), (3, 10.1, 10.2), (4, 1000.5, 2000.0)) p(k, lo, hi) LEFT JOIN a ON a.supp = s.supp AND v > lo AND v < hi GROUP BY s.supp, k"
PROBES = [(90.0, 163.0), (20.25, 60.5), (5000.0, 6000.0), (10.1, 10.2), (1000.5, 2000.0)]
SOME_DAYS = [900, 901, 902, 903, 905, 1234, 1235.5, 9999]


def day_axes(c: Context, search, schema: str, ascending: bool) -> DataFrame:
    """What a search of each supplier's axis gives, worked out where the axis is."""
    day = F.datediff("l_shipdate", F.lit("1992-01-01").cast("date"))
    days = c.table("lineitem").select(F.col("l_suppkey").alias("supp"), day.alias("day")).where("supp IS NOT NULL AND day IS NOT NULL")
    axes = days.groupBy("supp").agg(F.sort_array(F.collect_set("day"), ascending).alias("days"))
    return axes.select("supp", F.inline(F.udf(search, f"array<struct<{schema}>>")("days")))


def axis_probes(c: Context, ascending: bool) -> DataFrame:
    def search(days):
        return [(k, *axis_span(days, after(lo), before(hi))) for k, (lo, hi) in enumerate(PROBES)]

    return day_axes(c, search, "k: int, start: int, stop: int", ascending)


def axis_items(c: Context) -> DataFrame:
    def search(days):
        return axis_spans_in(days, SOME_DAYS)

    return day_axes(c, search, "start: int, stop: int", False)


add("axis_span_asc", lambda c: axis_probes(c, True), _PROBE.format(""))
add("axis_span_desc", lambda c: axis_probes(c, False), _PROBE.format(" DESC"))
add(
    "axis_spans_in",
    axis_items,
    _DAYS.format(" DESC") + f", h AS (SELECT supp, ix, ix - row_number() OVER (PARTITION BY supp ORDER BY ix) AS run FROM a WHERE v IN ({', '.join(map(str, SOME_DAYS))})) SELECT supp, CAST(MIN(ix) AS INTEGER) AS start, CAST(MAX(ix) + 1 AS INTEGER) AS stop FROM h GROUP BY supp, run",
)

# --- convex queries -----------------------------------------------------------------

add("q_convex", lambda c: c.grid("g3").scan(CELL, Q1), f"WITH {G3} SELECT {CELLS} FROM g3 WHERE {Q1_SQL}")


@query("q_convex_global", "SELECT 'qty' AS axis, 15 AS start, 30 AS stop UNION ALL SELECT 'disc', 0, 11")
def q_convex_global(c: Context) -> DataFrame:
    grid = c.grid("g3")
    plan = grid.plan(Q1)
    return pairs(c, [(a.name, *r) for b in plan.boxes for a, r in zip(grid.spec.axes, b, strict=True) if not a.spans], "axis string, start int, stop int")


_MONTHS = f"WITH {G3}, m AS (SELECT DISTINCT chunk, ship_month FROM g3)"


@query("q_convex_local", f"{_MONTHS} SELECT chunk, 0 AS ship_month_start, 1 AS ship_month_stop, 15 AS qty_start, 30 AS qty_stop FROM m WHERE ship_month > TIMESTAMP '1997-01-01 00:15:00'")
def q_convex_local(c: Context) -> DataFrame:
    grid = c.grid("g3")
    return grid.local_boxes(grid.plan(Q1)).select("chunk", "ship_month_start", "ship_month_stop", "qty_start", "qty_stop")


HOURS = "hour >= '2024-01-05 06:30' AND hour < '2024-01-06 15:00' AND etype <= 2"


@query("local_partial_chunk", f"WITH {GE} SELECT chunk, strftime(hour, '%Y-%m-%d %H') AS hour, \"user\", etype, n_events FROM ge WHERE hour >= TIMESTAMP '2024-01-05 06:30:00' AND hour < TIMESTAMP '2024-01-06 15:00:00' AND etype <= 2")
def local_partial_chunk(c: Context) -> DataFrame:
    cells = c.grid("ge").scan(["chunk", "hour", "user", "etype", "n_events"], HOURS)
    return hours_of(cells.groupBy("chunk", "hour", (F.col("user") % 100).alias("user"), "etype").agg(F.sum("n_events").alias("n_events")))


add(
    "local_partial_users",
    lambda c: hours_of(c.grid("ge").scan(["chunk", "hour", "user", "etype", "n_events"], HOURS + " AND user > 20")),
    f"WITH {GU} SELECT chunk, strftime(hour, '%Y-%m-%d %H') AS hour, \"user\", etype, n_events FROM gu WHERE hour >= TIMESTAMP '2024-01-05 06:30:00' AND hour < TIMESTAMP '2024-01-06 15:00:00' AND etype <= 2 AND \"user\" > 20",
)


add("chunks_touched", lambda c: (lambda g: g.local_boxes(g.plan(Q1)).select("chunk").distinct())(c.grid("g3")), f"{_MONTHS} SELECT chunk FROM m WHERE ship_month > TIMESTAMP '1997-01-01 00:15:00'")


@query("lookups_of_q1", f"{_MONTHS} SELECT chunk, 0 AS o0, 15 AS o1, 0 AS o2, 1 AS n0, 15 AS n1, 11 AS n2 FROM m WHERE ship_month > TIMESTAMP '1997-01-01 00:15:00'")
def lookups_of_q1(c: Context) -> DataFrame:
    grid = c.grid("g3")
    return grid.lookups(grid.plan(Q1)).select("chunk", *[F.col("origin")[k].alias(f"o{k}") for k in range(3)], *[F.col("length")[k].alias(f"n{k}") for k in range(3)])


@query("split_lookups", "SELECT CAST(range AS INTEGER) AS piece, CAST(119 + range * 50 AS INTEGER) AS lat_start, CAST(LEAST(119 + range * 50 + 50, 280) AS INTEGER) AS lat_stop, CAST((LEAST(119 + range * 50 + 50, 280) - 119 - range * 50) * 1440 AS BIGINT) AS cells FROM range(4)")
def split(c: Context) -> DataFrame:
    pieces = bx.split_lookups(((0, 1), (119, 280), (0, 1440)), 8, 8 * 1440 * 50)
    return pairs(c, [(k, *b[1], bx.volume(b)) for k, b in enumerate(pieces)], "piece int, lat_start int, lat_stop int, cells long")


# --- non-convex queries -------------------------------------------------------------

for name, test in {
    "q_nonconvex": Q2,
    "q_nonconvex_dnf": "(qty < 10 OR disc > 0.07) AND (qty > 3 OR disc < 0.02) AND (qty <> 5 OR disc <> 0.08)",
    "nnf_eval": "NOT (NOT (qty > 10 AND disc < 0.08) OR NOT (qty <= 40 OR disc = 0.01))",
    "neq_axis": "qty <> 25 AND disc <> 0.05",
    "tighten_redundant": "qty >= 20 AND qty > 30 AND qty < 50 AND qty <= 44 AND disc >= 0.02 AND disc > 0.01",
    "tighten_empty": "qty > 30 AND qty < 20",
    "q_overlap_regions": OVERLAPPING,
}.items():
    add(name, lambda c, test=test: c.grid("g3").scan(CELL, test), f"WITH {G3} SELECT {CELLS} FROM g3 WHERE {test}")
add("q_nonconvex_grid", lambda c: c.grid("g3").scan(CELL, Q2, ScanOptions(cover="grid", residual=False)), f"WITH {G3} SELECT {CELLS} FROM g3 WHERE {Q2}")
add("q_nonconvex_many", lambda c: c.grid("g3").scan(CELL, OVERLAPPING, ScanOptions(inline_boxes=0, residual=False)), f"WITH {G3} SELECT {CELLS} FROM g3 WHERE {OVERLAPPING}")
add("q_guarded", lambda c: c.grid("g3").scan(CELL, OVERLAPPING, ScanOptions(max_clauses=1)), f"WITH {G3} SELECT {CELLS} FROM g3 WHERE {OVERLAPPING}")
add("q_two_regions", lambda c: c.grid("gp").scan(["chunk", "nation", "prio", "n_orders", "price_max"], REGIONS), f"WITH {GP} SELECT chunk, nation, prio, n_orders, price_max FROM gp WHERE {REGIONS}")

# --- covers -------------------------------------------------------------------------

_ROW = "18 * (i // 2) + 8 * (i % 2)"
BOXES_SQL = {  # of axes 0 and 1, for i in range(n)
    "aligned": (f"{_ROW}", f"{_ROW} + 10", "0", "10"),
    "misaligned": (f"{_ROW}", f"{_ROW} + 10", "5 * (i % 2)", "5 * (i % 2) + 10"),
    "diagonal": ("CASE WHEN i = 0 THEN 0 ELSE 4 * (i - 1) + 1 END", "CASE WHEN i = 0 THEN 4 * {n} ELSE 4 * (i - 1) + 3 END") * 2,
    "centred": ("-2 * (i + 1)", "2 * (i + 1)", "-2 * ({n} - i)", "2 * ({n} - i)"),
}


def cover_sql(boxes: str) -> str:
    """Two-dimensional covers in SQL: elementary cells, then islands along axis 1 and axis 0."""
    return f"""WITH b AS ({boxes}),
c0 AS (SELECT x AS a, LEAD(x) OVER (ORDER BY x) AS z FROM (SELECT lo0 AS x FROM b UNION SELECT hi0 FROM b)),
c1 AS (SELECT x AS a, LEAD(x) OVER (ORDER BY x) AS z FROM (SELECT lo1 AS x FROM b UNION SELECT hi1 FROM b)),
e AS (SELECT DISTINCT c0.a AS lo0, c0.z AS hi0, c1.a AS lo1, c1.z AS hi1 FROM b JOIN c0 ON c0.a >= b.lo0 AND c0.z <= b.hi0 JOIN c1 ON c1.a >= b.lo1 AND c1.z <= b.hi1),
f AS (SELECT *, CASE WHEN LAG(hi1) OVER (PARTITION BY lo0, hi0 ORDER BY lo1) = lo1 THEN 0 ELSE 1 END AS new FROM e),
g AS (SELECT *, SUM(new) OVER (PARTITION BY lo0, hi0 ORDER BY lo1) AS run FROM f),
h AS (SELECT lo0, hi0, MIN(lo1) AS lo1, MAX(hi1) AS hi1 FROM g GROUP BY lo0, hi0, run),
i AS (SELECT *, CASE WHEN LAG(hi0) OVER (PARTITION BY lo1, hi1 ORDER BY lo0) = lo0 THEN 0 ELSE 1 END AS new FROM h),
j AS (SELECT *, SUM(new) OVER (PARTITION BY lo1, hi1 ORDER BY lo0) AS run FROM i)
SELECT CAST(MIN(lo0) AS INTEGER) AS a0_lo, CAST(MAX(hi0) AS INTEGER) AS a0_hi, CAST(lo1 AS INTEGER) AS a1_lo, CAST(hi1 AS INTEGER) AS a1_hi FROM j GROUP BY lo1, hi1, run"""


BOX = "a0_lo int, a0_hi int, a1_lo int, a1_hi int"
for kind, (lo0, hi0, lo1, hi1) in BOXES_SQL.items():
    n = 16
    boxes_sql = f"SELECT {lo0} AS lo0, {hi0} AS hi0, {lo1} AS lo1, {hi1} AS hi1 FROM (SELECT range AS i FROM range({n}))".replace("{n}", str(n))
    add(f"cover_sweep_{kind}", lambda c, kind=kind, n=n: pairs(c, [b[0] + b[1] for b in bx.cover_sweep(bx.WORKLOADS[kind](n, 2)).boxes], BOX), cover_sql(boxes_sql))


def covers_sql(boxes: str) -> str:
    """The same for each ``grp`` of the boxes."""
    return f"""WITH b AS ({boxes}),
c0 AS (SELECT grp, x AS a, LEAD(x) OVER (PARTITION BY grp ORDER BY x) AS z FROM (SELECT grp, lo0 AS x FROM b UNION SELECT grp, hi0 FROM b)),
c1 AS (SELECT grp, x AS a, LEAD(x) OVER (PARTITION BY grp ORDER BY x) AS z FROM (SELECT grp, lo1 AS x FROM b UNION SELECT grp, hi1 FROM b)),
e AS (SELECT DISTINCT b.grp, c0.a AS lo0, c0.z AS hi0, c1.a AS lo1, c1.z AS hi1 FROM b JOIN c0 ON c0.grp = b.grp AND c0.a >= b.lo0 AND c0.z <= b.hi0 JOIN c1 ON c1.grp = b.grp AND c1.a >= b.lo1 AND c1.z <= b.hi1),
f AS (SELECT *, CASE WHEN LAG(hi1) OVER (PARTITION BY grp, lo0, hi0 ORDER BY lo1) = lo1 THEN 0 ELSE 1 END AS new FROM e),
g AS (SELECT *, SUM(new) OVER (PARTITION BY grp, lo0, hi0 ORDER BY lo1) AS run FROM f),
h AS (SELECT grp, lo0, hi0, MIN(lo1) AS lo1, MAX(hi1) AS hi1 FROM g GROUP BY grp, lo0, hi0, run),
i AS (SELECT *, CASE WHEN LAG(hi0) OVER (PARTITION BY grp, lo1, hi1 ORDER BY lo0) = lo0 THEN 0 ELSE 1 END AS new FROM h),
j AS (SELECT *, SUM(new) OVER (PARTITION BY grp, lo1, hi1 ORDER BY lo0) AS run FROM i)
SELECT grp, CAST(MIN(lo0) AS INTEGER) AS a0_lo, CAST(MAX(hi0) AS INTEGER) AS a0_hi, CAST(lo1 AS INTEGER) AS a1_lo, CAST(hi1 AS INTEGER) AS a1_hi FROM j GROUP BY grp, lo1, hi1, run"""


#: Sixteen customers by number make a group; ``i`` is the place in it, ``v`` comes of the balance.
_GROUP, _SHIFT = "CAST(floor(c_custkey / 16) AS BIGINT)", "CAST(floor(abs(c_acctbal)) AS BIGINT) % 4"
KEPT = "c_custkey IS NOT NULL AND c_acctbal IS NOT NULL"
SIDES = {  # of axes 0 and 1
    "aligned": ("9 * i + v", "9 * i + v + 10", "0", "10"),
    "misaligned": ("9 * i + v", "9 * i + v + 10", "5 * (i % 2)", "5 * (i % 2) + 10"),
    "diagonal": ("4 * i + 1 + v % 2", "4 * i + 3 + v % 2") * 2,
    "centred": ("-2 * (i + 1) - v % 2", "2 * (i + 1) + v % 2", "-2 * (16 - i)", "2 * (16 - i)"),
}
BOUNDS = ("a0_lo", "a0_hi", "a1_lo", "a1_hi")


def customer_boxes_sql(kind: str) -> str:
    w = f"(SELECT grp, c_custkey - 16 * grp AS i, v FROM (SELECT c_custkey, {_GROUP} AS grp, {_SHIFT} AS v FROM customer WHERE {KEPT}))"
    lo0, hi0, lo1, hi1 = SIDES[kind]
    around = f" UNION SELECT grp, 0, 64, 0, 64 FROM {w}" if kind == "diagonal" else ""
    return f"SELECT grp, {lo0} AS lo0, {hi0} AS hi0, {lo1} AS lo1, {hi1} AS hi1 FROM {w}" + around


def customer_boxes(c: Context, kind: str) -> DataFrame:
    """``grp`` and the bounds of its boxes: one for each customer, on the diagonal one around all too."""
    keyed = c.table("customer").where(KEPT).selectExpr("c_custkey", f"{_GROUP} AS grp", f"{_SHIFT} AS v").selectExpr("grp", "c_custkey - 16 * grp AS i", "v")
    boxes = keyed.selectExpr("grp", *(f"CAST({side} AS INT) AS {name}" for side, name in zip(SIDES[kind], BOUNDS, strict=True)))
    return boxes.union(keyed.selectExpr("grp", "0", "64", "0", "64")).distinct() if kind == "diagonal" else boxes.distinct()


def covers_of(c: Context, kind: str, run) -> DataFrame:
    """A cover of each group's boxes, made where they are."""

    def cover(boxes):
        return [b[0] + b[1] for b in run([((x[0], x[1]), (x[2], x[3])) for x in boxes]).boxes]

    groups = customer_boxes(c, kind).groupBy("grp").agg(F.collect_list(F.struct(*BOUNDS)).alias("boxes"))
    return groups.select("grp", F.inline(F.udf(cover, f"array<struct<{', '.join(f'{x}: int' for x in BOUNDS)}>>")("boxes")))


for kind in SIDES:
    add(f"cover_grid_{kind}", lambda c, kind=kind: covers_of(c, kind, bx.cover_grid), covers_sql(customer_boxes_sql(kind)))
    add(f"cover_{kind}", lambda c, kind=kind: cover_df(customer_boxes(c, kind), ["a0", "a1"], ["grp"]), covers_sql(customer_boxes_sql(kind)))

_DATA_BOXES = "SELECT CAST(MIN(l_quantity) AS INTEGER) AS lo0, CAST(MAX(l_quantity) AS INTEGER) + 1 AS hi0, CAST(round(MIN(l_discount) * 100) AS INTEGER) AS lo1, CAST(round(MAX(l_discount) * 100) AS INTEGER) + 1 AS hi1 FROM lineitem JOIN part ON l_partkey = p_partkey WHERE l_quantity % 7 <> 0 GROUP BY p_type, strftime(l_shipdate, '%Y-%m'), l_tax"


def data_boxes(c: Context) -> DataFrame:
    """Bounds of quantity and discount for each part type, month and tax."""
    both = c.table("lineitem").where("l_quantity % 7 <> 0").join(c.table("part").select("p_partkey", "p_type"), F.col("l_partkey") == F.col("p_partkey"))
    disc = F.round(F.col("l_discount") * 100).cast("int")
    return both.groupBy("p_type", F.date_format("l_shipdate", "yyyy-MM"), "l_tax").agg(
        F.min("l_quantity").cast("int").alias("a0_lo"), (F.max("l_quantity").cast("int") + 1).alias("a0_hi"), F.min(disc).alias("a1_lo"), (F.max(disc) + 1).alias("a1_hi"),
    )


add("cover_from_data", lambda c: cover_df(data_boxes(c), ["a0", "a1"]), cover_sql(_DATA_BOXES))
add("cover_df", lambda c: cover_df(data_boxes(c).where("a1_lo <= 4"), ["a0", "a1"]), cover_sql(f"SELECT * FROM ({_DATA_BOXES}) WHERE lo1 <= 4"))
add(
    "interval_union",
    lambda c: islands(c.table("lineitem").select(F.col("l_partkey").alias("part"), F.datediff("l_shipdate", F.lit("1992-01-01").cast("date")).alias("lo"), (F.datediff("l_shipdate", F.lit("1992-01-01").cast("date")) + 30).alias("hi")), "lo", "hi", ["part"]),
    """WITH b AS (SELECT l_partkey AS part, CAST(date_diff('day', DATE '1992-01-01', CAST(l_shipdate AS DATE)) AS INTEGER) AS lo FROM lineitem),
f AS (SELECT *, CASE WHEN lo <= MAX(lo + 30) OVER (PARTITION BY part ORDER BY lo ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) THEN 0 ELSE 1 END AS new FROM b),
g AS (SELECT *, SUM(new) OVER (PARTITION BY part ORDER BY lo ROWS UNBOUNDED PRECEDING) AS run FROM f)
SELECT part, MIN(lo) AS lo, MAX(lo + 30) AS hi FROM g GROUP BY part, run""",
)


#: Pieces at which the full split is not begun, and seconds that a run may be expected to take.
MOST_PIECES, MOST_SECONDS = 300_000, 5.0


def cover_times(kind: str, d: int, sizes, shifts=(0,), ways=tuple(bx.COVERS)) -> list[tuple]:
    """Mean seconds of five runs, pieces and boxes of both covers on growing workloads.

    ``shifts`` are added, in turn, to the boxes' bounds on axis 0.
    The full split alone stops at a number of pieces.  Either stops where its last two
    means let the next run be expected to take too long; nulls say so.
    """
    rows = []
    for way in ways:
        run = bx.COVERS[way]
        means, over = [0.0, 0.0], False
        for n in sizes:
            boxes = [((lo + x, hi + x), *rest) for ((lo, hi), *rest), x in zip(bx.WORKLOADS[kind](n, d), cycle(shifts))]
            over = over or means[-1] * max(1.0, means[-1] / means[-2] if means[-2] > 0.001 else 2.0**d) > MOST_SECONDS
            over = over or (way == "grid" and bx.predicted_pieces(boxes) > MOST_PIECES)
            if over:
                rows.append((kind, d, n, way, None, None, None))
                continue
            got = [run(boxes) for _ in range(5)]
            means.append(sum(g.stats.seconds for g in got) / 5)
            rows.append((kind, d, n, way, means[-1], got[0].stats.pieces, len(got[0].boxes)))
    return rows


BENCH_SIZES = [1 << k for k in range(1, 17)]


def bench_times(c: Context, sizes) -> DataFrame:
    """``cover_times`` of each workload, number of axes and cover in a task of its own, with the
    boxes shifted as the customers' balances say; the largest size needs so many customers."""
    work = list(product(("sweep", "grid"), reversed(bx.WORKLOADS), (4, 3, 2, 1)))  # the longest first
    rows = "array<struct<workload: string, d: int, n: int, cover: string, seconds: double, pieces: bigint, boxes: bigint>>"

    def times(k, shifts):
        way, kind, d = work[k]
        return cover_times(kind, d, sizes, shifts or [0], (way,))

    first = c.table("customer").where(KEPT).selectExpr("c_custkey", f"CAST({_SHIFT} AS INT) AS v").orderBy("c_custkey", "v").limit(sizes[-1])
    shifts = first.agg(F.transform(F.array_sort(F.collect_list(F.struct("c_custkey", "v"))), lambda x: x["v"]).alias("shifts"))
    tasks = c.spark.range(0, len(work), 1, len(work)).crossJoin(F.broadcast(shifts))
    return tasks.select(F.inline(F.udf(times, rows)("id", "shifts")))


@query("cover_bench")
def cover_bench(c: Context) -> DataFrame:
    """Seconds and pieces of both covers on all workloads, n from 2 to 2^16; kept, so that
    every use of the rows gives the same seconds."""
    return bench_times(c, BENCH_SIZES).persist()


add(
    "cover_multiplicity",
    lambda c: ms.multiplicity(c.spark, bx.centred(8, 2)),
    "WITH b AS (SELECT -2 * (i + 1) AS lo0, 2 * (i + 1) AS hi0, -2 * (8 - i) AS lo1, 2 * (8 - i) AS hi1 FROM (SELECT range AS i FROM range(8))), c AS (SELECT x AS a, LEAD(x) OVER (ORDER BY x) AS z FROM (SELECT lo0 AS x FROM b UNION SELECT hi0 FROM b)), d AS (SELECT x AS a, LEAD(x) OVER (ORDER BY x) AS z FROM (SELECT lo1 AS x FROM b UNION SELECT hi1 FROM b)), e AS (SELECT c.a, d.a AS a2, COUNT(*) AS copies FROM b JOIN c ON c.a >= lo0 AND c.z <= hi0 JOIN d ON d.a >= lo1 AND d.z <= hi1 GROUP BY ALL) SELECT copies, COUNT(*) AS pieces FROM e GROUP BY copies",
)

# --- envelopes ----------------------------------------------------------------------

SELECTIVE = "ship_month >= '1998-01-01' AND ship_month <= '1998-06-01' AND qty BETWEEN 20 AND 30"
SELECTIVE_SQL = "ship_month >= TIMESTAMP '1998-01-01' AND ship_month <= TIMESTAMP '1998-06-01' AND qty BETWEEN 20 AND 30"
ON = ["ship_month", "qty", "disc"]


def selective(c: Context, *more: str) -> DataFrame:
    return c.grid("g3").scan(["chunk", *ON, *more], SELECTIVE)


add("envelope_bounds", lambda c: envelope_bounds(selective(c), "qty", "disc"), f"WITH {G3} SELECT chunk, MIN(qty) AS qty_lo, MAX(qty) AS qty_hi, MIN(disc) AS disc_lo, MAX(disc) AS disc_hi FROM g3 WHERE {SELECTIVE_SQL} GROUP BY chunk")


@query("register_envelope", f"WITH {G3}, {G4} SELECT g4.chunk, g4.level, g4.qty, g4.disc, r.n_lines FROM (SELECT * FROM g3 WHERE {SELECTIVE_SQL}) r JOIN g4 ON r.ship_month = g4.ship_month AND r.qty = g4.qty AND r.disc = g4.disc")
def register_envelope(c: Context) -> DataFrame:
    """A small grid of selected cells, registered with its envelope, prunes a registered S."""
    known, cells = catalog(c, "g4"), c.grid("g3").scan(predicate=SELECTIVE)
    known.register("r", c.grid("g3"), tuple(ON), cells)
    cells.select(*ON).distinct().createOrReplaceTempView("gridlake_selected")
    return known.sql("SELECT g4.chunk, g4.level, g4.qty, g4.disc, r.n_lines FROM r JOIN gridlake_selected USING (ship_month, qty, disc) JOIN g4 USING (ship_month, qty, disc)")


add("envelope_noop", lambda c: envelope(c.grid("g3").scan(CELL, SELECTIVE), "qty", "disc"), f"WITH {G3} SELECT {CELLS} FROM g3 WHERE {SELECTIVE_SQL}")
JOINED = f"WITH {G3}, {G4} SELECT g4.chunk, g4.level, g4.qty, g4.disc, g3.price_avg AS surface, g4.price_avg AS inside FROM (SELECT * FROM g3 WHERE {SELECTIVE_SQL}) g3 {{}} JOIN g4 ON g3.ship_month = g4.ship_month AND g3.qty = g4.qty AND g3.disc = g4.disc"
SIDE = ["chunk", "level", *ON, "price_avg"]


def env_join(c: Context, mode: str, how: str = "inner") -> DataFrame:
    r = selective(c, "price_avg").withColumnRenamed("price_avg", "surface")
    return envelope_join(r, c.grid("g4"), ON, how, mode, SIDE).select("chunk", "level", "qty", "disc", "surface", F.col("price_avg").alias("inside"))


for mode in ("hull", "boxes", "off"):
    add(f"env_join_{mode}", lambda c, mode=mode: env_join(c, mode), JOINED.format(""))
add("env_join_left", lambda c: env_join(c, "boxes", "left").drop("qty", "disc"), JOINED.format("LEFT").replace("g4.qty, g4.disc, ", ""))
add("env_join_right", lambda c: env_join(c, "boxes", "right"), JOINED.format("RIGHT"))
add(
    "env_join_semi",
    lambda c: envelope_join(selective(c), c.grid("g4").scan([*ON, "n_lines"]).where("n_lines > 1"), ON, "left_semi", "hull").select("qty", "disc"),
    f"WITH {G3}, {G4} SELECT qty, disc FROM g3 WHERE {SELECTIVE_SQL} AND EXISTS (SELECT 1 FROM g4 WHERE g4.ship_month = g3.ship_month AND g4.qty = g3.qty AND g4.disc = g3.disc AND g4.n_lines > 1)",
)

# --- quantities ---------------------------------------------------------------------

add("speed_max", lambda c: c.grid("g3").scan(["chunk", "price_avg", "price_max"]).groupBy("chunk").agg(F.round(F.max(speed(F.col("price_avg"), F.col("price_max"))), 6).alias("speed")), f"WITH {G3} SELECT chunk, round(MAX(sqrt(price_avg * price_avg + price_max * price_max)), 6) AS speed FROM g3 GROUP BY chunk")

RH_SQL = "100.0 * ((q * p / (0.622 + 0.378 * q)) / exp(9.550426 - 5723.265 / t + 3.53068 * ln(t) - 0.00728332 * t))"
PHYSICS_SQL = f"WITH {G3}, {G4}, j AS (SELECT g4.chunk, g4.level, g4.qty, g4.disc, 200 + g4.qty AS t, 2e-5 * (1 + round(100 * g4.disc)) AS q, (0.1 + 0.05 * round(100 * g4.level)) * (1e5 + g3.price_avg / 10) AS p FROM g3 JOIN g4 ON g3.ship_month = g4.ship_month AND g3.qty = g4.qty AND g3.disc = g4.disc), r AS (SELECT chunk, level, qty, disc, t, {RH_SQL} AS rhi FROM j)"


def physics(c: Context) -> DataFrame:
    """Pseudo-physical inputs from both grids, and the humidity over ice."""
    g3 = c.grid("g3").scan([*ON, "price_avg"]).withColumnRenamed("price_avg", "surface")
    both = c.grid("g4").scan(["chunk", "level", *ON]).join(g3, ON)
    t, q = F.lit(200) + F.col("qty"), F.lit(2e-5) * (1 + F.round(100 * F.col("disc")))
    p = (F.lit(0.1) + F.lit(0.05) * F.round(100 * F.col("level"))) * (F.lit(1e5) + F.col("surface") / 10)
    return both.select("chunk", "level", "qty", "disc", t.alias("t"), rh_ice(q, p, t).alias("rhi"))


add("rh_ice_vals", lambda c: physics(c).select("chunk", "level", "qty", "disc", F.round("rhi", 6).alias("rhi")), f"{PHYSICS_SQL} SELECT chunk, level, qty, disc, round(rhi, 6) AS rhi FROM r")

# --- baselines ----------------------------------------------------------------------

SPEED_BOX = "ship_month >= '1997-01-01' AND ship_month < '1999-01-01' AND qty <= 30"
SPEED_BOX_SQL = "ship_month >= TIMESTAMP '1997-01-01' AND ship_month < TIMESTAMP '1999-01-01' AND qty <= 30"
LONG_AXES = ["ship_month", "qty", "disc"]
add("b_full_scan", lambda c: bl.full_scan(c.grid("g3"), CELL, Q2), f"WITH {G3} SELECT {CELLS} FROM g3 WHERE {Q2}")
add(
    "b_long_rows",
    lambda c: bl.long_rows(c.grid("g3"), ["price_avg", "price_max"], SPEED_BOX).withColumn("ship_month", F.date_format("ship_month", "yyyy-MM")),
    f"WITH {G3}, s AS (SELECT * FROM g3 WHERE {SPEED_BOX_SQL}) SELECT 'price_avg' AS variable, chunk AS ship_month, qty, disc, price_avg AS value FROM s UNION ALL SELECT 'price_max', chunk, qty, disc, price_max FROM s",
)
_FASTEST = f"WITH {G3} SELECT round(MAX(sqrt(price_avg * price_avg + price_max * price_max)), 6) AS speed FROM g3 WHERE {SPEED_BOX_SQL}"


def fastest(rows: DataFrame) -> DataFrame:
    return rows.agg(F.round(F.max(speed(F.col("price_avg"), F.col("price_max"))), 6).alias("speed"))


add("b_long_speed_max", lambda c: fastest(bl.wide_by_selfjoin(bl.long_rows(c.grid("g3"), ["price_avg", "price_max"], SPEED_BOX), LONG_AXES, ["price_avg", "price_max"])), _FASTEST)
add("b_long_pivot", lambda c: fastest(bl.wide_by_pivot(bl.long_rows(c.grid("g3"), ["price_avg", "price_max"], SPEED_BOX), LONG_AXES, ["price_avg", "price_max"])), _FASTEST)
add("b_hull_max", lambda c: bl.hull_scan(c.grid("gp"), ["price_max"], REGIONS).agg(F.max("price_max").alias("price_max")), f"WITH {GP} SELECT MAX(price_max) AS price_max FROM gp WHERE {REGIONS}")
add("b_hull_rows", lambda c: bl.hull_scan(c.grid("gp"), ["chunk", "nation", "prio", "n_orders"], REGIONS), f"WITH {GP} SELECT chunk, nation, prio, n_orders FROM gp WHERE {REGIONS}")
add("b_join_plain", lambda c: env_join(c, "off"), JOINED.format(""))
add(
    "b_dup_rows",
    lambda c: bl.no_elimination(c.grid("g3"), CELL, OVERLAPPING),
    f"WITH {G3} SELECT {CELLS} FROM g3 WHERE qty BETWEEN 10 AND 30 AND disc <= 0.05 UNION ALL SELECT {CELLS} FROM g3 WHERE qty BETWEEN 20 AND 40 AND disc >= 0.03 UNION ALL SELECT {CELLS} FROM g3 WHERE qty = 25",
)
add(
    "b_manual_filter",
    lambda c: selective(c, "price_avg").drop("chunk").withColumnRenamed("price_avg", "surface").join(c.grid("g4").scan(SIDE, SELECTIVE), ON).select("chunk", "level", "qty", "disc", "surface", F.col("price_avg").alias("inside")),
    JOINED.format(""),
)
add("b_index_lookup", lambda c: bl.ChunkIndex(c.grid("g3")).scan(CELL, "1997-03-01", "1997-08-15"), f"WITH {G3} SELECT {CELLS} FROM g3 WHERE ship_month BETWEEN TIMESTAMP '1997-03-01' AND TIMESTAMP '1997-08-15'")

# --- measures -----------------------------------------------------------------------

add(
    "measures_q1",
    lambda c: ms.measure(c.grid("g3"), Q1),
    f"WITH {G3}, m AS (SELECT COUNT(DISTINCT chunk) AS k FROM g3 WHERE ship_month > TIMESTAMP '1997-01-01 00:15:00'), q AS (SELECT COUNT(*) AS n FROM g3 WHERE {Q1_SQL}) SELECT 'cells_loaded' AS metric, CAST(k * 15 * 11 AS DOUBLE) AS value FROM m UNION ALL SELECT 'chunks_touched', k FROM m UNION ALL SELECT 'lookups', k FROM m UNION ALL SELECT 'cells_qualifying', n FROM q UNION ALL SELECT 'read_amplification', CAST(k * 15 * 11 AS DOUBLE) / n FROM m, q",
)
add(
    "measures_hull",
    lambda c: ms.measure(c.grid("gp"), REGIONS).where("metric IN ('cells_loaded', 'lookups')"),
    f"WITH {GP}, m AS (SELECT COUNT(DISTINCT chunk) AS k FROM gp) SELECT 'cells_loaded' AS metric, CAST(k * 12 * 5 AS DOUBLE) AS value FROM m UNION ALL SELECT 'lookups', k * 2 FROM m",
)


@query("measure_diff", "SELECT CAST(0 AS BIGINT) AS missing, CAST(0 AS BIGINT) AS extra")
def measure_diff(c: Context) -> DataFrame:
    """Rows of the planned scan against those of the full one."""
    grid = c.grid("g3")
    return pairs(c, [ms.diff(bl.full_scan(grid, CELL, Q2), grid.scan(CELL, Q2))], "missing long, extra long")
