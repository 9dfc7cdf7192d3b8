"""The experiments' workloads on the derived grids."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from gridlake.functions.science import histogram, ratio
from gridlake.operators import baselines as bl
from gridlake.operators.envelope import envelope_join
from gridlake.queries.methods import EXACT, LONG_AXES, ON, PHYSICS_SQL, REGIONS, SIX, exact_sum, fastest, means, physics
from gridlake.queries.registry import G3, G4, GP, Context, add
from gridlake.sources.store import shared_dir

MONTH = "ship_month = '1998-03-01'"
MONTH_SQL = "ship_month = TIMESTAMP '1998-03-01'"

# one chunk, growing extent of one axis; one chunk, growing number of variables
for extent in (0, 10, 20, 30, 40, 50):
    add(
        f"w_hprune_{extent:02d}",
        lambda c, extent=extent: c.grid("g4").scan(["price_max"], f"{MONTH} AND qty <= {extent}").agg((exact_sum("price_max") / F.nullif(F.count("*"), F.lit(0))).alias("mean"), F.count("*").alias("n")),
        f"WITH {G4} SELECT {EXACT.format('price_max')} / NULLIF(COUNT(*), 0) AS mean, COUNT(*) AS n FROM g4 WHERE {MONTH_SQL} AND qty <= {extent}",
    )
for k in range(1, 7):
    add(f"w_vprune_{k}", lambda c, k=k: c.grid("g4").scan(list(SIX[:k]), MONTH).agg(*means(SIX[:k], False)), f"WITH {G4} SELECT {means(SIX[:k], True)} FROM g4 WHERE {MONTH_SQL}")

# histogram over the join of both grids, twelve months, one extent varied
BINS, WIDTH = 30, 10


def both_grids(c: Context, test: str) -> DataFrame:
    g3 = c.grid("g3").scan([*ON, "price_avg"], test).withColumnRenamed("price_avg", "surface")
    return c.grid("g4").scan(["level", *ON, "price_avg", "n_lines"], test).join(g3, ON).withColumn("ratio", ratio(F.col("price_avg"), F.col("surface")))


def months(n: int) -> tuple[str, str]:
    """The first ``n`` months of 1998 as a predicate, for the planner and for SQL."""
    end = "1999-01-01" if n == 12 else f"1998-{n + 1:02d}-01"
    return f"ship_month >= '1998-01-01' AND ship_month < '{end}'", f"ship_month >= TIMESTAMP '1998-01-01' AND ship_month < TIMESTAMP '{end}'"


def ratio_hist_sql(test: str) -> str:
    return f"WITH {G3}, {G4}, r AS (SELECT 100 * (g4.price_avg / g3.price_avg) AS ratio FROM g3 JOIN g4 ON g3.ship_month = g4.ship_month AND g3.qty = g4.qty AND g3.disc = g4.disc WHERE {test}), h AS (SELECT LEAST({BINS - 1}, CAST(floor(ratio / {WIDTH}) AS INTEGER)) AS bin, COUNT(*) AS n FROM r GROUP BY 1) SELECT CAST(b.range AS INTEGER) AS bin, COALESCE(h.n, 0) AS n FROM range({BINS}) b LEFT JOIN h ON h.bin = b.range"


def add_hist(name: str, planned: str, sql: str) -> None:
    add(name, lambda c: histogram(both_grids(c, planned), F.col("ratio"), WIDTH, BINS), ratio_hist_sql(sql.replace("ship_month", "g3.ship_month").replace("qty", "g3.qty").replace("disc", "g3.disc")))


YEAR, YEAR_SQL = months(12)
for extent in (10, 20, 30, 40, 50):
    add_hist(f"w_hist_qty_{extent}", f"{YEAR} AND qty <= {extent}", f"{YEAR_SQL} AND qty <= {extent}")
for extent in (2, 5, 8, 11):
    add_hist(f"w_hist_disc_{extent}", f"{YEAR} AND disc < {extent / 100 - 0.005}", f"{YEAR_SQL} AND disc < {extent / 100 - 0.005}")
for n in (0, 3, 6, 9, 12):
    add_hist(f"w_hist_month_{n}", *months(n))

add(
    "w_hist_rhi",
    lambda c: histogram(physics(c), F.col("rhi"), WIDTH, BINS),
    f"{PHYSICS_SQL}, h AS (SELECT LEAST({BINS - 1}, CAST(floor(rhi / {WIDTH}) AS INTEGER)) AS bin, COUNT(*) AS n FROM r GROUP BY 1) SELECT CAST(b.range AS INTEGER) AS bin, COALESCE(h.n, 0) AS n FROM range({BINS}) b LEFT JOIN h ON h.bin = b.range",
)
add("w_count_rhi", lambda c: physics(c).where("rhi > 100 AND t < 243").agg(F.count("*").alias("n")), f"{PHYSICS_SQL} SELECT COUNT(*) AS n FROM r WHERE rhi > 100 AND t < 243")

# a selective side from CSV, joined with twelve months of the level grid
R_TEST, R_SQL = months(6)


_saved: dict[tuple[str, str], str] = {}


def from_csv(c: Context) -> DataFrame:
    """The selective side as a CSV file, written on first use and read with its schema."""
    key = (c.spark.sparkContext.applicationId, c.sf)
    if key not in _saved:
        rows = c.grid("g3").scan([*ON, "price_avg"], f"{R_TEST} AND qty BETWEEN 20 AND 30").withColumnRenamed("price_avg", "surface")
        path = f"{shared_dir(c.spark)}/gridlake-selective-{uuid.uuid4().hex}"
        rows.write.option("header", True).csv(path)
        _saved[key] = path
    path = _saved[key]
    read = c.spark.read.schema("ship_month timestamp_ntz, qty double, disc double, surface double").option("header", True).csv(path)
    return read.withColumn("chunk", F.date_format("ship_month", "yyyy-MM"))


_ENV_SQL = f"WITH {G3}, {G4} SELECT COUNT(*) AS joined, COUNT(*) FILTER (WHERE 100 * (g4.price_avg / g3.price_avg) > 100) AS above, COUNT(*) FILTER (WHERE 100 * (g4.price_avg / g3.price_avg) > 100 AND g4.n_lines < 2) AS counted FROM g3 JOIN g4 ON g3.ship_month = g4.ship_month AND g3.qty = g4.qty AND g3.disc = g4.disc WHERE g3.ship_month >= TIMESTAMP '1998-01-01' AND g3.ship_month < TIMESTAMP '1998-07-01' AND g3.qty BETWEEN 20 AND 30"


def env_count(c: Context, mode: str) -> DataFrame:
    joined = envelope_join(from_csv(c), c.grid("g4"), ON, "inner", mode, ["level", *ON, "price_avg", "n_lines"])
    above = ratio(F.col("price_avg"), F.col("surface")) > 100
    return joined.agg(F.count("*").alias("joined"), F.count_if(above).alias("above"), F.count_if(above & (F.col("n_lines") < 2)).alias("counted"))


for mode in ("off", "hull", "boxes"):
    add(f"w_env_{mode}", lambda c, mode=mode: env_count(c, mode), _ENV_SQL)

# greatest speed: one scan against the long format with its self-join
for extent in (10, 20, 30, 40, 50):
    test = f"ship_month >= '1997-01-01' AND ship_month < '1999-01-01' AND qty <= {extent}"
    sql = f"WITH {G3} SELECT round(MAX(sqrt(price_avg * price_avg + price_max * price_max)), 6) AS speed FROM g3 WHERE ship_month >= TIMESTAMP '1997-01-01' AND ship_month < TIMESTAMP '1999-01-01' AND qty <= {extent}"
    tail = "" if extent == 30 else f"_{extent}"
    add(f"w_speed_ours{tail}", lambda c, test=test: fastest(c.grid("g3").scan(["price_avg", "price_max"], test)), sql)
    add(f"w_speed_long{tail}", lambda c, test=test: fastest(bl.wide_by_selfjoin(bl.long_rows(c.grid("g3"), ["price_avg", "price_max"], test), LONG_AXES, ["price_avg", "price_max"])), sql)



def greatest(rows: DataFrame) -> DataFrame:
    return rows.agg(F.max("price_max").alias("price_max"), F.count("*").alias("cells"))


# greatest value over two regions: their boxes against one enclosing box
for n in (10, 20, 40, 80):
    last = f"order_month < '{1992 + (36 + n) // 12}-{(36 + n) % 12 + 1:02d}-01'"
    sql = f"WITH {GP} SELECT MAX(price_max) AS price_max, COUNT(*) AS cells FROM gp WHERE ({REGIONS}) AND {last.replace('< ', '< TIMESTAMP ')}"
    add(f"w_regions_ours_{n}", lambda c, last=last: greatest(c.grid("gp").scan(["price_max"], f"({REGIONS}) AND {last}")), sql)
    add(f"w_regions_hull_{n}", lambda c, last=last: greatest(bl.hull_scan(c.grid("gp"), ["price_max"], f"({REGIONS}) AND {last}")), sql)
