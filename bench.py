"""Headline queries after ingest, each run once before it is timed: prints one JSON line.

BENCH_SF_DIR and BENCH_CPUS choose the tables and the cores.  The derived grids have some
10^5 cells, where fixed costs rule; so the experiments' sweeps also run on a dense grid of
6 million cells, every point with its optimisation on and off, with files and bytes read.
Ratios of each baseline to the planned query and the covers' growth are in the same line.
"""

from __future__ import annotations

import json
import os
import statistics
import sys
import time

sys.path.insert(0, os.path.dirname(os.path.abspath(__file__)))

from pyspark.sql import SparkSession

SF_DIR = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
CPUS = os.environ.get("BENCH_CPUS", "4")
HEADLINES = [
    "q_convex", "q_nonconvex", "w_hprune_10", "w_hprune_50", "w_vprune_1", "w_vprune_6", "w_hist_qty_10", "w_hist_qty_50", "w_hist_month_12", "w_env_off", "w_env_hull", "w_env_boxes",
    "w_speed_ours", "w_speed_long", "w_regions_ours_80", "w_regions_hull_80", "b_full_scan", "cover_from_data",
]
PAIRS = {"pruning": ("b_full_scan", "q_nonconvex"), "envelope": ("w_env_off", "w_env_hull"), "self_join": ("w_speed_long", "w_speed_ours"), "hull": ("w_regions_hull_80", "w_regions_ours_80")}


def covers() -> dict:
    """Mean seconds of five runs by workload, axes, boxes and cover; the full split is skipped
    where it would make too many pieces."""
    from gridlake.operators import boxes as bx

    out = {}
    sizes = {"aligned": (16, 256, 4096), "misaligned": (16, 256, 4096), "diagonal": (16, 64), "centred": (16, 64)}
    for kind, counts in sizes.items():
        for d in (1, 2, 3, 4):
            for n in counts:
                if kind in ("diagonal", "centred") and d >= 3 and n > 16:
                    continue
                boxes = bx.random_rows(n, d, kind == "misaligned") if "aligned" in kind else bx.WORKLOADS[kind](n, d)
                for way, run in bx.COVERS.items():
                    if way == "grid" and bx.predicted_pieces(boxes) > 300_000:
                        out[f"{kind}_{d}d_{n}_{way}"] = None
                        continue
                    out[f"{kind}_{d}d_{n}_{way}"] = round(statistics.mean(run(boxes).stats.seconds for _ in range(5)), 5)
    return out


CHUNKS, LEVELS, LATS, LONS, LAT_TILE = 12, 8, 180, 360, 15


def dense_grid(spark):
    """Time, level, latitude (stored downwards) and longitude, two variables without gaps."""
    from pyspark.sql import functions as F

    from gridlake.plans.scan import Grid
    from gridlake.sources import store

    path = f"{store.shared_dir(spark)}/gridlake-dense-{os.getpid()}"
    chunk = F.date_format(F.expr("add_months(DATE '2020-01-01', cast(c as int))"), "yyyy-MM")
    at = F.expr("cast(add_months(DATE '2020-01-01', cast(c as int)) as timestamp_ntz)")
    base = spark.range(CHUNKS).withColumnRenamed("id", "c").withColumns({"chunk_key": chunk, "chunk": chunk, "time_values": F.array(at)})
    tiles = base.crossJoin(spark.range(LEVELS).select(F.col("id").cast("int").alias("o_level"))).crossJoin(spark.range(0, LATS, LAT_TILE).select(F.col("id").cast("int").alias("o_lat")))
    cells = F.sequence(F.lit(0), F.lit(LAT_TILE * LONS - 1))
    one = F.lit(1)
    seed = F.col("c") * 7919 + F.col("o_level") * 104729 + F.col("o_lat") * 1299709
    tiles = tiles.select(
        "chunk_key", "chunk", "time_values", F.lit(0).alias("o_time"), "o_level", "o_lat", F.lit(0).alias("o_lon"), one.alias("n_time"), one.alias("n_level"), F.lit(LAT_TILE).alias("n_lat"), F.lit(LONS).alias("n_lon"),
        F.transform(cells, lambda k: F.pmod(k * 31 + seed, F.lit(9973)).cast("double")).alias("t"), F.transform(cells, lambda k: F.pmod(k * 17 + seed, F.lit(997)).cast("double")).alias("q"),
    )
    axes = {"level_values": list(map(float, range(LEVELS))), "lat_values": [90.0 - k for k in range(LATS)], "lon_values": list(map(float, range(LONS)))}
    heads = base.select("chunk_key", "chunk", "time_values", *[F.lit(v).alias(n) for n, v in axes.items()])
    store.write_grid(tiles.repartition(8, "chunk_key"), heads.coalesce(1), path)
    return Grid(spark, store.infer_grid(spark, "dense", path, {"time": True}, "date_format({0}, 'yyyy-MM')"))


def sweeps(spark) -> dict:
    """Seconds of the sweeps on the dense grid: the mean of two runs after one; what is slow on
    purpose runs once."""
    from pyspark.sql import functions as F

    from gridlake.model import ScanOptions
    from gridlake.operators import baselines as bl
    from gridlake.operators import measures as ms
    from gridlake.operators.envelope import envelope_join
    from gridlake.sources.store import shared_dir

    grid, out, reads = dense_grid(spark), {}, {}
    off = ScanOptions(prune_rows=False, prune_columns=False)

    def put(name: str, build, repeats: int = 2) -> None:
        def run():
            build().write.format("noop").mode("overwrite").save()

        if repeats > 1:
            run()
        out[name] = round(ms.timed(run, repeats), 3)
        print(name, out[name], file=sys.stderr, flush=True)

    def mean(rows, *names):
        return rows.agg(*[F.avg(n).alias(n) for n in names], F.count("*").alias("n"))

    month = "time = '2020-03-01'"
    for extent in (0, 45, 180):
        test = f"{month} AND lat > {90 - extent}"
        put(f"rows_{extent}_on", lambda test=test: mean(grid.scan(["t"], test), "t"))
        if extent == 45:
            put(f"rows_{extent}_off", lambda test=test: mean(grid.scan(["t"], test, off), "t"), 1)
        for way, opts in (("on", ScanOptions()), ("off", off)) if extent == 45 else ():
            reads[f"rows_{extent}_{way}"] = ms.scan_metrics(mean(grid.scan(["t"], test, opts), "t"))
    put("columns_1_on", lambda: mean(grid.scan(["t"]), "t"), 1)
    put("columns_1_off", lambda: mean(grid.scan(["t"], options=ScanOptions(prune_columns=False)), "t"), 1)
    keys, path = ["time", "lat", "lon"], f"{shared_dir(spark)}/gridlake-dense-r-{os.getpid()}"
    r = grid.scan(["chunk", *keys, "q"], "time >= '2020-04-01' AND time < '2020-06-01' AND level = 0 AND lat BETWEEN 10 AND 20 AND lon BETWEEN 100 AND 140")
    r.withColumnRenamed("q", "surface").write.parquet(path)
    r = spark.read.parquet(path)
    for mode in ("off", "hull", "boxes"):
        put(f"envelope_{mode}", lambda mode=mode: envelope_join(r, grid, keys, "inner", mode, ["level", *keys, "t"]).agg(F.count("*").alias("n"), F.sum("t").alias("t")), 1 if mode == "off" else 2)
    # the envelope's own price: a filter that removes nothing, on the whole grid
    put("envelope_test_none", lambda: mean(grid.scan(["lat", "lon", "t"]), "t"), 1)
    put("envelope_test_noop", lambda: mean(grid.scan(["lat", "lon", "t"]).where("lat >= -90 AND lat <= 90 AND lon >= 0 AND lon <= 360"), "t"), 1)
    regions = "(lat > 80 AND lon < 60) OR (lat < -70 AND lon > 300)"
    for n in (2, 12):
        test = f"({regions}) AND time < '{2020 + n // 12}-{n % 12 + 1:02d}-01'"
        put(f"regions_{n}_ours", lambda test=test: grid.scan(["t"], test).agg(F.max("t").alias("t")))
        put(f"regions_{n}_hull", lambda test=test: bl.hull_scan(grid, ["t"], test).agg(F.max("t").alias("t")), 1)
    ratios = {
        "pruning": out["rows_45_off"] / out["rows_45_on"], "columns": out["columns_1_off"] / out["columns_1_on"], "envelope": out["envelope_off"] / out["envelope_hull"],
        "envelope_boxes": out["envelope_off"] / out["envelope_boxes"], "envelope_overhead": out["envelope_test_noop"] / out["envelope_test_none"], "hull": out["regions_12_hull"] / out["regions_12_ours"],
    }
    return {"cells": CHUNKS * LEVELS * LATS * LONS, "seconds": out, "reads": reads, "ratios": {k: round(v, 2) for k, v in ratios.items()}}


def main() -> None:
    import gridlake.queries as gq
    from gridlake.queries.registry import Context

    spark = (
        SparkSession.builder.master(f"local[{CPUS}]").appName("bench").config("spark.sql.shuffle.partitions", CPUS).config("spark.ui.enabled", "false")
        .config("spark.sql.session.timeZone", "UTC").config("spark.driver.memory", "4g").config("spark.ui.showConsoleProgress", "false").getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    context, seconds = Context(spark, SF_DIR), {}
    for name in ("g3", "g4", "gp"):
        began = time.perf_counter()
        context.grid(name)
        seconds[f"ingest_{name}"] = round(time.perf_counter() - began, 3)
        print("ingest", name, seconds[f"ingest_{name}"], file=sys.stderr, flush=True)
    queries = gq.queries()
    queries["q_convex"](spark, SF_DIR).count()  # the first run compiles and lists files
    for name in HEADLINES:
        queries[name](spark, SF_DIR).write.format("noop").mode("overwrite").save()
        began = time.perf_counter()
        queries[name](spark, SF_DIR).write.format("noop").mode("overwrite").save()
        seconds[name] = round(time.perf_counter() - began, 3)
        print(name, seconds[name], file=sys.stderr, flush=True)
    ratios = {k: round(seconds[a] / seconds[b], 2) for k, (a, b) in PAIRS.items()}
    total = round(sum(seconds[n] for n in HEADLINES), 3)
    print(json.dumps({"metric": "headline_seconds", "value": total, "unit": "sec", "queries": seconds, "sf": SF_DIR.rsplit("sf", 1)[-1], "ratios": ratios, "dense": sweeps(spark), "covers": covers()}))
    spark.stop()


if __name__ == "__main__":
    main()
