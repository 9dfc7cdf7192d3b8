"""Physical quantities and histogram helpers as column expressions."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def speed(u: Column, v: Column) -> Column:
    """Total speed of two perpendicular components."""
    return F.sqrt(u * u + v * v)


def rh_ice(q: Column, p: Column, t: Column) -> Column:
    """Relative humidity over ice in percent from specific humidity, pressure and temperature
    (SI), with a published fit of the saturation pressure over ice."""
    e = q * p / (F.lit(0.622) + F.lit(0.378) * q)
    saturation = F.exp(F.lit(9.550426) - F.lit(5723.265) / t + F.lit(3.53068) * F.log(t) - F.lit(0.00728332) * t)
    return F.lit(100.0) * e / saturation


def ratio(a: Column, b: Column) -> Column:
    """Percentage of two averages; the division comes first, so equal ones give exactly 100."""
    return F.lit(100) * (a / b)


def histogram(rows: DataFrame, value: Column, width: int, bins: int) -> DataFrame:
    """Counts of bins ``[k*width, (k+1)*width)``, the last one open, empty bins kept."""
    found = rows.groupBy(F.least(F.lit(bins - 1), F.floor(value / width)).cast("int").alias("bin")).agg(F.count("*").alias("n"))
    every = rows.sparkSession.range(bins).select(F.col("id").cast("int").alias("bin"))
    return every.join(F.broadcast(found), "bin", "left").select("bin", F.coalesce("n", F.lit(0)).cast("long").alias("n"))


def decode_time(value: Column, unit: str, epoch: str) -> Column:
    """An offset in ``unit`` since ``epoch`` as a timestamp without time zone."""
    seconds = {"seconds": 1, "minutes": 60, "hours": 3600, "days": 86400}[unit]
    return F.lit(epoch).cast("timestamp_ntz") + F.make_dt_interval(secs=value * seconds)
