"""Streaming counterparts, on a file stream of events.

Event times are cast to ``timestamp`` (UTC) first, as watermarks need it.  Each runner
processes what is there (``availableNow``) and returns the table that the stream filled.
"""

from __future__ import annotations

import uuid
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from gridlake.sources.store import shared_dir

SCHEMA = "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string"


def events(spark: SparkSession, path: str) -> DataFrame:
    """The event table as a file stream.

    A stream watches a folder; of a table that is a single file, the folder is watched with
    a filter on the file's name.
    """
    folder, _, name = path.rstrip("/").rpartition("/")
    where = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    single = where.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).getFileStatus(where).isFile()
    reader = spark.readStream.schema(SCHEMA)
    return (reader.option("pathGlobFilter", name).parquet(folder) if single else reader.parquet(path)).withColumn("ts", F.col("ts").cast("timestamp"))


def drained(stream: DataFrame, mode: str = "append", keys: tuple[str, ...] = ()) -> DataFrame:
    """Runs a stream over all there is; its output lands in files of the shared folder.

    A ``complete`` batch replaces the one before.  Of ``update`` batches the last state of
    each key stays.  A batch that is repeated after a failure replaces its own rows only.
    """
    spark = stream.sparkSession
    root = f"{shared_dir(spark)}/gridlake-stream-{uuid.uuid4().hex}"
    if mode == "append":
        run = stream.writeStream.format("parquet").option("path", f"{root}/out").outputMode("append")
    else:
        run = stream.writeStream.foreachBatch(lambda rows, k: rows.write.mode("overwrite").parquet(f"{root}/out" if mode == "complete" else f"{root}/out/batch_id={k}")).outputMode(mode)
    run.option("checkpointLocation", f"{root}/checkpoint").trigger(availableNow=True).start().awaitTermination()
    if mode != "update":
        return spark.read.schema(stream.schema).parquet(f"{root}/out")
    rest = [c for c in stream.columns if c not in keys]
    rows = spark.read.option("basePath", f"{root}/out").parquet(f"{root}/out")
    return rows.groupBy(*keys).agg(F.max_by(F.struct(*rest), "batch_id").alias("last")).select(*[c if c in keys else f"last.{c}" for c in stream.columns])


def append_chunks(spark: SparkSession, path: str, root: str) -> DataFrame:
    """Each micro-batch adds to the day chunks it holds; a repeated batch replaces its own part only."""

    def put(rows: DataFrame, batch: int) -> None:
        parts = rows.withColumn("chunk_key", F.date_format("ts", "yyyy-MM-dd")).withColumn("batch_id", F.lit(batch))
        parts.write.mode("overwrite").option("partitionOverwriteMode", "dynamic").partitionBy("chunk_key", "batch_id").parquet(f"{root}/chunks")

    events(spark, path).writeStream.foreachBatch(put).option("checkpointLocation", f"{root}/checkpoint").trigger(availableNow=True).start().awaitTermination()
    return spark.read.parquet(f"{root}/chunks").drop("batch_id")


def tumbling(stream: DataFrame, width: str = "1 hour") -> DataFrame:
    return stream.withWatermark("ts", "1 hour").groupBy(F.window("ts", width), "event_type").agg(F.count("*").alias("n")).select(F.col("window.start").alias("start"), "event_type", "n")


def sliding(stream: DataFrame, width: str = "2 hours", step: str = "1 hour") -> DataFrame:
    return stream.withWatermark("ts", "1 hour").groupBy(F.window("ts", width, step)).agg(F.count("*").alias("n")).select(F.col("window.start").alias("start"), "n")


def sessions(stream: DataFrame, gap: str = "30 minutes") -> DataFrame:
    return stream.withWatermark("ts", "1 hour").groupBy(F.session_window("ts", gap), "user_id").agg(F.count("*").alias("n")).select("user_id", F.col("session_window.start").alias("start"), "n")


def deduplicated(stream: DataFrame) -> DataFrame:
    return stream.withWatermark("ts", "40 days").dropDuplicatesWithinWatermark(["user_id", "event_type"])


def interval_join(left: DataFrame, right: DataFrame, within: str = "10 minutes") -> DataFrame:
    """Clicks and the purchases of the same user that follow within an interval."""
    a = left.where("event_type = 'click'").withWatermark("ts", "1 hour").select(F.col("event_id").alias("click_id"), F.col("user_id").alias("click_user"), F.col("ts").alias("click_ts"))
    b = right.where("event_type = 'purchase'").withWatermark("ts", "1 hour").select(F.col("event_id").alias("purchase_id"), "user_id", "ts")
    return a.join(b, F.expr(f"click_user = user_id AND ts >= click_ts AND ts <= click_ts + INTERVAL {within}")).select("click_id", "purchase_id")


def state_bounds(stream: DataFrame) -> DataFrame:
    """An incremental envelope: least and greatest value of each day chunk so far."""

    def fold(key: tuple, batches: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        lo, hi = state.get if state.exists else (float("inf"), float("-inf"))
        for b in batches:
            lo, hi = min(lo, float(b["value"].min())), max(hi, float(b["value"].max()))
        state.update((lo, hi))
        yield pd.DataFrame({"chunk": [key[0]], "value_lo": [lo], "value_hi": [hi]})

    rows = stream.select(F.date_format("ts", "yyyy-MM-dd").alias("chunk"), "value").where("value IS NOT NULL")
    return rows.groupBy("chunk").applyInPandasWithState(fold, "chunk string, value_lo double, value_hi double", "lo double, hi double", "update", GroupStateTimeout.NoTimeout)
