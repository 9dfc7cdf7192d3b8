"""Streams that get more than one batch."""

from pyspark.sql import functions as F

from gridlake.streaming import ops

EVENTS = "/root/testdata/sf0.001/events.parquet"


def test_batches_share_a_day(spark, tmp_path):
    """Rows of a day that come later are added to those that came before."""
    source, root = str(tmp_path / "events"), str(tmp_path / "out")
    events = spark.read.parquet(EVENTS)
    for k in range(2):
        events.where(F.col("event_id") % 2 == k).coalesce(1).write.mode("append").parquet(source)
        got = ops.append_chunks(spark, source, root)
    assert "batch_id" not in got.columns
    assert sorted(r.event_id for r in got.select("event_id").collect()) == sorted(r.event_id for r in events.select("event_id").collect())
