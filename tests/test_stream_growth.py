from pyspark.sql import functions as F

from approxset.streaming import jobs


def test_stream_filter_grows(spark, tmp_path):
    """More event ids than a shard's first ring holds."""
    e = spark.range(70_000).select(F.col("id").alias("event_id"), F.lit("2024-01-01").cast("timestamp").alias("ts"))
    out = jobs.filtered(spark, e, f"file://{tmp_path}", shards=1)
    assert out.count() == out.distinct().count() >= 69_990
