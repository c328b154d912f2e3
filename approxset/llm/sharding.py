"""Contiguous shards of near-equal bytes: global prefix sums of sizes from per-partition totals, cut at equal targets.

DataFrame operations only. The rows are range-partitioned once by key; each partition's total gives the partitions'
bases by a prefix sum over one row per partition; a running sum inside each partition then places every row. Only
(key, size, checksum) moves, never the text.

Defined results: a null text has size `overhead`; null keys sort first; equal rows keep their own places, in checksum
order; an empty table gives no rows; columns of the input other than key and text are left out.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import cut, documents, partitions


def balanced_shards(docs: DataFrame, shards: int = 40, key: str = "doc_id", size: Column | None = None, check: Column | None = None, overhead: int = 16) -> DataFrame:
    """key, size, text_crc32, shard, slot (gapless in its shard), start (bytes before the row, of all rows).

    A row goes to the shard in whose share of the total its first byte lies, so a shard's bytes differ from the
    target by less than one row at either end."""
    spark = docs.sparkSession
    size = F.coalesce(F.octet_length("text"), F.lit(0)).cast("long") + F.lit(overhead) if size is None else size
    check = F.crc32(F.coalesce(F.col("text"), F.lit("")).cast("binary")) if check is None else check
    sized = docs.select(F.col(key).alias("k"), size.alias("size"), check.alias("check"))
    placed = cut(sized.repartitionByRange(partitions(spark), "k", "check", "size").sortWithinPartitions("k", "check", "size").select("*", F.spark_partition_id().alias("part"), F.monotonically_increasing_id().alias("at")), "shard-sizes")
    # one row per partition from here to `bases`
    totals = placed.groupBy("part").agg(F.sum("size").alias("bytes"), F.count("*").alias("rows"))
    before = Window.orderBy("part").rowsBetween(Window.unboundedPreceding, -1)
    bases = totals.select("part", F.coalesce(F.sum("bytes").over(before), F.lit(0)).alias("byte_base"), F.coalesce(F.sum("rows").over(before), F.lit(0)).alias("row_base"), F.sum("bytes").over(Window.partitionBy()).alias("total"))
    inside = Window.partitionBy("part").orderBy("at").rowsBetween(Window.unboundedPreceding, -1)
    ranked = (
        placed.withColumn("run", F.coalesce(F.sum("size").over(inside), F.lit(0)))
        .withColumn("nth", F.col("at").bitwiseAND(F.lit((1 << 33) - 1)))
        .join(F.broadcast(bases), "part")
        .select("k", "size", "check", (F.col("byte_base") + F.col("run")).alias("start"), (F.col("row_base") + F.col("nth")).alias("rank"), "total")
        .withColumn("shard", F.least(F.lit(shards - 1).cast("long"), F.floor((F.col("start").cast("decimal(38,0)") * shards) / F.col("total")).cast("long")).cast("int"))
    )
    ranked = cut(ranked, "shard-ranks")
    firsts = ranked.groupBy("shard").agg(F.min("rank").alias("first"))  # one row per shard
    return ranked.join(F.broadcast(firsts), "shard").select(F.col("k").alias(key), "size", F.col("check").alias("text_crc32"), "shard", (F.col("rank") - F.col("first")).alias("slot"), "start")


def op3_sharding(spark, sf_dir: str) -> DataFrame:
    s = balanced_shards(documents(spark, sf_dir), 40)
    return s.select("doc_id", "size", "text_crc32", F.lit("bytes").alias("law"), "shard", "slot", F.lit(None).cast("int").alias("grown_shard"))
