"""Tables, key sets and arrival order."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def key_text(*cols: str | Column) -> Column:
    """Keys in canonical text: parts joined by the unit separator; null if any part is null."""
    parts = [(F.col(c) if isinstance(c, str) else c).cast("string") for c in cols]
    return parts[0] if len(parts) == 1 else F.concat(*[x for p in parts for x in (p, F.lit("\x1f"))][:-1])


def order_keys(spark, sf_dir) -> DataFrame:
    return table(spark, sf_dir, "orders").select(key_text("o_orderkey").alias("k"))


def line_keys(spark, sf_dir) -> DataFrame:
    """The order keys of lineitem: repeated."""
    return table(spark, sf_dir, "lineitem").select(key_text("l_orderkey").alias("k"))


def absent_keys(spark, sf_dir, copies: int = 4) -> DataFrame:
    """Keys outside the orders' domain."""
    shift = F.explode(F.sequence(F.lit(1), F.lit(copies)))
    return table(spark, sf_dir, "orders").select("o_orderkey", shift.alias("i")).select(key_text(F.col("o_orderkey") + F.col("i") * 1000000).alias("k"))


def triple_keys(spark, sf_dir) -> DataFrame:
    return table(spark, sf_dir, "lineitem").select(key_text("l_orderkey", "l_partkey", "l_suppkey").alias("k"))


def arrivals(keys: DataFrame, spark_parts: int | None = None) -> DataFrame:
    """k, seq (from 1): arrival in the order of the keys' md5, which stands for uniform random order.

    The order is by hash, so ranges of the hash's leading digits are even shares: each share is ranked by itself and
    shifted by the counts before it (one row per share), never by one window over everything."""
    from pyspark.sql import Window

    d = keys.select("k", F.substring(F.md5("k"), 1, 2).alias("share"))
    counts = d.groupBy("share").agg(F.count("*").alias("c"))
    bases = counts.select("share", (F.sum("c").over(Window.orderBy("share")) - F.col("c")).alias("base"))
    inside = F.row_number().over(Window.partitionBy("share").orderBy("h", "k"))
    moved = d.repartition("share").withColumn("h", F.unhex(F.md5("k")))  # digests don't move
    return moved.withColumn("i", inside).join(F.broadcast(bases), "share").select("k", (F.col("base") + F.col("i")).alias("seq"))


def arrived_by(keys: DataFrame, ranks: list[int]) -> DataFrame:
    """k, seq as in `arrivals`, but seq is 1 more than the largest of `ranks` (ascending) below it: all that consumers need who
    only ask which of the ranks an arrival lies behind. Nothing is sorted or moved but the keys of the ranks' own shares.

    A count by the hash's first 16 bits (65,536 rows) says in which share a rank lies; the share is ranked by itself. Of a
    key whose copies lie on both sides of a rank, rows are made again with their own numbers."""
    from bisect import bisect_left

    from pyspark.sql import Window

    spark, ranks = keys.sparkSession, sorted({r for r in ranks if r > 0})
    d = keys.filter("k is not null").select("k", F.md5("k").alias("h"))
    share = F.substring("h", 1, 4)
    base, bases, n = [], {}, 0
    for r in sorted(d.groupBy(share.alias("s")).agg(F.count("*").alias("c")).collect()):  # 65,536 rows at most
        base.append((r["s"], n))
        n += r["c"]
    ranks = [r for r in ranks if r < n]
    for r in ranks:
        at = bisect_left(base, r, key=lambda x: x[1]) - 1
        bases[base[at][0]] = base[at][1]
    if not ranks:
        return d.select("k", F.lit(1).cast("long").alias("seq"))
    few = d.withColumn("s", share).filter(F.col("s").isin(list(bases))).withColumn("seq", F.row_number().over(Window.partitionBy("s").orderBy("h", "k")) + F.element_at(F.create_map(*[F.lit(x).cast(t) for s, b in bases.items() for x, t in ((s, "string"), (b, "long"))]), F.col("s")))
    some = few.groupBy("h", "k").agg(F.min("seq").alias("lo"), F.max("seq").alias("hi"))
    met = some.filter(F.exists(F.array(*[F.lit(r).cast("long") for r in ranks]), lambda x: (x >= F.col("lo")) & (x <= F.col("hi")))).collect()  # a row a rank at most
    split = [m for m in met if any(m["lo"] <= r < m["hi"] for r in ranks)]
    seq = F.lit(1).cast("long")
    for i, r in enumerate(ranks):
        h = next(m["h"] for m in met if m["lo"] <= r <= m["hi"])
        seq = seq + F.when(F.col("h") > h, F.lit(r - (ranks[i - 1] if i else 0)).cast("long")).otherwise(F.lit(0).cast("long"))
    out = (d.filter(~F.col("h").isin([m["h"] for m in split])) if split else d).select("k", seq.alias("seq"))
    for m in split:
        own = F.lit(0).cast("long")
        for r in ranks:
            own = F.when(F.col("id") > r, F.lit(r).cast("long")).otherwise(own)
        out = out.unionByName(spark.range(m["lo"], m["hi"] + 1).select(F.lit(m["k"]).alias("k"), (own + 1).alias("seq")))
    return out
