"""Fingerprints, quotients and digests as column expressions inside whole-stage code generation."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..schema import FilterSpec


def hash60(key: Column, seed: int = 0, family: str = "portable") -> Column:
    """60 bits: of md5 (the same in other engines), or of xxhash64 (faster)."""
    if family == "fast":
        return F.shiftrightunsigned(F.xxhash64(F.lit(seed), key), 4)
    return F.conv(F.substring(F.md5(F.concat(F.lit("k:" if not seed else f"k{seed}:"), key)), 1, 15), 16, 10).cast("long")


def fingerprint(key: Column, spec: FilterSpec) -> Column:
    """The top p bits; null for a null key. In the reserved variant the space shrinks to slots * width values."""
    h = hash60(key, spec.seed, spec.family)
    if spec.variant == "reserved":
        return F.pmod(h, F.lit(spec.slots * spec.width))
    return F.shiftright(h, 60 - spec.p)


def quotient_of(fp: Column, spec: FilterSpec) -> Column:
    return F.call_function("div", fp, F.lit(spec.width).cast("long"))


def remainder_of(fp: Column, spec: FilterSpec) -> Column:
    return F.pmod(fp, F.lit(spec.width)).cast("long")


def rejoin(quotient: Column, remainder: Column, spec: FilterSpec) -> Column:
    return quotient * F.lit(spec.width) + remainder


def once(value: Column, use) -> Column:
    """use(value) with `value` evaluated once, however often `use` names it."""
    return F.transform(F.array(value), use)[0]


def digest_lanes(key: Column, lanes: int, width: int = 9) -> Column:
    """Array of 4*width-bit lanes cut from two domain-separated SHA-256 digests (512 bits), computed once a key."""
    if lanes * width > 128:
        raise ValueError("the digest has 128 hexadecimal digits")
    digest = F.concat(F.sha2(F.concat(F.lit("0:"), key), 256), F.sha2(F.concat(F.lit("1:"), key), 256))
    return once(digest, lambda d: F.transform(F.sequence(F.lit(0), F.lit(lanes - 1)), lambda i: F.conv(F.substring(d, i * width + 1, F.lit(width)), 16, 10).cast("long")))


def register(spark: SparkSession) -> None:
    """SQL functions over fingerprints; Catalyst inlines them."""
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION hash60(k STRING) RETURNS BIGINT RETURN CAST(conv(substr(md5(concat('k:', k)), 1, 15), 16, 10) AS BIGINT)")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION quotient_of(fp BIGINT, width BIGINT) RETURNS BIGINT RETURN fp div width")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION remainder_of(fp BIGINT, width BIGINT) RETURNS BIGINT RETURN fp % width")


def collisions(keys: DataFrame, spec: FilterSpec) -> DataFrame:
    """One row: keys, fingerprints, keys that share a fingerprint (hard), fingerprints that share a quotient (soft)."""
    d = keys.filter("k is not null").distinct().select(fingerprint(F.col("k"), spec).alias("fp"))
    per = d.groupBy("fp").agg(F.count("*").alias("keys")).withColumn("quotient", quotient_of(F.col("fp"), spec))
    q = per.groupBy("quotient").agg(F.count("*").alias("fps"), F.sum("keys").alias("keys"), F.sum(F.when(F.col("keys") > 1, F.col("keys")).otherwise(0)).alias("hard"))
    z = lambda c: F.coalesce(c, F.lit(0)).cast("long")
    return q.agg(z(F.sum("keys")).alias("n_keys"), z(F.sum("fps")).alias("n_fps"), z(F.sum("hard")).alias("hard_keys"), z(F.sum(F.when(F.col("fps") > 1, F.col("fps")).otherwise(0))).alias("soft_fps"))
