"""Decisions made before Catalyst: how to probe, and whether to filter a join's larger side first."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.fingerprint import fingerprint
from ..operators.quotient import BROADCAST_BYTES
from ..schema import FilterSpec
from ..sources.tables import key_text


def choose_probe(packed_bytes: int, co_partitioned: bool = False) -> str:
    """broadcast under a checked size; shard where keys are dealt like the filter; else the semi join."""
    if packed_bytes <= BROADCAST_BYTES:
        return "broadcast"
    return "shard" if co_partitioned else "join"


def prefilter_join(fact: DataFrame, dim: DataFrame, fact_key: str, dim_key: str, eps: float = 1 / 4096) -> DataFrame:
    """The inner join, with the fact side first cut by a filter of the dimension's keys where that pays.

    Equal to the plain join: the filter has no false negatives and the join removes the false positives. The filter is a
    semi join on fingerprints, which Catalyst broadcasts or merges by size."""
    n = dim.count()
    if not n:
        return fact.join(dim, F.col(fact_key) == F.col(dim_key))
    spec = FilterSpec.for_items(n, eps)
    f = dim.select(fingerprint(key_text(dim_key), spec).alias("__fp")).distinct()
    cut = fact.withColumn("__fp", fingerprint(key_text(fact_key), spec)).join(f, "__fp", "left_semi").drop("__fp")
    return cut.join(dim, F.col(fact_key) == F.col(dim_key))
