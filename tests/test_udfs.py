import numpy as np
import pytest

from approxset.functions import udfs
from approxset.schema import FilterSpec


@pytest.mark.parametrize("n", [0, 1, 200])
def test_payload_round_trip(n):
    spec = FilterSpec(p=20, slots=1 << 8)
    f = np.sort(np.random.default_rng(n).integers(0, 1 << 20, n))
    assert udfs.decode(udfs.encode(f, 0, spec.slots, spec.r, spec.width)).tolist() == f.tolist()


def test_functions_on_nulls_and_unknown_filters(spark):
    spec = FilterSpec(p=20, slots=1 << 8)
    f = np.array([5, 5, 70000], np.int64)
    rows = [("a", bytearray(udfs.encode(f, 0, spec.slots, spec.r, spec.width))), ("b", None)]
    d = spark.createDataFrame(rows, "filter_id string, payload binary")
    udfs.register_tables(spark)
    out = spark.sql("SELECT filter_id, t.fp, t.cnt FROM {d}, LATERAL traverse_filter(payload) t ORDER BY fp", d=d).collect()
    assert [tuple(r) for r in out] == [("a", 5, 2), ("a", 70000, 1)]
    assert [r["s"] and r["s"]["n"] for r in spark.sql("SELECT filter_stats(payload) AS s FROM {d} ORDER BY filter_id", d=d).collect()] == [3, None]
    udfs.register_might_contain(spark, d.filter("payload is not null"), spec.p)
    got = spark.sql("SELECT might_contain('a', 5L << 40) AS x, might_contain('a', 6L << 40) AS y, might_contain('c', 5L << 40) AS z, might_contain('a', CAST(NULL AS BIGINT)) AS n").first()
    assert tuple(got) == (True, False, False, False)


def test_merge_adds_copies(spark):
    spec = FilterSpec(p=20, slots=1 << 8)
    one = bytearray(udfs.encode(np.array([9], np.int64), 0, spec.slots, spec.r, spec.width))
    d = spark.createDataFrame([(one,), (one,), (None,)], "payload binary")
    p = d.agg(udfs.merge_filters(spec)("payload").alias("payload")).first()["payload"]
    assert udfs.decode(bytes(p)).tolist() == [9, 9]
