import os

import numpy as np
from pyspark.sql import functions as F

from approxset.cluster import shared_folder
from approxset.operators import bloom, tiered
from approxset.operators.quotient import build_fp
from approxset.schema import FilterSpec
from approxset.sources import tables as src
from approxset.workloads import experiments, throughput, tiers


def keys(spark, n, copies=1):
    return spark.range(n * copies).select((F.col("id") % n).cast("string").alias("k"))


def test_arrivals_by_rank_without_a_sort(spark):
    """Also where a rank falls among the copies of one key."""
    d = keys(spark, 7, 30)
    for ranks in ([], [1, 2, 100, 101, 209, 210, 500], [45, 90, 135, 180]):
        cut = F.array(*[F.lit(r) for r in [0, *ranks]])
        want = src.arrivals(d).select("k", (F.array_max(F.filter(cut, lambda x: x < F.col("seq"))) + 1).cast("long").alias("seq"))
        got = src.arrived_by(d, ranks)
        assert got.exceptAll(want).count() == want.exceptAll(got).count() == 0
        plan = got._jdf.queryExecution().executedPlan().toString()
        assert "Window" not in plan and "Exchange" not in plan  # every key was sorted and moved before


def test_counters_beyond_a_byte(spark):
    b = bloom.CountingBloom(64, 3)
    d = keys(spark, 5, 700)
    want = d.select(F.explode(F.array_distinct(b.positions(F.col("k")))).alias("cell")).groupBy("cell").agg(F.count("*").alias("c"))
    assert sorted(map(tuple, b._cells(d).collect())) == sorted(map(tuple, want.collect())) and want.agg(F.max("c")).first()[0] > 510
    plan = b._cells(d)._jdf.queryExecution().executedPlan().toString()
    assert "Generate" not in plan  # nine rows a key were shuffled before


def test_blocks_of_buffered_writes(spark):
    b, d = bloom.BloomFilter(1 << 20, 5), src.arrivals(keys(spark, 1000))
    e = F.call_function("div", F.col("seq") - 1, F.lit(300).cast("long"))
    want = d.select(e.alias("epoch"), F.explode(b.positions(F.col("k"))).alias("bit")).groupBy("epoch").agg(F.countDistinct(F.call_function("div", F.col("bit"), F.lit(512).cast("long"))).alias("n"))
    assert sorted(map(tuple, bloom.write_buffered_writes(d, b, 300, 512).collect())) == sorted(map(tuple, want.collect()))


def test_flushes_count_as_their_times(spark):
    y, d = bloom.LayeredBloom(100, 18, 12), src.arrivals(keys(spark, 1000))
    got = y.flushes(d, 100).filter("flushes > 0").groupBy("layer").agg(F.sum("flushes")).collect()
    assert sorted(map(tuple, got)) == sorted(map(tuple, y.flush_times(d, 100).groupBy("layer").count().collect()))


def test_replaced_files_are_gone(spark):
    """A two-tier filter of six flushes keeps one level, not six."""
    d = keys(spark, 600)
    f = tiers.fed(tiered.TwoTierFilter(spark, f"{shared_folder(spark)}/fed", FilterSpec(p=34, slots=1 << 12), 100), src.arrived_by(d, tiers.ends(600, 100)), 100)
    root = f.path.removeprefix("file://")
    assert len(os.listdir(f"{root}/level=1")) == 1 and not os.listdir(f"{root}/buffer")
    assert f.history().count() == 6 and f.contents().exceptAll(build_fp(d, f.spec)).count() == 0


def test_a_repeated_lookup_is_asked_once_and_counted_each_time(spark, sf, monkeypatch):
    asked = []
    monkeypatch.setattr(experiments, "all_answers", lambda spark, d, df: (asked.append(df.count()), [("one", df.withColumn("maybe", F.lit(True)))])[1])
    row = experiments.accuracies(spark, sf, keys(spark, 10, 5).withColumn("present", F.lit(False))).first()
    assert asked == [10] and (row["absent_probed"], row["fp"]) == (50, 50)


def test_lanes_are_those_of_the_digest(spark):
    from approxset.functions.fingerprint import digest_lanes

    for lanes, width in ((10, 9), (14, 9), (15, 8)):
        d = keys(spark, 50).select("k", digest_lanes(F.col("k"), lanes, width).alias("l")).toArrow()
        assert np.array_equal(bloom.lanes_of(d["k"].combine_chunks(), lanes, width), np.array(d["l"].to_pylist()))


def test_phases_are_cut_without_a_sort(spark, sf, monkeypatch):
    d = src.triple_keys(spark, sf)
    slots = -(-d.count() * 10 // 9)
    step = F.call_function("div", F.col("seq") * 20 + slots - 1, F.lit(slots).cast("long"))
    want = [src.arrivals(d).filter((step > lo) & (step <= hi)).count() for lo, hi in ((0, 5), (5, 18))]
    monkeypatch.setattr(src, "arrivals", None)
    got = throughput.run(spark, sf, ("classic",), (5, 18))
    assert [x[3] for x in got if x[2] == "insert"] == want and sum(want) == d.count()
