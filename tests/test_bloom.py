import pytest
from pyspark.sql import functions as F

from approxset.operators import bloom


def keys(spark, n, prefix="k"):
    return spark.range(n).select(F.concat(F.lit(prefix), "id").alias("k"))


KINDS = [bloom.BloomFilter.for_items(800, 1 / 256), bloom.CountingBloom(12_000, 8), bloom.PageLocalBloom.for_items(800, 1 / 256)]


@pytest.mark.parametrize("kind", KINDS)
def test_probe_keeps_columns_and_rows(spark, kind):
    """Repeated and null keys, and columns named like the operators' own; present keys are always found."""
    asked = keys(spark, 800).union(keys(spark, 800)).union(keys(spark, 2000, "a")).union(spark.createDataFrame([(None,)], "k string"))
    asked = asked.select("k", *[F.lit(i).alias(c) for i, c in enumerate(("hits", "reads", "word", "word_idx", "cell", "c", "block", "id"))])
    out = kind.probe(asked, kind.build(keys(spark, 800).union(spark.createDataFrame([(None,)], "k string"))))
    assert out.columns == [*asked.columns, "maybe"]
    got = out.toPandas()
    assert len(got) == 3601 and set(got["hits"]) == {0} and set(got["id"]) == {7}
    assert got[got["k"].fillna("").str.startswith("k")]["maybe"].all() and not got[got["k"].isna()]["maybe"].any()
    assert got[got["k"].fillna("").str.startswith("a")]["maybe"].mean() < 0.03


def test_empty(spark):
    b = KINDS[0]
    none = keys(spark, 0)
    assert not b.probe(keys(spark, 3), b.build(none)).filter("maybe").count()
    assert b.probe(none, b.build(keys(spark, 3))).count() == 0


def test_both_ways_agree(spark, monkeypatch):
    b, y = KINDS[0], bloom.LayeredBloom(100, 18, 8)
    arrived = keys(spark, 500).withColumn("seq", F.substring("k", 2, 9).cast("long") + 1)
    asked = keys(spark, 700)
    sent = [b.reads(asked, b.build(arrived), 64).toPandas(), y.reads(asked, y.build(arrived), y.layers(500), 64).toPandas()]
    monkeypatch.setattr(bloom, "BROADCAST_WORDS", 0)
    moved = [b.reads(asked, b.build(arrived), 64).toPandas(), y.reads(asked, y.build(arrived), y.layers(500), 64).toPandas()]
    for x, z in zip(sent, moved, strict=True):
        assert x.sort_values("k").values.tolist() == z.sort_values("k").values.tolist()


def test_absent_lookups_stop_early(spark):
    """At half the bits set, about two looks for an absent key, k for a present one."""
    b = bloom.BloomFilter.for_items(3000, 2.0**-12)
    words = b.build(keys(spark, 3000))
    absent = b.reads(keys(spark, 4000, "a"), words, 1).agg(F.avg("reads")).first()[0]
    present = b.reads(keys(spark, 3000), words, 1).agg(F.min("reads")).first()[0]
    assert 1.8 < absent < 2.2 and present >= b.k - 1


@pytest.mark.parametrize("shards", [1, 3])
def test_group_flushes(spark, shards):
    b = bloom.PageLocalBloom(23, 4096, 5)
    arrived = keys(spark, 1500).withColumn("seq", F.expr("cast(substring(k, 2, 9) as long) * 7919 % 1500 + 1"))
    blocks = [r["b"] for r in arrived.orderBy("seq").select(b.block(F.col("k")).alias("b")).collect()]
    groups, want = -(-23 // 2), []
    per = -(-groups // shards)
    for s in range(shards):
        held, count = {g: 0 for g in range(s * per, (s + 1) * per)}, 0
        for g in (x // 2 for x in blocks):
            if g in held:
                held[g] += 1
                if sum(held.values()) == 40:
                    top = max(held, key=lambda i: (held[i], -i))
                    count += 1
                    want.append((s, count, top * 2, held[top]))
                    held[top] = 0
        want += [(s, 0, g * 2, n) for g, n in held.items() if n]
    assert sorted(map(tuple, b.group_flushes(arrived, 40, 2, shards).collect())) == sorted(want)


def test_delayed_lookups_read_a_block_once(spark):
    b = bloom.PageLocalBloom(16, 512, 5)
    asked = keys(spark, 300).withColumn("seq", F.substring("k", 2, 9).cast("long") + 1)
    answers, cost = b.delayed(asked, b.build(asked), 100)
    assert answers.filter("not maybe").count() == 0
    assert [r["lookups"] for r in cost.collect()] == [100] * 3 and all(r["block_reads"] <= 16 for r in cost.collect())
