import json

import pytest
from pyspark.sql import functions as F

from approxset.operators import quotient, tiered
from approxset.schema import FilterSpec, FilterSpecMismatch

SPEC = FilterSpec(p=34, slots=1 << 12)


def keys(spark, lo, hi):
    return spark.range(lo, hi).select(F.col("id").cast("string").alias("k"))


def same(f, want):
    got = f.contents()
    return got.exceptAll(want).count() == 0 and want.exceptAll(got).count() == 0


def test_a_batch_above_the_buffer_counts_whole(spark, tmp_path):
    f = tiered.LevelledFilter(spark, f"file://{tmp_path}", SPEC, 10)
    f.ingest(keys(spark, 0, 1000))
    h = f.history().first()
    assert (h["flushed"], h["written"], h["target"]) == (1000, 1000, 8)  # 10 * 2^7 is the first capacity from 1000 on


def test_the_buffer_is_held_and_asked_first(spark, tmp_path):
    f = tiered.TwoTierFilter(spark, f"file://{tmp_path}", SPEC, 100)
    f.ingest(keys(spark, 0, 100))
    f.ingest(keys(spark, 100, 140))
    assert len(f.state()["buffer"]) == 1 and f.history().count() == 1
    asked = keys(spark, 0, 200).select("k", *[F.lit(1).alias(c) for c in ("fp", "lv", "hit", "net", "bucket")])
    got = f.probe(asked)
    assert got.columns == [*asked.columns, "maybe", "level", "levels_read"]
    assert {(r["level"], r["levels_read"]): r["count"] for r in got.groupBy("level", "levels_read").count().collect()} == {(1, 1): 100, (0, 0): 40, (None, 1): 60}
    f.flush()
    assert not f.state()["buffer"] and f.probe(asked).filter("level = 1").count() == 140


@pytest.mark.parametrize("fanout", [2, 4, 16])
def test_fan_out(spark, tmp_path, fanout):
    f = tiered.LevelledFilter(spark, f"file://{tmp_path}", SPEC, 20, fanout)
    for e in range(6):
        f.ingest(keys(spark, e * 20, e * 20 + 20))
    assert [(h["target"], h["written"], h["levels"]) for h in f.history().orderBy("epoch").collect()] == [(t, 20 * u, n) for _, t, u, n in tiered.merge_schedule(6, fanout)]
    assert same(f, quotient.build_fp(keys(spark, 0, 120), SPEC))


def test_deletes_settle(spark, tmp_path):
    f = tiered.LevelledFilter(spark, f"file://{tmp_path}", SPEC, 40)
    for e in range(3):
        f.ingest(keys(spark, e * 40, e * 40 + 40))
    f.delete(keys(spark, 0, 10))
    assert f.state()["buffer"] and f.probe(keys(spark, 0, 10)).filter("maybe").count() == 0
    f.ingest(keys(spark, 0, 5))
    assert same(f, quotient.build_fp(keys(spark, 0, 5).union(keys(spark, 10, 120)), SPEC))
    f.flush()
    f.compact()
    assert same(f, quotient.build_fp(keys(spark, 0, 5).union(keys(spark, 10, 120)), SPEC)) and len(f.levels()) == 1


def test_commits(spark, tmp_path):
    """Replays change nothing, a second writer fails, a torn commit is passed over, another spec is refused."""
    path = f"file://{tmp_path}"
    f = tiered.LevelledFilter(spark, path, SPEC, 10)
    f.ingest(keys(spark, 0, 10), batch="a")
    f.ingest(keys(spark, 0, 10), batch="a")
    assert f.contents().agg(F.sum("cnt")).first()[0] == 10
    stale = f.state()
    f.ingest(keys(spark, 10, 20), batch="b")
    with pytest.raises(RuntimeError):
        f.cat.commit(stale)
    (tmp_path / "catalogue" / f"{f.state()['number'] + 1:012d}.json").write_text(json.dumps(f.state())[:40])
    assert f.contents().agg(F.sum("cnt")).first()[0] == 20
    f.ingest(keys(spark, 20, 30), batch="c")
    assert tiered.LevelledFilter(spark, path, SPEC, 10).contents().agg(F.sum("cnt")).first()[0] == 30
    with pytest.raises(FilterSpecMismatch):
        tiered.LevelledFilter(spark, path, FilterSpec(p=35, slots=1 << 12), 10).contents()


def test_lookups_while_merges_wait(spark, tmp_path):
    f = tiered.DeamortisedFilter(spark, f"file://{tmp_path}", SPEC, 25, per_flush=5)
    for e in range(6):
        f.ingest(keys(spark, e * 25, e * 25 + 25))
        assert same(f, quotient.build_fp(keys(spark, 0, e * 25 + 25), SPEC))
        assert f.probe(keys(spark, 0, e * 25 + 25)).filter("not maybe").count() == 0
    done = [r["done"] for r in f.progress().orderBy("epoch").collect()]
    assert max(done) <= 5 and f.progress().agg(F.max("waiting")).first()[0] > 0
