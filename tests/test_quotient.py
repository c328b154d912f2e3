import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from approxset.operators import quotient as qf
from approxset.operators.tiered import merge_schedule
from approxset.schema import FilterFull, FilterSpec, FilterSpecMismatch


def simulate(fps, m, width):
    """Sequential judge: runs in bucket order, each item at the first free slot from its bucket on, twice round the ring."""
    items = sorted(fps)
    start = 0
    for _ in range(3):
        at, slots = start, {}
        for f in items:
            at = max(at, f // width)
            slots[at % m] = (f % width, f // width)
            at += 1
        wrapped = max(0, at - m)
        if wrapped == start:
            break
        start = wrapped
    return slots


@settings(max_examples=200, deadline=None)
@given(st.integers(3, 6), st.data())
def test_ring_round_trip(q, data):
    m, r = 1 << q, 5
    fps = sorted(data.draw(st.lists(st.integers(0, (m << r) - 1), max_size=m - 1)))
    g, rem = np.array(fps, np.int64) >> r, np.array(fps, np.int64) & 31
    slots = qf.layout(g, m)
    assert {int(s): (int(x), int(b)) for s, x, b in zip(slots, rem, g)} == simulate(fps, m, 32)
    back = qf.unpack_ring(qf.pack_ring(g, rem, m, r), m, r)
    assert (back[0] << r | back[1]).tolist() == fps


def test_ten_slot_example(spark):
    """Ten slots of width 16: a wrapped run, a duplicate, one cluster."""
    spec = FilterSpec(p=8, slots=10)
    object.__setattr__(spec, "_", None)
    fps = [19, 25, 37, 65, 65, 151, 156]
    g, rem = np.array([f // 16 for f in fps]), np.array([f % 16 for f in fps])
    s = qf.layout(g, 10)
    assert s.tolist() == [1, 2, 3, 4, 5, 9, 0]
    assert (s != g).tolist() == [False, True, True, False, True, False, True]
    assert rem.tolist() == [3, 9, 5, 1, 1, 7, 12]


def test_guards():
    with pytest.raises(FilterFull):
        qf.pack_ring(np.zeros(8, np.int64), np.zeros(8, np.int64), 8, 3)
    with pytest.raises(FilterSpecMismatch):
        FilterSpec(p=20, slots=16).same_space(FilterSpec(p=21, slots=16))
    with pytest.raises(FilterFull):
        FilterSpec(p=20, slots=16).check(13, 0.75)


def test_faces_agree_and_nulls_stay_out(spark):
    keys = spark.range(300).selectExpr("CASE WHEN id % 10 = 0 THEN NULL ELSE CAST(id % 120 AS STRING) END AS k")
    spec = FilterSpec(p=16, slots=512)
    f = qf.build_fp(keys, spec)
    want = sorted(map(tuple, f.collect()))
    assert sum(c for _, c in want) == 270
    assert sorted(map(tuple, qf.decode(qf.as_slots(f, spec), spec).collect())) == want
    for n in (1, 4, 16):
        assert sorted(map(tuple, qf.unpack(qf.pack(f, spec, n), spec, n).collect())) == want
    packed = qf.pack(f, spec, 4)
    for out in (qf.probe_broadcast(keys, packed, spec, 4), qf.probe_shard(keys, packed, spec, 4), qf.probe_join(keys, f, spec)):
        assert all(r["maybe"] == (r["k"] is not None) for r in out.collect())


def test_delete_undoes_insert(spark):
    spec = FilterSpec(p=20, slots=256)
    a = qf.build_fp(spark.range(50).selectExpr("CAST(id AS STRING) AS k"), spec)
    b = qf.build_fp(spark.range(20).selectExpr("CAST(id AS STRING) AS k"), spec)
    assert sorted(qf.delete(qf.insert(a, b), b).collect()) == sorted(a.collect())
    assert sorted(qf.merge(a, b).collect()) == sorted(qf.merge(b, a).collect())


def test_schedules():
    assert [(t, u) for _, t, u, _ in merge_schedule(8, 2, 1)] == [(1, 1), (2, 2), (1, 1), (3, 4), (1, 1), (2, 2), (1, 1), (4, 8)]
    assert [(t, u) for _, t, u, _ in merge_schedule(6, 2, 2)] == [(1, 1), (1, 2), (2, 3), (1, 1), (1, 2), (3, 6)]
    assert round(sum(x[2] for x in merge_schedule(24, 16, 16)) / 24, 2) == 7.54


def test_one_cluster_answers_a_lookup():
    """Rings with wrapped runs, repeats and hot buckets."""
    r = np.random.default_rng(5)
    for m, n in ((8, 6), (32, 28), (64, 40), (64, 63), (16, 0)):
        for _ in range(10):
            g = np.sort(r.integers(0, m, n))
            rem = r.integers(0, 8, n)
            o = np.lexsort((rem, g))
            payload = qf.pack_ring(g[o], rem[o], m, 3)
            known = set(zip(g.tolist(), rem.tolist(), strict=True))
            assert all(qf.scan_cluster(payload, m, 3, b, x) == ((b, x) in known) for b in range(m) for x in range(8))


def test_strict_delete_and_clashing_columns(spark):
    f = spark.createDataFrame([(1, 2), (5, 1)], "fp long, cnt long")
    gone = spark.createDataFrame([(1, 1), (7, 1)], "fp long, cnt long")
    assert sorted(map(tuple, qf.delete(f, gone).collect())) == [(1, 1), (5, 1)]
    with pytest.raises(ValueError):
        qf.delete(f, gone, strict=True)
    spec = FilterSpec(p=20, slots=1 << 10)
    d = spark.createDataFrame([("a", 7, "x"), (None, 8, "y")], "k string, fp long, hit string")
    out = qf.probe_join(d, qf.build_fp(d, spec), spec)
    assert sorted(map(tuple, out.collect()), key=str) == [("a", 7, "x", True), (None, 8, "y", False)]
