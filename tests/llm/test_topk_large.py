import pytest

pytest.importorskip("approxset.llm")
from approxset.llm import topk


def test_large_vectors_are_never_dropped(spark):
    rows = [(1, [1.0, 2.0]), (2, [1e15, 0.0])]
    with pytest.raises(Exception, match="too long for exact scores"):
        topk.integer_vectors(spark.createDataFrame(rows, "vec_id long, embedding array<double>")).collect()
    edge = [(1, [1.0, 2.0]), (2, [100_000.0, -0.5]), (3, [float("inf"), 0.0]), (4, [float("nan"), 0.0])]
    got = topk.integer_vectors(spark.createDataFrame(edge, "vec_id long, embedding array<double>")).orderBy("id").collect()
    assert [(r["id"], r["v"]) for r in got] == [(1, [256, 512]), (2, [25_600_000, -128])]


def test_groups_without_a_best_score_are_left_out():
    """Queries near one pivot skip the groups near the others; what they get is the same as from all inner products, ties included."""
    import numpy as np

    rng = np.random.default_rng(3)
    centre = rng.normal(size=(4, 16)) * 400
    v = np.floor(np.repeat(centre, 256, axis=0) + rng.integers(-2, 3, (1024, 16)))
    v[40:60] = v[40]
    ids, p = rng.permutation(1024), np.floor(centre)
    q, qid = v[:32], ids[:32]
    s = q @ v.T
    s[np.arange(32), np.arange(32)] = -np.inf
    least = -np.sort(-s, axis=1)[:, 4]
    got = topk.block_top(qid, q, topk._distances(q, p), ids, v, topk.group_table(v, p), 5, least)
    want = [(int(qid[i]), int(ids[j]), int(s[i, j])) for i in range(32) for j in np.lexsort((ids, -s[i]))[:5]]
    assert list(zip(*[x.tolist() for x in got[:3]], strict=True)) == want
    assert got[3] <= 32 * 1024 / 2


def _sent(plan):
    """Bytes that the plan's broadcasts sent."""
    kind = plan.getClass().getSimpleName()
    if kind == "AdaptiveSparkPlanExec":
        return _sent(plan.executedPlan())
    if kind.endswith("QueryStageExec"):
        return _sent(plan.plan())
    own = plan.metrics().apply("dataSize").value() if kind == "BroadcastExchangeExec" else 0
    below = plan.children()
    return own + sum(_sent(below.apply(i)) for i in range(below.size()))


def _vectors(spark, many, dim=64):
    import numpy as np

    rng = np.random.default_rng(7)
    x = np.round(rng.normal(size=(many, dim)), 2)
    x[::7] = x[7]  # ties
    ids = np.arange(many)
    ids[100:120] = 0  # several rows of a query's id
    rows = topk.integer_vectors(spark.createDataFrame([(int(i), v.tolist()) for i, v in zip(ids, x, strict=True)], "vec_id long, embedding array<double>"))
    v = np.floor(256 * x).astype(int)
    want = set()
    for i in np.unique(ids[ids % 50 == 0]):
        s = sorted((-int(v[j] @ v[a]), int(ids[a])) for j in np.flatnonzero(ids == i) for a in np.flatnonzero(ids != i))[:5]
        want |= {(int(i), rank + 1, a, -score) for rank, (score, a) in enumerate(s)}
    return rows, want


def test_queries_are_sent_once_not_once_a_block(spark):
    """What is sent to all tasks must not grow with the candidates: at 600,000 vectors it was 0.5 GB, at the driver."""
    rows, want = _vectors(spark, 2000)
    got = topk.top_k(rows, rows.filter("id % 50 = 0"), 5, block=64)
    assert set(map(tuple, got.collect())) == want
    assert _sent(got._jdf.queryExecution().executedPlan()) < 100 * 64 * 4 * 3


def test_queries_of_several_passes(spark, monkeypatch):
    rows, want = _vectors(spark, 1000)
    monkeypatch.setattr(topk, "SENT", 1)
    got = topk.top_k(rows, rows.filter("id % 50 = 0"), 5, block=16)
    assert sorted(map(tuple, got.collect())) == sorted(want)


def test_few_queries_decide_only_for_groups_they_reach():
    """The same groups as all bounds of all queries give, whether the first queries reach them, the last ones, or none."""
    import numpy as np

    rng = np.random.default_rng(11)
    centre = np.floor(rng.normal(size=(6, 16)) * 400)
    v = np.floor(np.repeat(centre, 128, axis=0) + rng.integers(-2, 3, (768, 16)))
    q = np.concatenate([np.repeat(centre[:1], 20, axis=0), np.repeat(centre[1:3], 30, axis=0)])
    table, qt, floor = topk.group_table(v, centre), topk._distances(q, centre), (q**2).sum(1)[:, None] - 100
    want = (topk.group_bounds(q, qt, table) >= floor).any(axis=0)
    assert topk.reached(q, qt, table, floor).tolist() == want.tolist() and 0 < want.sum() < len(want)
    assert topk.reached(q[:3], qt[:3], table, floor[:3]).tolist() == (topk.group_bounds(q[:3], qt[:3], table) >= floor[:3]).any(axis=0).tolist()
