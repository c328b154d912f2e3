import numpy as np
import pytest

pytest.importorskip("approxset.llm")
import public_tokenizers as P

from approxset.llm import packing

WORDS = "river stone market engine garden winter letter doctor bridge copper island music planet silver forest window".split()


def test_related_documents_share_a_shard(spark):
    """Sixteen vocabularies, dealt over about as many shards: windows hold documents of one vocabulary."""
    rng = np.random.default_rng(2)
    topic = [[f"{a}{b}" for b in rng.choice(WORDS, 40)] for a in WORDS]
    rows = [(i, " ".join(rng.choice(topic[i % 16], 60))) for i in range(640)]
    df = spark.createDataFrame(rows, "doc_id long, text string").repartition(3)
    out = packing.pack(df, P.path("word_bpe_49k.json"), window=1024, shard_tokens=6000).collect()
    assert len({r["sequence_id"] >> 32 for r in out}) >= 10
    windows: dict[int, list[int]] = {}
    for r in out:
        windows.setdefault(r["sequence_id"], []).append(r["doc_id"] % 16)
    same = sum(np.bincount(t).max() for t in windows.values()) / len(out)
    assert same > 0.7
    assert sorted({r["doc_id"] for r in out}) == list(range(640))


def test_copies_are_spread_over_shards():
    v = np.zeros((4000, packing.DIM), np.float32)
    v[:, 0] = 1
    v[:1000] = np.random.default_rng(1).standard_normal((1000, packing.DIM)) / packing.DIM**0.5
    h = np.random.default_rng(3).integers(0, 1 << 63, 4000).astype(np.uint64)
    splits = packing.Splits(v[::4].astype(np.float16), np.ones(1000), h[::4], 10)
    assert np.bincount(splits.leaf(v, h), minlength=10).max() < 800
