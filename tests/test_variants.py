import numpy as np
import pytest

from approxset.operators import variants
from approxset.schema import FilterSpec, FilterSpecMismatch

CODERS = [variants.Sync(1, 1), variants.Sync(16, 2), variants.Sync(64, 5), variants.Reserved(), variants.Ordered()]


def fixtures():
    r = np.random.default_rng(3)
    for per, bits, n in ((16, 2, 10), (64, 3, 60), (64, 3, 63), (256, 5, 0), (256, 5, 1), (256, 4, 230), (1000, 6, 700), (64, 2, 300)):
        for _ in range(20):
            yield per, bits, n, r
    yield 32, 4, -1, r  # all in the last bucket


@pytest.mark.parametrize("coder", CODERS)
def test_round_trip(coder):
    """Also with many zero remainders, repeated items, hot buckets and items behind the last bucket."""
    for per, bits, n, r in fixtures():
        top = (1 << bits) - (2 if isinstance(coder, variants.Reserved) else 1)
        g = r.integers(0, per, n) if n >= 0 else np.full(20, per - 1)
        rem = np.where(r.random(len(g)) < 0.3, 0, r.integers(0, top + 1, len(g)))
        o = np.lexsort((rem, g))
        g, rem = g[o], rem[o]
        m, payload, entries = coder.encode(g, rem, per, bits)
        assert len(payload) == -(-m * (bits + 2) // 8)
        got = coder.decode(m, payload, entries, per, bits)
        back = np.lexsort(got[::-1])
        assert got[0][back].tolist() == g.tolist() and got[1][back].tolist() == rem.tolist()


@pytest.mark.parametrize("coder", CODERS[:3])
def test_lookups_through_entries(coder):
    for per, bits, n, r in fixtures():
        g = r.integers(0, per, n) if n >= 0 else np.full(20, per - 1)
        rem = r.integers(0, 1 << bits, len(g))
        o = np.lexsort((rem, g))
        m, payload, entries = coder.encode(g[o], rem[o], per, bits)
        q, x = (v.ravel() for v in np.meshgrid(np.arange(per), np.arange(1 << bits)))
        known = set(zip(g.tolist(), rem.tolist(), strict=True))
        assert coder.probe(m, payload, entries, per, bits, q, x).tolist() == [p in known for p in zip(q.tolist(), x.tolist(), strict=True)]


def test_merge_refuses_other_widths(spark):
    f = spark.createDataFrame([(1, 1)], "fp long, cnt long")
    a, b = FilterSpec(20, 1 << 10, variant="reserved"), FilterSpec(20, 1 << 11, variant="reserved")
    assert variants.merge_reserved(f, f, a, a).first()["cnt"] == 2
    with pytest.raises(FilterSpecMismatch):
        variants.merge_reserved(f, f, a, b)
