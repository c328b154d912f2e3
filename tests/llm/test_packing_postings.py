import numpy as np
import pytest

pytest.importorskip("approxset.llm")
from approxset.llm import packing


def test_used_up_documents_leave_the_postings():
    """What is left scores as before."""
    rng = np.random.default_rng(2)
    docs = [rng.integers(0, 50, rng.integers(1, 40)).astype(np.uint16) for _ in range(60)]
    index = packing.Shard(docs, np.linspace(0.1, 3, 50).astype(np.float32), 20.0)
    before, size = [index.scores(i) for i in range(60)], len(index.posted)
    alive = rng.random(60) < 0.4
    index.keep(alive)
    assert len(index.posted) < 0.7 * size
    for i in range(60):
        assert (index.scores(i)[alive] == before[i][alive]).all()
