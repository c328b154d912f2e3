import numpy as np
import pytest

pytest.importorskip("approxset.llm")
from approxset.llm import licenses


def scan(text):
    import pyarrow as pa

    batch = pa.RecordBatch.from_arrays([pa.array([1]), pa.array([text])], names=["doc_id", "text"])
    return [r for b in licenses._scanner(licenses.TEMPLATES, 3, 3, 6, 0.7)([batch]) for r in b.to_pylist()]


@pytest.mark.parametrize("name", ["MIT-line", "Apache-2.0-line", "ISC"])
@pytest.mark.parametrize("copies", [1, 2, 7])
def test_every_copy_of_a_run(name, copies):
    t = licenses.TEMPLATES[name]
    got = [r for r in scan(" ".join(["before", *[t] * copies, "after"])) if r["license"] == name]
    starts = [len("before ") + i * (len(t) + 1) for i in range(copies)]
    assert sorted(r["start_byte"] for r in got) == starts and {r["coverage"] for r in got} == {1.0}
    assert {r["span"].rstrip(".") for r in got} == {t.rstrip(".")}


@pytest.mark.parametrize("foreign", [4, 8])
def test_insertions_at_thirds(foreign):
    w = licenses.TEMPLATES["MIT"].split()
    more = [f"foreign{i}" for i in range(foreign)]
    third = len(w) // 3
    got = [r for r in scan(" ".join([*w[:third], *more, *w[third : 2 * third], *more, *w[2 * third :]])) if r["license"] == "MIT"]
    assert len(got) == 1 and got[0]["coverage"] > 0.98


def test_alignment_equals_a_plain_one():
    """The row-wise alignment against a cell-by-cell one."""

    def plain(doc, t, diagonal, band):
        low, best = diagonal - band, 0
        s = np.zeros((len(t) + 1, 2 * band + 3), int)
        for i in range(1, len(t) + 1):
            for c in range(1, 2 * band + 2):
                j = i - 1 + low + c - 1
                if 0 <= j < len(doc):
                    s[i, c] = max(0, s[i - 1, c] + (2 if t[i - 1] == doc[j] else -1), s[i - 1, c + 1] - 1, s[i, c - 1] - 1)
                    best = max(best, s[i, c])
        return best

    rng = np.random.default_rng(4)
    for _ in range(200):
        doc, t = rng.integers(0, 4, rng.integers(1, 30)).astype(np.uint64), rng.integers(0, 4, rng.integers(1, 15)).astype(np.uint64)
        d, band = int(rng.integers(-3, 20)), int(rng.integers(1, 6))
        matched, first, last = licenses.align(doc, t, d, band)
        best = plain(doc, t, d, band)
        assert (matched == 0) == (best == 0) and 2 * matched >= best and (not matched or doc[last] in t and doc[first] in t)
