from approxset import registry
from approxset.operators.bloom import PageLocalBloom


def test_page_local_filter_grows_with_the_keys():
    for n in (1500, 150_000, 15_000_000):
        b = PageLocalBloom.for_items(n, 2.0**-9)
        assert 12.9 * n <= b.blocks * b.block_bits <= 13 * n + b.block_bits and b.k == 9


def test_every_structure_has_a_row(spark, sf):
    out = {r["structure"]: r for r in registry.QUERIES["acc_sized_structures"](spark, sf).collect()}
    assert set(out) == {"quotient", "classic", "counting", "write-buffered", "page-local", "layered", "two-tier", "levelled"}
    assert all(r["fn"] == 0 and r["fpr"] < 0.02 for r in out.values())
