import math

import pytest

from approxset import registry


@pytest.mark.parametrize(("column", "flags", "load"), [("quotient", 3, 0.75), ("quotient_half", 3, 0.5), ("quotient_nine_tenths", 3, 0.9), ("two_flags", 2, 0.75), ("two_flags_half", 2, 0.5), ("two_flags_nine_tenths", 2, 0.9)])
def test_every_curve_gives_its_rate(spark, sf, column, flags, load):
    """From the bits of a slot without its flags follows the rate that the row names."""
    n = spark.read.parquet(f"{sf}/orders.parquet").count()
    got = {r["bits"]: r for r in registry.QUERIES["space_curve"](spark, sf).collect()}
    assert sorted(got) == list(range(1, 25))
    for e, r in got.items():
        remainder = r[column] / n * load - flags
        assert math.isclose(load * 2**-remainder, r["eps"], rel_tol=1e-4) and r["eps"] == 2.0**-e
