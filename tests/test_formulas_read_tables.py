import duckdb
import pytest
from test_queries import TABLES, rows

from approxset import registry

MOVED = ["capacity_table", "cluster_bounds", "eps_formulas", "lqf_fanout_sweep", "lqf_schedule", "space_curve", "sub_recursive", "var_space_curve", "w10_space_accuracy"]


@pytest.mark.parametrize("name", MOVED)
def test_the_table_decides(spark, sf, name):
    """Equal to the SQL, and another table gives another result."""
    got = {}
    for d in (sf, sf.replace("0.001", "0.01")):
        c = duckdb.connect()
        for t in TABLES:
            c.sql(f"CREATE VIEW {t} AS SELECT * FROM '{d}/{t}.parquet'")
        got[d] = rows(registry.QUERIES[name](spark, d).toPandas())
        assert got[d] == rows(c.sql(registry.ORACLES[name]).df())
    a, b = got.values()
    assert a != b
