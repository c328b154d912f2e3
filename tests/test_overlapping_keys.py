import duckdb
import pyarrow as pa
import pyarrow.parquet as pq
import pytest
from test_queries import rows

from approxset import registry


def against_sql(spark, folder, name):
    c = duckdb.connect()
    for f in folder.iterdir():
        c.sql(f"CREATE VIEW {f.stem} AS SELECT * FROM '{f}'")
    assert rows(registry.QUERIES[name](spark, str(folder)).toPandas()) == rows(c.sql(registry.ORACLES[name]).df())


@pytest.mark.parametrize("name", ["bf_probe", "plb_probe", "lyb_probe", "wbf_probe_reads"])
def test_a_key_probed_twice_has_one_answer(spark, tmp_path, name):
    """Orders a million apart: keys shifted by millions meet each other and the keys of lines."""
    keys = [i + j * 1_000_000 for i in range(40) for j in range(3)]
    pq.write_table(pa.table({"o_orderkey": pa.array(keys, pa.int64())}), tmp_path / "orders.parquet")
    pq.write_table(pa.table({"l_orderkey": pa.array(keys[::2], pa.int64())}), tmp_path / "lineitem.parquet")
    against_sql(spark, tmp_path, name)


@pytest.mark.parametrize("name", ["udf_filter_slots", "udf_filter_stats"])
def test_a_large_nation_has_one_ring(spark, tmp_path, name):
    """More customers than a shard's items."""
    n = 40_000
    pq.write_table(pa.table({"c_custkey": pa.array(range(n), pa.int64()), "c_nationkey": pa.array([int(i % 50 == 0) for i in range(n)], pa.int32())}), tmp_path / "customer.parquet")
    against_sql(spark, tmp_path, name)
