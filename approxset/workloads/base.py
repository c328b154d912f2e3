"""Registration, and the fragments of SQL that restate the fingerprint in DuckDB."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..schema import FilterSpec

QUERIES: dict = {}
ORACLES: dict = {}


def query(name: str, oracle: str | None = None):
    def put(f):
        QUERIES[name] = f
        if oracle:
            ORACLES[name] = oracle
        return f

    return put


def spec_for(keys: DataFrame, r: int = 9, load: float = 0.75, **more) -> FilterSpec:
    """The least power of two of slots for the keys counted with repeats."""
    n = keys.count()
    q = max(1, math.ceil(math.log2(max(n, 1) / load)))
    return FilterSpec(p=q + r, slots=1 << q, max_load=load, **more)


def count_of(keys: DataFrame) -> int:
    """The keys that are there, with repeats; the key column is read."""
    return keys.filter("k is not null").count()


ORDERS = "SELECT o_orderkey::VARCHAR AS k FROM orders"
LINES = "SELECT l_orderkey::VARCHAR AS k FROM lineitem"
PAIRS = "SELECT l_orderkey::VARCHAR || chr(31) || l_linenumber::VARCHAR AS k FROM lineitem"
TRIPLES = "SELECT l_orderkey::VARCHAR || chr(31) || l_partkey::VARCHAR || chr(31) || l_suppkey::VARCHAR AS k FROM lineitem"
ABSENT = "SELECT (o_orderkey + i * 1000000)::VARCHAR AS k FROM orders, range(1, 5) t(i)"
H60 = "('0x' || substr(md5('k:' || k), 1, 15))::BIGINT"


def fps(keys: str, r: int = 9, load: float = 0.75, name: str = "fps", spec: str = "") -> str:
    """CTEs spec (q, m, width, p) and `name` (fp, cnt) of the keys."""
    spec = spec or f"SELECT greatest(1, ceil(log2(count(*) / {load})))::BIGINT AS q FROM ({keys})"
    return f"""spec AS (SELECT q, pow(2, q)::BIGINT AS m, pow(2, {r})::BIGINT AS width, q + {r} AS p FROM ({spec})),
        {name} AS (SELECT {H60} // pow(2, 60 - p)::BIGINT AS fp, count(*) AS cnt FROM ({keys}), spec WHERE k IS NOT NULL GROUP BY 1)"""


#: CTE slots (i, g, rem, at, slot, shifted, cont, m) of CTEs fps and spec.
SLOTS = """items AS (SELECT fp // width AS g, fp % width AS rem, m, row_number() OVER (ORDER BY fp) - 1 AS i FROM fps, spec, range(1, cnt + 1) t(c)),
        raw AS (SELECT *, i + max(g - i) OVER (ORDER BY i) AS s FROM items),
        over AS (SELECT count(*) FILTER (WHERE s >= m) AS c FROM raw),
        slots AS (SELECT i, g, rem, m, (i + greatest(c, s - i)) % m AS slot, i + greatest(c, s - i) <> g AS shifted, coalesce(lag(g) OVER (ORDER BY i) = g, false) AS cont FROM raw, over)"""
