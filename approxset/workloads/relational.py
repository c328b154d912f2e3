"""Relational operators and functions around the filters. Where both engines read the same SQL, one text serves both."""

from __future__ import annotations

import re

from pyspark.sql import Window
from pyspark.sql import functions as F

from ..sources import tables as src
from .base import query

NAMES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


def both(name: str, sql: str, duck: str | None = None):
    """Register one text for Spark (tables in braces) and DuckDB."""

    def run(spark, d):
        used = set(re.findall(r"\{(\w+)\}", sql)) & set(NAMES)
        return spark.sql(sql, **{t: src.table(spark, d, t) for t in used})

    query(name, re.sub(r"\{(\w+)\}", r"\1", duck or sql))(run)


both("scan_pruned", "SELECT l_orderkey, l_quantity FROM {lineitem} WHERE l_quantity > 45 AND l_shipdate < TIMESTAMP '1994-01-01'", "SELECT l_orderkey, l_quantity FROM lineitem WHERE l_quantity > 45 AND l_shipdate < TIMESTAMP '1994-01-01'")
both("scan_filter_logic", "SELECT p_partkey, CASE WHEN p_size BETWEEN 1 AND 15 THEN 'small' WHEN p_size IN (16, 17, 18) THEN 'middle' ELSE 'large' END AS band, coalesce(nullif(p_brand, 'Brand#11'), 'none') AS brand FROM {part} WHERE p_type LIKE '%A%' OR p_retailprice > 1000")
both("join_inner", "SELECT o_orderkey, count(*) AS n, round(sum(l_extendedprice), 2) AS price FROM {orders} JOIN {lineitem} ON o_orderkey = l_orderkey GROUP BY o_orderkey")
both("join_left", "SELECT c_custkey, count(o_orderkey) AS n FROM {customer} LEFT JOIN {orders} ON c_custkey = o_custkey GROUP BY c_custkey")
both("join_right", "SELECT o_orderkey, count(l_orderkey) AS n FROM {lineitem} RIGHT JOIN {orders} ON o_orderkey = l_orderkey GROUP BY o_orderkey")
both("join_full", "SELECT coalesce(s_nationkey, c_nationkey) AS nation, s, c FROM (SELECT s_nationkey, count(*) AS s FROM {supplier} GROUP BY s_nationkey) FULL JOIN (SELECT c_nationkey, count(*) AS c FROM {customer} GROUP BY c_nationkey) ON s_nationkey = c_nationkey")
both("join_semi", "SELECT o_orderkey FROM {orders} WHERE EXISTS (SELECT 1 FROM {lineitem} WHERE l_orderkey = o_orderkey AND l_quantity > 49)")
both("join_anti", "SELECT o_orderkey FROM {orders} WHERE NOT EXISTS (SELECT 1 FROM {lineitem} WHERE l_orderkey = o_orderkey)")
both("join_theta", "SELECT s_suppkey, count(*) AS richer FROM {supplier} JOIN {customer} ON s_nationkey = c_nationkey AND c_acctbal > s_acctbal GROUP BY s_suppkey")
both("join_cross", "SELECT r_name, n_name FROM {region} CROSS JOIN {nation}")
both("join_interval", "SELECT a.event_id AS click, b.event_id AS purchase FROM {events} a JOIN {events} b ON a.user_id = b.user_id AND a.event_type = 'click' AND b.event_type = 'purchase' AND b.ts >= a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR", "SELECT a.event_id AS click, b.event_id AS purchase FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_type = 'click' AND b.event_type = 'purchase' AND b.ts BETWEEN a.ts AND a.ts + INTERVAL 1 HOUR")
both("agg_hash", "SELECT l_returnflag, l_linestatus, count(*) AS n, round(sum(l_quantity), 2) AS quantity, round(avg(l_discount), 6) AS discount FROM {lineitem} GROUP BY l_returnflag, l_linestatus")
both("agg_distinct", "SELECT l_returnflag, count(DISTINCT l_orderkey) AS orders_, count(DISTINCT l_partkey) AS parts FROM {lineitem} GROUP BY l_returnflag")
both("agg_rollup", "SELECT o_orderstatus AS status, o_orderpriority AS priority, count(*) AS n FROM {orders} GROUP BY ROLLUP (o_orderstatus, o_orderpriority)")
both("agg_cube", "SELECT o_orderstatus AS status, o_orderpriority AS priority, count(*) AS n FROM {orders} GROUP BY CUBE (o_orderstatus, o_orderpriority)")
both("agg_gsets", "SELECT o_orderstatus AS status, o_orderpriority AS priority, count(*) AS n FROM {orders} GROUP BY GROUPING SETS ((o_orderstatus), (o_orderpriority), ())")
both("agg_stats", "SELECT o_orderstatus AS status, round(stddev_samp(o_totalprice), 2) AS sd, round(median(o_totalprice), 2) AS med, max_by(o_orderkey, o_totalprice) AS top FROM {orders} GROUP BY o_orderstatus", "SELECT o_orderstatus AS status, round(stddev_samp(o_totalprice), 2) AS sd, round(median(o_totalprice), 2) AS med, arg_max(o_orderkey, o_totalprice) AS top FROM orders GROUP BY o_orderstatus")
both("agg_bits", "SELECT user_id, bit_or(event_id) AS any_, bit_and(event_id) AS all_, bit_xor(event_id) AS odd FROM {events} GROUP BY user_id")
both("win_rank", "SELECT event_id, row_number() OVER w AS rn, rank() OVER w AS rk, dense_rank() OVER w AS dr, CAST(ntile(4) OVER w AS INT) AS nt FROM {events} WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)", "SELECT event_id, (row_number() OVER w)::INT AS rn, (rank() OVER w)::INT AS rk, (dense_rank() OVER w)::INT AS dr, (ntile(4) OVER w)::INT AS nt FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)")
both("win_offset", "SELECT event_id, lag(event_id) OVER w AS before_, lead(event_id) OVER w AS after_, first_value(event_id) OVER w AS first_ FROM {events} WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)")
both("win_frame_rows", "SELECT o_orderkey, round(sum(o_totalprice) OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey ROWS BETWEEN 2 PRECEDING AND CURRENT ROW), 2) AS sliding FROM {orders}")
both("win_frame_range", "SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY event_id RANGE BETWEEN 100 PRECEDING AND CURRENT ROW) AS near FROM {events}")
both("win_islands", "SELECT user_id, count(*) AS sessions FROM (SELECT user_id, event_id - lag(event_id) OVER (PARTITION BY user_id ORDER BY event_id) AS gap FROM {events}) WHERE gap IS NULL OR gap > 200 GROUP BY user_id")
both("sort_multi", "SELECT o_orderkey, row_number() OVER (ORDER BY o_orderpriority DESC, o_orderkey) AS position FROM {orders} WHERE o_totalprice > 150000", "SELECT o_orderkey, (row_number() OVER (ORDER BY o_orderpriority DESC, o_orderkey))::INT AS position FROM orders WHERE o_totalprice > 150000")
both("topk_suppliers", "SELECT l_suppkey, round(sum(l_extendedprice), 2) AS revenue FROM {lineitem} GROUP BY l_suppkey ORDER BY revenue DESC, l_suppkey LIMIT 10")
both("topk_per_group", "SELECT o_custkey, o_orderkey FROM (SELECT o_custkey, o_orderkey, row_number() OVER (PARTITION BY o_custkey ORDER BY o_totalprice DESC, o_orderkey) AS rn FROM {orders}) WHERE rn <= 2")
both("set_union", "SELECT l_partkey AS k FROM {lineitem} WHERE l_returnflag = 'R' UNION SELECT l_partkey FROM {lineitem} WHERE l_linestatus = 'O'")
both("set_union_all", "SELECT o_custkey AS k FROM {orders} UNION ALL SELECT c_custkey FROM {customer}")
both("set_intersect", "SELECT l_partkey AS k FROM {lineitem} WHERE l_returnflag = 'R' INTERSECT SELECT l_partkey FROM {lineitem} WHERE l_returnflag = 'A'")
both("set_intersect_all", "SELECT o_custkey AS k FROM {orders} INTERSECT ALL SELECT c_custkey FROM {customer}")
both("set_except", "SELECT o_orderkey AS k FROM {orders} EXCEPT SELECT l_orderkey FROM {lineitem}")
both("set_except_all", "SELECT o_custkey AS k FROM {orders} EXCEPT ALL SELECT c_custkey FROM {customer}")
both("sub_scalar", "SELECT o_orderkey FROM {orders} WHERE o_totalprice > (SELECT avg(o_totalprice) * 1.5 FROM {orders})")
both("sub_correlated", "SELECT o_orderkey FROM {orders} o WHERE o_totalprice > (SELECT avg(i.o_totalprice) FROM {orders} i WHERE i.o_custkey = o.o_custkey)")
both("sub_lateral", "SELECT c_custkey, t.n FROM {customer}, LATERAL (SELECT count(*) AS n FROM {orders} WHERE o_custkey = c_custkey) t")
both("sub_cte", "WITH big AS (SELECT l_orderkey, sum(l_quantity) AS q FROM {lineitem} GROUP BY l_orderkey HAVING sum(l_quantity) > 150) SELECT count(*) AS n FROM big JOIN {orders} ON l_orderkey = o_orderkey")
both("sub_recursive", "WITH RECURSIVE s(e, u) AS (SELECT 1, 1 UNION ALL SELECT e + 1, (e + 1) & -(e + 1) FROM s WHERE e < 24) SELECT e, u, count(*) AS items FROM s JOIN {orders} ON o_orderkey % 24 + 1 = e GROUP BY e, u")
both("fn_string", "SELECT page_id, lower(substr(url, 1, 12)) AS head, length(url) AS n, regexp_replace(url, '[0-9]+', '#') AS shape, split_part(url, '/', 3) AS host FROM {pages}", "SELECT page_id, lower(substr(url, 1, 12)) AS head, length(url)::INT AS n, regexp_replace(url, '[0-9]+', '#', 'g') AS shape, split_part(url, '/', 3) AS host FROM pages")
both("fn_hash", "SELECT doc_id, md5(text) AS m, sha1(text) AS s1, sha2(text, 256) AS s2 FROM {documents}", "SELECT doc_id, md5(text) AS m, sha1(text) AS s1, sha256(text) AS s2 FROM documents")
both("fn_date", "SELECT CAST(year(o_orderdate) AS INT) AS y, CAST(quarter(o_orderdate) AS INT) AS q, count(*) AS n FROM {orders} GROUP BY 1, 2")
both("fn_math", "SELECT s_suppkey, round(ln(abs(s_acctbal) + 1), 6) AS l, round(pow(s_acctbal, 2), 2) AS p, CAST(floor(s_acctbal / 7) AS BIGINT) AS f, s_suppkey & 7 AS b FROM {supplier}")
both("fn_array", "SELECT vec_id, round(aggregate(transform(embedding, x -> cast(x as double) * x), 0D, (a, x) -> a + x), 4) AS norm FROM {embeddings}", "SELECT vec_id, round(list_sum(list_transform(embedding, lambda x: x::DOUBLE * x)), 4) AS norm FROM embeddings")
both("fn_map", "SELECT user_id, map_from_entries(collect_list(struct(event_type, n)))['click'] AS clicks FROM (SELECT user_id, event_type, count(*) AS n FROM {events} GROUP BY user_id, event_type) GROUP BY user_id", "SELECT user_id, max(CASE WHEN event_type = 'click' THEN n END) AS clicks FROM (SELECT user_id, event_type, count(*) AS n FROM events GROUP BY user_id, event_type) GROUP BY user_id")
both("fn_json", "SELECT event_id, CAST(get_json_object(props, '$.k') AS BIGINT) AS k FROM {events}", "SELECT event_id, (props ->> '$.k')::BIGINT AS k FROM events")
both("fn_null", "SELECT event_id, coalesce(nullif(event_type, 'view'), 'other') AS t, try_cast(props AS INT) AS bad FROM {events}")


@query("fn_sqlfn", "SELECT o_orderkey, ('0x' || substr(md5('k:' || o_orderkey::VARCHAR), 1, 15))::BIGINT // 1048576 AS quotient FROM orders")
def fn_sqlfn(spark, d):
    """The registered SQL functions, inlined by Catalyst."""
    from ..functions.fingerprint import register

    register(spark)
    return spark.sql("SELECT o_orderkey, quotient_of(hash60(CAST(o_orderkey AS STRING)), 1048576) AS quotient FROM {orders}", orders=src.table(spark, d, "orders"))


@query("join_range", "SELECT a.p_partkey AS k, count(*) AS n FROM part a JOIN (SELECT i * 10 AS lo, i * 10 + 12 AS hi FROM range(0, 6) t(i)) b ON a.p_size BETWEEN lo AND hi GROUP BY 1")
def join_range(spark, d):
    """A range join through bins of width 10."""
    bands = spark.range(6).select((F.col("id") * 10).alias("lo"), (F.col("id") * 10 + 12).alias("hi"))
    bins = bands.select("*", F.explode(F.sequence(F.call_function("div", F.col("lo"), F.lit(10).cast("long")), F.call_function("div", F.col("hi"), F.lit(10).cast("long")))).alias("bin"))
    p = src.table(spark, d, "part").select("p_partkey", "p_size", F.call_function("div", F.col("p_size").cast("long"), F.lit(10).cast("long")).alias("bin"))
    return p.join(bins, "bin").filter("p_size between lo and hi").groupBy(F.col("p_partkey").alias("k")).agg(F.count("*").alias("n"))


@query("join_asof", "SELECT p.event_id AS purchase, max(c.event_id) AS prior FROM events p LEFT JOIN events c ON c.user_id = p.user_id AND c.event_type = 'click' AND c.event_id < p.event_id WHERE p.event_type = 'purchase' GROUP BY 1")
def join_asof(spark, d):
    """The latest click before each purchase: one window, no join."""
    e = src.table(spark, d, "events").filter(F.col("event_type").isin("click", "purchase"))
    w = Window.partitionBy("user_id").orderBy("event_id").rowsBetween(Window.unboundedPreceding, -1)
    return e.withColumn("prior", F.last(F.when(F.col("event_type") == "click", F.col("event_id")), ignorenulls=True).over(w)).filter("event_type = 'purchase'").select(F.col("event_id").alias("purchase"), "prior")


@query("join_salted", "SELECT s_nationkey AS nation, count(*) AS n, round(sum(l_quantity), 2) AS quantity FROM lineitem JOIN supplier ON l_suppkey = s_suppkey GROUP BY 1")
def join_salted(spark, d):
    salt = 8
    li = src.table(spark, d, "lineitem").select("l_suppkey", "l_quantity", F.pmod(F.xxhash64("l_orderkey", "l_linenumber"), F.lit(salt)).alias("salt"))
    s = src.table(spark, d, "supplier").select("s_suppkey", "s_nationkey", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(salt - 1).cast("long"))).alias("salt"))
    j = li.hint("merge").join(s, (F.col("l_suppkey") == F.col("s_suppkey")) & (li["salt"] == s["salt"]))
    return j.groupBy(F.col("s_nationkey").alias("nation")).agg(F.count("*").alias("n"), F.round(F.sum("l_quantity"), 2).alias("quantity"))


@query("agg_pivot", "SELECT o_orderpriority AS priority, count(*) FILTER (WHERE o_orderstatus = 'F') AS \"F\", count(*) FILTER (WHERE o_orderstatus = 'O') AS \"O\", count(*) FILTER (WHERE o_orderstatus = 'P') AS \"P\" FROM orders GROUP BY 1")
def agg_pivot(spark, d):
    return src.table(spark, d, "orders").groupBy(F.col("o_orderpriority").alias("priority")).pivot("o_orderstatus", ["F", "O", "P"]).count().na.fill(0)


@query("agg_unpivot", "SELECT l_orderkey AS k, l_linenumber AS line, 'tax' AS name, l_tax AS value FROM lineitem UNION ALL SELECT l_orderkey, l_linenumber, 'discount', l_discount FROM lineitem")
def agg_unpivot(spark, d):
    li = src.table(spark, d, "lineitem").select(F.col("l_orderkey").alias("k"), F.col("l_linenumber").alias("line"), F.col("l_tax").alias("tax"), F.col("l_discount").alias("discount"))
    return li.unpivot(["k", "line"], ["tax", "discount"], "name", "value")


@query("agg_approx")
def agg_approx(spark, d):
    return src.table(spark, d, "lineitem").agg(F.approx_count_distinct("l_orderkey").alias("orders_"), F.hll_sketch_estimate(F.hll_sketch_agg("l_partkey")).alias("parts"))


@query("sample_hash", "SELECT doc_id FROM documents WHERE ('0x' || substr(md5('k:' || doc_id::VARCHAR), 1, 15))::BIGINT < pow(2, 60)::BIGINT // 10")
def sample_hash(spark, d):
    """A repeatable tenth, by threshold on the hash."""
    from ..functions.fingerprint import hash60

    return src.table(spark, d, "documents").filter(hash60(F.col("doc_id").cast("string")) < (1 << 60) // 10).select("doc_id")


@query("scan_formats", "SELECT n_nationkey, n_name, n_regionkey FROM nation")
def scan_formats(spark, d):
    """CSV, JSON and ORC round trips, equal to each other."""
    from ..cluster import work_folder

    n, base = src.table(spark, d, "nation"), work_folder(spark)
    out = []
    for kind in ("csv", "json", "orc"):
        n.write.mode("overwrite").format(kind).save(f"{base}/{kind}")
        out.append(spark.read.schema(n.schema).format(kind).load(f"{base}/{kind}"))
    return out[0].intersect(out[1]).intersect(out[2])


@query("scan_parquet_bloom", "SELECT l_orderkey, count(*) AS n FROM lineitem WHERE l_orderkey IN (SELECT l_orderkey FROM lineitem WHERE l_quantity > 49) GROUP BY 1")
def scan_parquet_bloom(spark, d):
    """Parquet's own Bloom filter on a column, written beside the pages and used to skip row groups."""
    from ..cluster import work_folder

    path = f"{work_folder(spark)}/lines"
    li = src.table(spark, d, "lineitem").select("l_orderkey", "l_quantity")
    li.write.option("parquet.bloom.filter.enabled#l_orderkey", "true").parquet(path)
    stored = spark.read.schema(li.schema).parquet(path)
    return stored.join(stored.filter("l_quantity > 49").select("l_orderkey"), "l_orderkey", "left_semi").groupBy("l_orderkey").agg(F.count("*").alias("n"))
