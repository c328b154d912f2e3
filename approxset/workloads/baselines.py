"""Bloom-family baselines and accuracy on the given tables."""

from __future__ import annotations

import math

from pyspark.sql import functions as F

from ..functions import formulas as fm
from ..operators import bloom
from ..operators import quotient as qf
from ..sources import tables as src
from .base import ABSENT, H60, LINES, ORDERS, count_of, fps, query, spec_for
from .membership import _probed, orders_filter


def lanes(k: int, key: str = "k") -> str:
    return f"list_transform(range(0, {k}), lambda i: ('0x' || substr(sha256('0:' || {key}) || sha256('1:' || {key}), i * 9 + 1, 9))::BIGINT)"


def bits(keys: str, k: int, m: str, extra: str = "") -> str:
    return f"SELECT {extra} k, unnest({lanes(k)}) % {m} AS bit FROM ({keys}), size"


SIZE9 = "size AS (SELECT greatest(8, ceil(-count(*) * ln(pow(2, -9)) / pow(ln(2), 2)))::BIGINT AS m FROM orders)"
BF = f"WITH {SIZE9}, bits AS ({bits(ORDERS, 9, 'm')}), words AS (SELECT bit // 32 AS word_idx, bit_or(1::BIGINT << (bit % 32)) AS word FROM bits GROUP BY 1)"
PROBED = f"SELECT DISTINCT k FROM ({LINES}) UNION ALL {ABSENT}"
BF_PROBE = BF + f", pb AS ({bits(PROBED, 9, 'm')}), hit AS (SELECT k, bool_and(bit IN (SELECT bit FROM bits)) AS maybe FROM pb GROUP BY k)"


def asked(spark, d):
    """The probed keys, each once: the shifted keys overlap where there are more than a million orders."""
    return _probed(spark, d).distinct()


def orders_bloom(spark, d, kind=bloom.BloomFilter, eps=2.0**-9):
    keys = src.order_keys(spark, d)
    b = bloom.BloomFilter.for_items(keys.count(), eps)
    return kind(b.m, b.k), keys


@query("bf_words", BF + " SELECT word_idx, word::BIGINT AS word FROM words")
def bf_words(spark, d):
    b, keys = orders_bloom(spark, d)
    return b.build(keys)


@query("bf_probe", BF_PROBE + " SELECT k, maybe FROM hit")
def bf_probe(spark, d):
    b, keys = orders_bloom(spark, d)
    return b.probe(asked(spark, d), b.build(keys))


@query("bf_union", BF + " SELECT word_idx, word::BIGINT AS word FROM words")
def bf_union(spark, d):
    b, keys = orders_bloom(spark, d)
    o = src.table(spark, d, "orders")
    return b.union(*[b.build(o.filter(F.col("o_orderstatus") == s).select(src.key_text("o_orderkey").alias("k"))) for s in "FOP"])


@query("bf_params", "SELECT e AS bits, ceil(-count(*) * ln(pow(2, -e)) / pow(ln(2), 2))::BIGINT AS m, e::BIGINT AS k FROM orders, (VALUES (6), (9), (12)) t(e) GROUP BY e")
def bf_params(spark, d):
    n = src.order_keys(spark, d).count()
    return spark.createDataFrame([(e, (b := bloom.BloomFilter.for_items(n, 2.0**-e)).m, b.k) for e in (6, 9, 12)], "bits int, m long, k long")


CELLS = f"cells AS (SELECT bit AS cell, count(*) AS n FROM (SELECT DISTINCT k, bit FROM ({bits(ORDERS, 9, 'm')})) GROUP BY 1)"


@query("cbf_cells", f"WITH {SIZE9}, {CELLS} SELECT cell, least(n, 15) AS c FROM cells")
def cbf_cells(spark, d):
    b, keys = orders_bloom(spark, d, bloom.CountingBloom)
    return b.build(keys)


GONE = "SELECT o_orderkey::VARCHAR AS k FROM orders WHERE o_orderstatus = 'F'"
CBF_DEL = f"""WITH {SIZE9}, {CELLS}, gone AS (SELECT bit AS cell, count(*) AS d FROM (SELECT DISTINCT k, bit FROM ({bits(GONE, 9, 'm')})) GROUP BY 1),
    left_ AS (SELECT cell FROM cells LEFT JOIN gone USING (cell) WHERE n >= 15 OR n > coalesce(d, 0)), pb AS ({bits(ORDERS, 9, 'm')})"""


@query("cbf_delete_probe", CBF_DEL + " SELECT k, bool_and(bit IN (SELECT cell FROM left_)) AS maybe FROM pb GROUP BY k")
def cbf_delete_probe(spark, d):
    b, keys = orders_bloom(spark, d, bloom.CountingBloom)
    gone = src.table(spark, d, "orders").filter("o_orderstatus = 'F'").select(src.key_text("o_orderkey").alias("k"))
    return b.probe(keys, b.delete(b.build(keys), gone))


ARRIVED = f"SELECT k, row_number() OVER (ORDER BY md5(k), k) AS seq FROM ({ORDERS})"


@query("wbf_page_writes", f"""WITH {SIZE9}, a AS ({ARRIVED}), b AS (SELECT (seq - 1) // (SELECT count(*) // 4 FROM orders) AS epoch, unnest({lanes(9)}) % m AS bit FROM a, size)
    SELECT epoch, count(DISTINCT bit // 2048) AS page_writes FROM b GROUP BY 1""")
def wbf_page_writes(spark, d):
    b, keys = orders_bloom(spark, d)
    return bloom.write_buffered_writes(src.arrivals(keys), b, keys.count() // 4, 2048)


def read_sql(probes: str, known: str, page: int, by: str = "k") -> str:
    """CTEs of probes (k, j, bit and what `by` names) against the set bits: hit (bool), reads (pages up to the first clear bit)."""
    return f"""(SELECT {by}, stop IS NULL AS hit, count(DISTINCT bit // {page}) FILTER (WHERE stop IS NULL OR j <= stop) AS reads
        FROM (SELECT *, min(CASE WHEN NOT s THEN j END) OVER (PARTITION BY {by}) AS stop FROM (SELECT *, bit IN (SELECT bit FROM {known}) AS s FROM {probes})) GROUP BY {by}, stop)"""


@query("wbf_probe_reads", BF + f""", pj AS (SELECT k, unnest(range(0, 9)) AS j, unnest({lanes(9)}) % m AS bit FROM ({PROBED}), size)
    SELECT hit AS maybe, count(*) AS probes, sum(reads)::BIGINT AS page_reads FROM {read_sql('pj', 'bits', 2048)} GROUP BY 1""")
def wbf_probe_reads(spark, d):
    """Pages that a lookup reads, by answer: k where present, about two where absent, since it stops at a clear bit."""
    b, keys = orders_bloom(spark, d)
    return b.reads(asked(spark, d), b.build(keys), 2048).groupBy("maybe").agg(F.count("*").alias("probes"), F.sum("reads").alias("page_reads"))


def lane(i: str) -> str:
    return f"('0x' || substr(sha256('0:' || k) || sha256('1:' || k), ({i}) * 9 + 1, 9))::BIGINT"


#: Blocks of 4096 bits for the orders' keys at 1/512, as `PageLocalBloom.for_items` counts them.
BLOCKS = "(SELECT (greatest(8, ceil(-count(*) * ln(pow(2, -9)) / pow(ln(2), 2)))::BIGINT + 4095) // 4096 FROM orders)"
PLB = f"list_transform(range(1, 10), lambda i: {lane('0')} % blocks * 4096 + {lane('i')} % 4096)"
AT = f"{BLOCKS} at_(blocks)"
SEQ = "SELECT k, row_number() OVER (ORDER BY md5(k), k) AS seq FROM (SELECT o_orderkey::VARCHAR AS k FROM orders)"


def orders_local(spark, d):
    keys = src.order_keys(spark, d)
    return bloom.PageLocalBloom.for_items(keys.count(), 2.0**-9), keys


@query("plb_flushes", f"SELECT {lane('0')} % {BLOCKS} AS block, count(*) // 50 AS flushes, count(*) % 50 AS \"left\" FROM ({ORDERS}) GROUP BY 1")
def plb_flushes(spark, d):
    b, keys = orders_local(spark, d)
    return b.flushes(keys, 50)


# the state of the recursion: how many arrivals are in, and per group how many of them had arrived at its last flush
GROUPED = f"""WITH RECURSIVE par AS (SELECT {BLOCKS} AS blocks, ({BLOCKS} + 3) // 4 AS groups, count(*) AS n, count(*) // 15 AS buffer FROM orders),
    a AS (SELECT seq, {lane('0')} % blocks // 4 AS g FROM ({SEQ}), par),
    c AS (SELECT seq, i AS g, sum((a.g = i)::INT) OVER (PARTITION BY i ORDER BY seq) AS c FROM a, par, range(0, groups) t(i)),
    cum AS (SELECT seq, list(c::BIGINT ORDER BY g) AS c FROM c GROUP BY seq),
    f AS (SELECT 0 AS flush, buffer AS t, list_transform(range(0, groups), lambda i: 0::BIGINT) AS last, 0::BIGINT AS g, 0::BIGINT AS items FROM par
        UNION ALL
        SELECT flush + 1, f.t + top, list_transform(range(0, groups), lambda i: CASE WHEN i = pick - 1 THEN c[pick] ELSE last[i + 1] END), pick - 1, top
        FROM (SELECT f.*, cum.c, par.n, par.groups, list_transform(range(0, groups), lambda i: cum.c[i + 1] - f.last[i + 1]) AS h, list_max(h) AS top, list_position(h, top) AS pick FROM f JOIN cum ON cum.seq = f.t, par) f),
    ends AS (SELECT max_by(last, flush) AS last FROM f),
    left_ AS (SELECT i AS g, cum.c[i + 1] - last[i + 1] AS items FROM ends, par JOIN cum ON cum.seq = par.n, range(0, groups) t(i))
    SELECT flush::BIGINT AS flush, g * 4 AS first_block, items FROM f WHERE flush > 0 UNION ALL SELECT 0, g * 4, items FROM left_ WHERE items > 0"""


@query("plb_group_flush", GROUPED)
def plb_group_flush(spark, d):
    """A buffer of a fifteenth of the keys, groups of four blocks."""
    b, keys = orders_local(spark, d)
    return b.group_flushes(src.arrivals(keys), keys.count() // 15, 4).select("flush", "first_block", "items")


@query("plb_probe", f"""WITH set_ AS (SELECT DISTINCT unnest({PLB}) AS bit FROM ({ORDERS}), {AT}), pb AS (SELECT k, unnest({PLB}) AS bit FROM ({PROBED}), {AT})
    SELECT k, bool_and(bit IN (SELECT bit FROM set_)) AS maybe FROM pb GROUP BY k""")
def plb_probe(spark, d):
    b, keys = orders_local(spark, d)
    return b.probe(asked(spark, d), b.build(keys))


@query("plb_delayed_lookups", f"""WITH a AS ({SEQ}) SELECT (seq - 1) // 2000 AS batch, count(*) AS lookups, count(DISTINCT {lane('0')} % {BLOCKS}) AS block_reads FROM a GROUP BY 1""")
def plb_delayed(spark, d):
    """Lookups held back in batches: each batch reads each of its blocks once."""
    b, keys = orders_local(spark, d)
    return b.delayed(src.arrivals(keys), b.build(keys), 2000)[1]


LAYER = "floor(log2(1 + (seq - 1) // 1000) + 1e-9)::BIGINT"


@query("lyb_layers", f"SELECT {LAYER} AS layer, count(*) AS n FROM ({ARRIVED}) GROUP BY 1")
def lyb_layers(spark, d):
    return src.arrivals(src.order_keys(spark, d)).groupBy(bloom.layer_of(F.col("seq"), 1000).alias("layer")).agg(F.count("*").alias("n"))


def layered_bits(key: str, k: int, base: str, per: int = 18, width: int = 9) -> str:
    """The bits of `key` in layer `layer`: a block of 4096 by the first lane, k bits inside it; layers 2^40 bits apart."""
    lane = lambda i: f"('0x' || substr(sha256('0:' || {key}) || sha256('1:' || {key}), ({i}) * {width} + 1, {width}))::BIGINT"
    return f"list_transform(range(1, {k + 1}), lambda i: layer * 1099511627776 + {lane('0')} % (({base} * {per} * pow(2, layer)::BIGINT + 4095) // 4096) * 4096 + {lane('i')} % 4096)"


LYB = f"""WITH a AS (SELECT k, {LAYER} AS layer FROM ({ARRIVED})), b AS (SELECT DISTINCT unnest({layered_bits('k', 12, '1000')}) AS bit FROM a),
    pb AS (SELECT k, layer, unnest({layered_bits('k', 12, '1000')}) AS bit FROM ({PROBED}), (SELECT DISTINCT layer FROM a)),
    hit AS (SELECT k, layer, bool_and(b.bit IS NOT NULL) AS h FROM pb LEFT JOIN b USING (bit) GROUP BY 1, 2)"""


@query("lyb_probe", LYB + " SELECT k, sum(h::INTEGER)::INTEGER AS hits, bool_or(h) AS maybe FROM hit GROUP BY k")
def lyb_probe(spark, d):
    keys = src.order_keys(spark, d)
    arrived, n = src.arrivals(keys), keys.count()
    b = bloom.LayeredBloom(1000, 18, 12)
    return b.probe(asked(spark, d), b.build(arrived, n), b.layers(n))


@query("exact_membership", f"SELECT k, k IN ({ORDERS}) AS present FROM ({PROBED})")
def exact_membership(spark, d):
    known = src.order_keys(spark, d).distinct().withColumn("p", F.lit(True))
    return _probed(spark, d).join(known, "k", "left").select("k", F.coalesce("p", F.lit(False)).alias("present"))


def accuracy(structure, probed, n, times=1):
    """One row: structure, n_inserted, present_probed, fn, absent_probed, fp, fpr. `times`: how many lookups a row stands for."""
    times = F.lit(times) if isinstance(times, int) else times
    z = lambda c: F.coalesce(F.sum(F.when(c, times)), F.lit(0)).cast("long")
    a = probed.agg(z(F.col("present")).alias("present_probed"), z(F.col("present") & ~F.col("maybe")).alias("fn"), z(~F.col("present")).alias("absent_probed"), z(~F.col("present") & F.col("maybe")).alias("fp"))
    return a.select(F.lit(structure).alias("structure"), F.lit(n).cast("long").alias("n_inserted"), "*", F.round(F.try_divide(F.col("fp"), F.col("absent_probed")), 6).alias("fpr"))


ACC = "SELECT '{s}' AS structure, (SELECT count(*) FROM orders) AS n_inserted, count(*) FILTER (WHERE present) AS present_probed, count(*) FILTER (WHERE present AND NOT maybe) AS fn, count(*) FILTER (WHERE NOT present) AS absent_probed, count(*) FILTER (WHERE NOT present AND maybe) AS fp, round(count(*) FILTER (WHERE NOT present AND maybe) / count(*) FILTER (WHERE NOT present), 6) AS fpr FROM "


@query("acc_all_structures", f"""WITH pr AS (SELECT DISTINCT k, true AS present FROM ({LINES}) UNION ALL SELECT k, false FROM ({ABSENT})), {fps(ORDERS)}, {BF_PROBE.removeprefix('WITH ')},
    set_ AS (SELECT DISTINCT unnest({PLB}) AS bit FROM ({ORDERS}), {AT}), plb AS (SELECT k, bool_and(bit IN (SELECT bit FROM set_)) AS maybe FROM (SELECT k, unnest({PLB}) AS bit FROM pr, {AT}) GROUP BY k)
    {ACC.format(s='quotient')} (SELECT present, {H60} // pow(2, 60 - p)::BIGINT IN (SELECT fp FROM fps) AS maybe FROM pr, spec)
    UNION ALL {ACC.format(s='classic')} (SELECT present, maybe FROM pr JOIN hit USING (k))
    UNION ALL {ACC.format(s='page-local')} (SELECT present, maybe FROM pr JOIN plb USING (k))""")
def acc_all(spark, d):
    present = src.line_keys(spark, d).distinct().withColumn("present", F.lit(True))
    df = present.unionByName(src.absent_keys(spark, d).withColumn("present", F.lit(False)))
    spec, f = orders_filter(spark, d)
    b, keys = orders_bloom(spark, d)
    plb = orders_local(spark, d)[0]
    n = keys.count()
    rows = accuracy("quotient", qf.probe_join(df, f, spec), n).unionByName(accuracy("classic", b.probe(df, b.build(keys)), n))
    return rows.unionByName(accuracy("page-local", plb.probe(df, plb.build(keys)), n))


# 1 - (1 - x)^n by the logarithm's first terms: x is small, and 1 - x would lose it
@query("eps_formulas", """WITH c AS (SELECT count(o_orderkey) AS n, greatest(1, ceil(log2(greatest(1, count(o_orderkey)) / 0.75))) AS q FROM orders), e AS (SELECT e, n, pow(2, -(q + e)) AS x FROM c, (VALUES (6), (9), (12)) t(e))
    SELECT e AS bits, round(1 - exp(-n * (x + x * x / 2 + x * x * x / 3)), 9) AS quotient, round(pow(1 - exp(-e * n / (n * e / ln(2))), e), 9) AS bloom, round(n * x, 9) AS bound FROM e""")
def eps_formulas(spark, d):
    """Expected rates of filters over the orders' keys, with 6, 9 and 12 bits of remainder or hash functions."""
    keys = src.order_keys(spark, d)
    n = count_of(keys)
    q = max(1, math.ceil(math.log2(max(n, 1) / 0.75)))
    rows = [(e, round(fm.qf_eps(n, q + e), 9), round(fm.bloom_eps(n, n * e / math.log(2), e), 9) if n else None, round(n / 2 ** (q + e), 9)) for e in (6, 9, 12)]
    return spark.createDataFrame(rows, "bits int, quotient double, bloom double, bound double")


@query("bloom_fill", BF + " SELECT round(sum(bit_count(word)) / max(m), 6) AS fill, round((1 - pow(sum(bit_count(word)) / max(m), 9)) / (1 - sum(bit_count(word)) / max(m)), 6) AS absent_probes FROM words, size")
def bloom_fill(spark, d):
    """Share of set bits, and bits looked at until the first clear one."""
    b, keys = orders_bloom(spark, d)
    rho = F.sum(F.bit_count("word")) / F.lit(b.m)
    return b.build(keys).agg(F.round(rho, 6).alias("fill"), F.round((1 - F.pow(rho, F.lit(b.k))) / (1 - rho), 6).alias("absent_probes"))


@query("bf_jvm")
def bf_jvm(spark, d):
    keys = src.order_keys(spark, d)
    b = bloom.jvm_bloom(keys, "k", keys.count(), 2.0**-9)
    return spark.createDataFrame([(int(b.bitSize()), bool(b.mightContainString("0")))], "bits long, first_key boolean")
