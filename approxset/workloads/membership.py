"""Fingerprints and quotient filters on the given tables."""

from __future__ import annotations


from pyspark.sql import functions as F

from ..cluster import work_folder
from ..functions import fingerprint as fpf
from ..operators import quotient as qf
from ..operators import variants
from ..schema import FilterSpec
from ..sources import tables as src
from .base import ABSENT, H60, LINES, ORDERS, PAIRS, SLOTS, fps, query, spec_for


def orders_filter(spark, d, r=9):
    keys = src.order_keys(spark, d)
    spec = spec_for(keys, r)
    return spec, qf.build_fp(keys, spec)


def lines_filter(spark, d, r=9):
    keys = src.line_keys(spark, d)
    spec = spec_for(keys, r)
    return spec, qf.build_fp(keys, spec)


def status_filter(spark, d, spec, *status):
    keys = src.table(spark, d, "orders").filter(F.col("o_orderstatus").isin(*status)).select(src.key_text("o_orderkey").alias("k"))
    return qf.build_fp(keys, spec)


def _status(s: str, name: str) -> str:
    return f"{name} AS (SELECT {H60} // pow(2, 60 - p)::BIGINT AS fp, count(*) AS cnt FROM (SELECT o_orderkey::VARCHAR AS k FROM orders WHERE o_orderstatus IN ({s})), spec GROUP BY 1)"


SPEC_ORDERS = "SELECT greatest(1, ceil(log2(count(*) / 0.75)))::BIGINT AS q FROM orders"


@query("fp_orders", f"WITH {fps(ORDERS)} SELECT fp, cnt FROM fps")
def fp_orders(spark, d):
    return orders_filter(spark, d)[1]


@query("fp_multiset_lineitem", f"WITH {fps(LINES)} SELECT fp, cnt FROM fps")
def fp_multiset(spark, d):
    return lines_filter(spark, d)[1]


@query("fp_roundtrip", f"WITH {fps(ORDERS)} SELECT fp, fp // width AS quotient, fp % width AS remainder, fp AS rejoined FROM fps, spec")
def fp_roundtrip(spark, d):
    spec, f = orders_filter(spark, d)
    g, r = fpf.quotient_of(F.col("fp"), spec), fpf.remainder_of(F.col("fp"), spec)
    return f.select("fp", g.alias("quotient"), r.alias("remainder"), fpf.rejoin(g, r, spec).alias("rejoined"))


@query("fp_general_slots", f"""WITH s AS (SELECT count(*) * 10 // 9 AS m FROM orders), w AS (SELECT (pow(2, 40)::BIGINT + m - 1) // m AS width FROM s)
    SELECT {H60} // pow(2, 20)::BIGINT // width AS quotient, count(*) AS n FROM ({ORDERS}), w GROUP BY 1""")
def fp_general_slots(spark, d):
    keys = src.order_keys(spark, d)
    spec = FilterSpec(p=40, slots=keys.count() * 10 // 9)
    return keys.groupBy(fpf.quotient_of(fpf.fingerprint(F.col("k"), spec), spec).alias("quotient")).agg(F.count("*").alias("n"))


@query("fp_collisions", f"""WITH {fps(ORDERS, 6)}, q AS (SELECT fp // width AS g, count(*) AS f, sum(cnt) AS keys, sum(CASE WHEN cnt > 1 THEN cnt ELSE 0 END) AS hard FROM fps, spec GROUP BY 1)
    SELECT sum(keys)::BIGINT AS n_keys, sum(f)::BIGINT AS n_fps, sum(hard)::BIGINT AS hard_keys, sum(CASE WHEN f > 1 THEN f ELSE 0 END)::BIGINT AS soft_fps FROM q""")
def fp_collisions(spark, d):
    keys = src.order_keys(spark, d)
    return fpf.collisions(keys, spec_for(keys, 6))


LANES = "list_transform(range(0, 12), lambda i: ('0x' || substr(sha256('0:' || k) || sha256('1:' || k), i * 9 + 1, 9))::BIGINT)"


@query("digest_lanes_orders", f"SELECT k, array_to_string({LANES}, ',') AS lanes FROM ({ORDERS})")
def digest_lanes(spark, d):
    return src.order_keys(spark, d).select("k", F.array_join(F.transform(fpf.digest_lanes(F.col("k"), 12), lambda x: x.cast("string")), ",").alias("lanes"))


@query("spec_sizing", """SELECT e AS bits, greatest(1, ceil(log2(count(*) / 0.75)))::BIGINT AS q, greatest(1, ceil(log2(count(*)::DOUBLE / pow(2, greatest(1, ceil(log2(count(*) / 0.75)))) * pow(2, e))))::BIGINT AS r
    FROM orders, (VALUES (6), (9), (12)) t(e) GROUP BY e""")
def spec_sizing(spark, d):
    n = src.order_keys(spark, d).count()
    rows = [(e, (s := FilterSpec.for_items(n, 2.0**-e)).q, s.r) for e in (6, 9, 12)]
    return spark.createDataFrame(rows, "bits int, q long, r long")


@query("qf_buckets", f"WITH {fps(LINES)} SELECT fp // width AS quotient, string_agg((fp % width)::VARCHAR, ',' ORDER BY fp % width) AS remainders, count(*) AS n FROM fps, spec, range(1, cnt + 1) GROUP BY 1")
def qf_buckets(spark, d):
    spec, f = lines_filter(spark, d)
    return qf.as_buckets(f, spec)


SLOT_OUT = "SELECT slot, rem AS remainder, slot IN (SELECT g FROM items) AS occupied, shifted, cont AS continuation FROM slots"
SLOT_COLS = ("slot", "remainder", "occupied", "shifted", "continuation")


@query("qf_slots", f"WITH {fps(ORDERS)}, {SLOTS} {SLOT_OUT}")
def qf_slots(spark, d):
    spec, f = orders_filter(spark, d)
    return qf.as_slots(f, spec).select(*SLOT_COLS)


@query("qf_slots_wrapped", f"WITH {fps(ORDERS, 9, 0.75, 'fps', 'SELECT ceil(log2(count(*) / 0.98))::BIGINT AS q FROM orders')}, {SLOTS} {SLOT_OUT}")
def qf_slots_wrapped(spark, d):
    """Nearly full where the key count allows: runs wrap round the ring."""
    keys = src.order_keys(spark, d)
    spec = spec_for(keys, 9, 0.98)
    return qf.as_slots(qf.build_fp(keys, spec), spec).select(*SLOT_COLS)


@query("qf_invariants", "SELECT v AS rule, 0::BIGINT AS violations FROM (VALUES ('occupied bucket without run'), ('unshifted item off its bucket'), ('continuation without predecessor'), ('slot used twice')) t(v)")
def qf_invariants(spark, d):
    """Violations of the layout's rules: all zero."""
    spec, f = lines_filter(spark, d)
    s = qf.as_slots(f, spec)
    runs = s.filter("used and not continuation").count()
    after = s.filter("used").select(F.pmod(F.col("slot") + 1, F.lit(spec.slots)).alias("slot"))
    rows = [
        ("occupied bucket without run", abs(s.filter("occupied").count() - runs)),
        ("unshifted item off its bucket", s.filter("used and not shifted and not continuation and not occupied").count()),
        ("continuation without predecessor", s.filter("continuation").join(after, "slot", "left_anti").count()),
        ("slot used twice", s.groupBy("slot").count().filter("count > 1").count()),
    ]
    return spark.createDataFrame(rows, "rule string, violations long")


@query("qf_packed_decode", f"WITH {fps(LINES)} SELECT fp, cnt FROM fps")
def qf_packed_decode(spark, d):
    spec, f = lines_filter(spark, d)
    n = qf.shards_of(spec, spec.slots)
    return qf.unpack(qf.pack(f, spec, n), spec, n)


@query("qf_slots_decode", f"WITH {fps(ORDERS)} SELECT fp, cnt FROM fps")
def qf_slots_decode(spark, d):
    spec, f = orders_filter(spark, d)
    return qf.decode(qf.as_slots(f, spec), spec)


PROBE = f"WITH {fps(ORDERS)} SELECT k, {H60} // pow(2, 60 - p)::BIGINT IN (SELECT fp FROM fps) AS maybe FROM (SELECT DISTINCT k FROM ({LINES}) UNION ALL {ABSENT}), spec"


def _probed(spark, d):
    return src.line_keys(spark, d).distinct().unionByName(src.absent_keys(spark, d))


@query("qf_probe_join", PROBE)
def qf_probe_join(spark, d):
    spec, f = orders_filter(spark, d)
    return qf.probe_join(_probed(spark, d), f, spec)


@query("qf_probe_broadcast", PROBE)
def qf_probe_broadcast(spark, d):
    spec, f = orders_filter(spark, d)
    n = qf.shards_of(spec, spec.slots)
    return qf.probe_broadcast(_probed(spark, d), qf.pack(f, spec, n), spec, n)


@query("qf_probe_shard", PROBE)
def qf_probe_shard(spark, d):
    spec, f = orders_filter(spark, d)
    n = qf.shards_of(spec, spec.slots, 1 << 12)
    return qf.probe_shard(_probed(spark, d), qf.pack(f, spec, n), spec, n)


@query("qf_probe_empty_bucket", f"""WITH {fps(ORDERS)}, b AS (SELECT DISTINCT fp // width AS g FROM fps, spec), a AS (SELECT {H60} // pow(2, 60 - p)::BIGINT AS f, width FROM ({ABSENT}), spec)
    SELECT count(*) AS probed, count(*) FILTER (WHERE f // width NOT IN (SELECT g FROM b)) AS empty_bucket, count(*) FILTER (WHERE f IN (SELECT fp FROM fps)) AS maybe FROM a""")
def qf_probe_empty_bucket(spark, d):
    """Lookups that end at a clear bucket flag."""
    spec, f = orders_filter(spark, d)
    a = src.absent_keys(spark, d).select(fpf.fingerprint(F.col("k"), spec).alias("fp")).withColumn("g", fpf.quotient_of(F.col("fp"), spec))
    b = f.select(fpf.quotient_of(F.col("fp"), spec).alias("g")).distinct().withColumn("occ", F.lit(1))
    j = a.join(b, "g", "left").join(f.select("fp", F.lit(1).alias("hit")), "fp", "left")
    return j.agg(F.count("*").alias("probed"), F.count(F.when(F.col("occ").isNull(), 1)).alias("empty_bucket"), F.count("hit").alias("maybe"))


SPECQ = f"spec AS (SELECT q, pow(2, q)::BIGINT AS m, pow(2, 9)::BIGINT AS width, q + 9 AS p FROM ({SPEC_ORDERS}))"


def _sets(*parts):
    return f"WITH {SPECQ}, " + ", ".join(_status(s, n) for s, n in parts)


@query("qf_insert", _sets(("'F','O'", "fps")) + " SELECT fp, cnt FROM fps")
def qf_insert(spark, d):
    spec = spec_for(src.order_keys(spark, d))
    return qf.insert(status_filter(spark, d, spec, "F"), status_filter(spark, d, spec, "O"))


@query("qf_delete", _sets(("'O','P'", "fps")) + " SELECT fp, cnt FROM fps")
def qf_delete(spark, d):
    spec, f = orders_filter(spark, d)
    return qf.delete(f, status_filter(spark, d, spec, "F"))


@query("qf_set_mode", f"WITH {fps(LINES)} SELECT fp, 1::BIGINT AS cnt FROM fps")
def qf_set_mode(spark, d):
    keys = src.line_keys(spark, d)
    return qf.build_fp(keys, spec_for(keys, mode="set"))


@query("qf_traverse", f"WITH {fps(ORDERS)} SELECT fp, cnt, row_number() OVER (ORDER BY fp) - 1 AS position FROM fps")
def qf_traverse(spark, d):
    """In fingerprint order, from range partitions with their bases."""
    spec, f = orders_filter(spark, d)
    from pyspark.sql import Window

    f = f.withColumn("range", F.call_function("div", fpf.quotient_of(F.col("fp"), spec) * 64, F.lit(spec.slots).cast("long")))
    n = f.groupBy("range").agg(F.count("*").alias("n"))
    base = n.select("range", (F.sum("n").over(Window.orderBy("range")) - F.col("n")).alias("base"))
    i = F.row_number().over(Window.partitionBy("range").orderBy("fp")) - 1
    return f.withColumn("i", i).join(F.broadcast(base), "range").select("fp", "cnt", (F.col("base") + F.col("i")).alias("position"))


def _resized(by):
    return f"WITH {fps(ORDERS, 9 - by, 0.75, 'fps', f'SELECT q + {by} AS q FROM ({SPEC_ORDERS})')} SELECT fp // width AS quotient, count(*) AS n FROM fps, spec GROUP BY 1"


for _name, _by in (("qf_resize_up", 2), ("qf_resize_down", -1)):

    @query(_name, _resized(_by))
    def _(spark, d, by=_by):
        spec, f = orders_filter(spark, d)
        return f.groupBy(fpf.quotient_of(F.col("fp"), spec.resized(by)).alias("quotient")).agg(F.count("*").alias("n"))


@query("qf_merge_two", _sets(("'F','P'", "fps")) + " SELECT fp, cnt FROM fps")
def qf_merge_two(spark, d):
    spec = spec_for(src.order_keys(spark, d))
    return qf.merge(status_filter(spark, d, spec, "F"), status_filter(spark, d, spec, "P"))


@query("qf_merge_three_sizes", f"WITH {fps(ORDERS)} SELECT fp, cnt FROM fps")
def qf_merge_three(spark, d):
    """Filters of three slot counts, packed each in its own, merged and unpacked."""
    spec = spec_for(src.order_keys(spark, d))
    parts = []
    for status, by in (("F", 0), ("O", -1), ("P", 1)):
        s = spec.resized(by)
        parts.append(qf.unpack(qf.pack(status_filter(spark, d, spec, status), s, 8), s, 8))
    return qf.merge(*parts)


@query("qf_intersect", _sets(("'F','O'", "a"), ("'O','P'", "b")) + " SELECT a.fp, least(a.cnt, b.cnt) AS cnt FROM a JOIN b ON a.fp = b.fp")
def qf_intersect(spark, d):
    spec = spec_for(src.order_keys(spark, d))
    return qf.intersect_filters(status_filter(spark, d, spec, "F", "O"), status_filter(spark, d, spec, "O", "P"))


@query("qf_subtract", _sets(("'F','O'", "a"), ("'O','P'", "b")) + " SELECT a.fp, a.cnt - coalesce(b.cnt, 0) AS cnt FROM a LEFT JOIN b ON a.fp = b.fp WHERE a.cnt > coalesce(b.cnt, 0)")
def qf_subtract(spark, d):
    spec = spec_for(src.order_keys(spark, d))
    return qf.subtract_filters(status_filter(spark, d, spec, "F", "O"), status_filter(spark, d, spec, "O", "P"))


@query("qf_save_load", f"WITH {fps(LINES)} SELECT fp, cnt FROM fps")
def qf_save_load(spark, d):
    spec, f = lines_filter(spark, d)
    path = f"{work_folder(spark)}/packed"
    qf.save(qf.pack(f, spec, 8), spec, 8, path)
    packed, found, shards = qf.load(spark, path, spec)
    return qf.unpack(packed, found, shards)


@query("qf_source", f"WITH {fps(ORDERS)} SELECT fp, cnt FROM fps")
def qf_source(spark, d):
    """A stored filter through the data source format."""
    from ..sources import filters

    spec, f = orders_filter(spark, d)
    path = f"{work_folder(spark)}/packed"
    qf.save(qf.pack(f, spec, 8), spec, 8, path)
    filters.register(spark)
    return spark.read.format("approxfilter").load(path)


@query("qf_bucketed", f"""WITH {fps(ORDERS)}, l AS (SELECT {H60} // pow(2, 60 - p)::BIGINT AS fp, count(*) AS cnt FROM ({LINES}), spec GROUP BY 1) SELECT fps.fp, fps.cnt AS orders, l.cnt AS lines FROM fps JOIN l USING (fp)""")
def qf_bucketed(spark, d):
    """Two filters stored alike, in buckets sorted by fingerprint: they meet without a shuffle."""
    spec, f = orders_filter(spark, d)
    lines, sides = qf.build_fp(src.line_keys(spark, d), spec), []
    for name, fp in (("orders", f), ("lines", lines)):
        folder = work_folder(spark)
        table = f"approxset_{folder[-32:]}"
        fp.select("fp", F.col("cnt").alias(name)).repartition(8, "fp").write.bucketBy(8, "fp").sortBy("fp").option("path", f"{folder}/{name}").saveAsTable(table)
        sides.append(spark.table(table))
        spark.sql(f"DROP TABLE {table}")  # external: the files stay
    return sides[0].hint("merge").join(sides[1], "fp")


@query("qf_single_key", f"""WITH {fps(ORDERS)}, q AS (SELECT k FROM (SELECT min(o_orderkey)::VARCHAR AS k FROM orders UNION ALL SELECT max(o_orderkey)::VARCHAR FROM orders UNION ALL SELECT (max(o_orderkey) + i)::VARCHAR FROM orders, range(1, 7) t(i) GROUP BY i))
    SELECT k, {H60} // pow(2, 60 - p)::BIGINT IN (SELECT fp FROM fps) AS maybe FROM q, spec""")
def qf_single_key(spark, d):
    """Eight keys, each looked up by itself in its shard, by the flags of one cluster."""
    spec, f = orders_filter(spark, d)
    n = qf.shards_of(spec, spec.slots, 1 << 12)
    packed = qf.pack(f, spec, n).cache()
    lo, hi = src.table(spark, d, "orders").agg(F.min("o_orderkey"), F.max("o_orderkey")).first()
    return spark.createDataFrame([(k, qf.might_contain(packed, k, spec, n)) for k in map(str, [lo, hi, *(hi + i for i in range(1, 7))])], "k string, maybe boolean")


@query("qf_insert_packed", _sets(("'F','O'", "fps")) + " SELECT fp, cnt FROM fps")
def qf_insert_packed(spark, d):
    """Into packed shards; shards without a new fingerprint are left as they are."""
    spec = spec_for(src.order_keys(spark, d))
    n = qf.shards_of(spec, spec.slots, 1 << 10)
    return qf.unpack(qf.insert_packed(qf.pack(status_filter(spark, d, spec, "F"), spec, n), status_filter(spark, d, spec, "O"), spec, n), spec, n)


@query("qf_delete_underflow", f"{_sets((chr(39) + 'F' + chr(39), 'a'), (chr(39) + 'F' + chr(39) + ',' + chr(39) + 'O' + chr(39), 'b'))} SELECT b.fp, b.cnt - coalesce(a.cnt, 0) AS missing FROM b LEFT JOIN a USING (fp) WHERE b.cnt > coalesce(a.cnt, 0)")
def qf_delete_underflow(spark, d):
    """What a strict delete would complain of."""
    spec = spec_for(src.order_keys(spark, d))
    return qf.underflow(status_filter(spark, d, spec, "F"), status_filter(spark, d, spec, "F", "O"))


@query("qf_load_guard", "SELECT a AS load, a <= 0.75 AS fits FROM (SELECT unnest([0.5, 0.75, 0.8, 0.9])::DOUBLE AS a)")
def qf_load_guard(spark, d):
    """Filters of 4096 slots at the advised limit of three quarters: which loads are let in."""
    from ..schema import FilterFull

    keys, out = src.arrivals(src.triple_keys(spark, d)), []
    for a in (0.5, 0.75, 0.8, 0.9):
        try:
            qf.guarded(keys.filter(F.col("seq") <= int(a * 4096)).select("k"), FilterSpec(p=21, slots=4096))
            out.append((a, True))
        except FilterFull:
            out.append((a, False))
    return spark.createDataFrame(out, "load double, fits boolean")


# variants

def _offsets(spacing: int) -> str:
    return f"""WITH {fps(ORDERS)}, items AS (SELECT fp // width AS g, m, row_number() OVER (ORDER BY fp) - 1 AS i FROM fps, spec, range(1, cnt + 1)),
    raw AS (SELECT *, i + max(g - i) OVER (ORDER BY i) AS s FROM items), over AS (SELECT count(*) FILTER (WHERE s >= m) AS c FROM raw),
    ends AS (SELECT g, max(i + greatest(c, s - i)) + 1 AS e FROM raw, over GROUP BY g),
    sync AS (SELECT x * {spacing} AS b FROM spec, range(0, m // {spacing}) t(x)),
    free AS (SELECT b, max(e) OVER (ORDER BY b, kind) AS e, kind FROM (SELECT b, NULL AS e, 0 AS kind FROM sync UNION ALL SELECT g, e, 1 FROM ends)),
    offs AS (SELECT b // {spacing} AS sync_idx, greatest(0, coalesce(e, c) - b, CASE WHEN e IS NULL THEN c - b ELSE 0 END) AS o FROM free, over WHERE kind = 0)"""


@query("var_sync_offsets", _offsets(16) + " SELECT sync_idx, least(o, 31)::BIGINT AS offset_ FROM offs")
def var_sync_offsets(spark, d):
    spec, f = orders_filter(spark, d)
    return variants.synchronizers(f, spec, 16, 5)


SPACINGS = (1, 16, 64, 256)


@query("var_sync_sweep", " UNION ALL ".join(f"SELECT * FROM ({_offsets(s)} SELECT {s} AS spacing, c AS bits, count(*) FILTER (WHERE o >= pow(2, c) - 1) AS saturated, count(*) AS entries, round(2 + c / {s}, 6) AS bits_a_slot FROM offs, (VALUES (1), (5), (8)) t(c) GROUP BY c)" for s in SPACINGS))
def var_sync_sweep(spark, d):
    """From one bit a bucket, much like the shifted flag, to few entries, which leave two bits a slot."""
    spec, f = orders_filter(spark, d)
    return variants.sync_sweep(f, spec, SPACINGS, (1, 5, 8))


@query("var_sync_probe", PROBE)
def var_sync_probe(spark, d):
    """Lookups in payloads without the shifted flag, from the nearest entry of five bits that isn't saturated."""
    spec, f = orders_filter(spark, d)
    coder, n = variants.Sync(64, 5), qf.shards_of(spec, spec.slots, 1 << 12)
    return variants.probe_variant(_probed(spark, d), variants.pack_variant(f, spec, coder, n), spec, coder, n)


@query("var_reserved_probe", f"""WITH spec AS (SELECT pow(2, q)::BIGINT * 511 AS space FROM ({SPEC_ORDERS})), fps AS (SELECT DISTINCT {H60} % space AS fp FROM ({ORDERS}), spec)
    SELECT k, {H60} % space IN (SELECT fp FROM fps) AS maybe FROM (SELECT DISTINCT k FROM ({LINES}) UNION ALL {ABSENT}), spec""")
def var_reserved_probe(spark, d):
    keys = src.order_keys(spark, d)
    spec = spec_for(keys, variant="reserved")
    coder = variants.Reserved()
    return qf.probe_join(_probed(spark, d), variants.unpack_variant(variants.pack_variant(qf.build_fp(keys, spec), spec, coder), spec, coder), spec)


@query("var_ordered_decode", f"WITH {fps(LINES)} SELECT fp, cnt FROM fps")
def var_ordered_decode(spark, d):
    spec, f = lines_filter(spark, d)
    coder = variants.Ordered()
    return variants.unpack_variant(variants.pack_variant(f, spec, coder), spec, coder)


@query("var_sync_decode", f"WITH {fps(LINES)} SELECT fp, cnt FROM fps")
def var_sync_decode(spark, d):
    spec, f = lines_filter(spark, d)
    coder = variants.Sync(16, 8)
    return variants.unpack_variant(variants.pack_variant(f, spec, coder), spec, coder)


@query("var_payload_bytes", f"""WITH {fps(ORDERS)} SELECT v AS variant, sum((slots * bits + 7) // 8)::BIGINT AS bytes FROM (SELECT greatest(max(m), max(s)) + 1 AS slots FROM (SELECT i + max(g - i) OVER (ORDER BY i) + 1 AS s, m FROM (SELECT fp // width AS g, m, row_number() OVER (ORDER BY fp) - 1 AS i FROM fps, spec, range(1, cnt + 1)))), (VALUES ('ordered', 11), ('sync', 11)) t(v, bits) GROUP BY v""")
def var_payload_bytes(spark, d):
    """Bytes of whole payloads at nine bits of remainder: eleven bits a slot."""
    spec, f = orders_filter(spark, d)
    out = None
    for name, coder in (("ordered", variants.Ordered()), ("sync", variants.Sync())):
        row = variants.pack_variant(f, spec, coder, 1).agg(F.sum(F.octet_length("payload")).cast("long").alias("bytes")).select(F.lit(name).alias("variant"), "bytes")
        out = row if out is None else out.unionByName(row)
    return out


@query("var_space_curve", """SELECT e AS bits, a AS load, round(n * ((log2(a * pow(2, e)) + 3) / a), 2) AS three_flags, round(n * ((log2(a * pow(2, e)) + 2) / a), 2) AS two_flags, round(n * (e / ln(2)), 2) AS bloom
    FROM range(1, 21) t(e), (VALUES (0.5::DOUBLE), (0.75), (0.9)) u(a), (SELECT count(l_orderkey) AS n FROM lineitem)""")
def var_space_curve(spark, d):
    """Bits for all the lines' keys, by rate and load, with three flags and with two."""
    from ..functions import formulas as fm
    from .base import count_of

    n = count_of(src.line_keys(spark, d))
    rows = [(e, a, round(n * fm.bits_qf(2.0**-e, a), 2), round(n * fm.bits_qf(2.0**-e, a, 2), 2), round(n * fm.bits_bloom(2.0**-e), 2)) for e in range(1, 21) for a in (0.5, 0.75, 0.9)]
    return spark.createDataFrame(rows, "bits long, load double, three_flags double, two_flags double, bloom double")
