"""Measures and experiment workloads."""

from __future__ import annotations

import math

from pyspark.sql import Window
from pyspark.sql import functions as F

from ..cluster import cleaned
from ..functions import formulas as fm
from ..functions.fingerprint import fingerprint, quotient_of
from ..operators import bloom, tiered
from ..operators import quotient as qf
from ..plans import optimizer
from ..schema import FilterSpec
from ..sources import tables as src
from .base import ABSENT, H60, LINES, ORDERS, SLOTS, TRIPLES, count_of, fps, query, spec_for
from .baselines import AT, LAYER, PLB, SEQ, SIZE9, accuracy, bits, lanes, layered_bits, orders_bloom, orders_local
from .membership import orders_filter
from .tiers import ingested


def clusters(slots, m):
    """(cluster_len): maximal runs of used slots on the ring, by gaps and islands inside slot ranges.

    An island starts after an unused slot; ranges are stitched through the starts before them."""
    u = slots.filter("used").select("slot")
    prev = u.select(F.pmod(F.col("slot") + 1, F.lit(m)).alias("slot"), F.lit(1).alias("p"))
    s = u.join(prev, "slot", "left").withColumn("head", F.col("p").isNull())
    s = s.withColumn("range", F.call_function("div", F.col("slot") * 64, F.lit(m).cast("long")))
    w = Window.partitionBy("range").orderBy("slot")
    s = s.withColumn("start", F.max(F.when(F.col("head"), F.col("slot"))).over(w))
    last = s.groupBy("range").agg(F.max("start").alias("last"))
    before = last.select("range", F.last("last", ignorenulls=True).over(Window.orderBy("range").rowsBetween(Window.unboundedPreceding, -1)).alias("carry"), F.max("last").over(Window.partitionBy()).alias("ring"))
    s = s.join(F.broadcast(before), "range").withColumn("start", F.coalesce("start", "carry", "ring"))
    return s.groupBy("start").agg(F.count("*").alias("cluster_len")).select("cluster_len")


CLUSTERS = """, ring AS (SELECT slot, slot - row_number() OVER (ORDER BY slot) AS isl FROM slots), isl AS (SELECT isl, count(*) AS n, min(slot) AS a, max(slot) AS b FROM ring GROUP BY 1),
    joined AS (SELECT CASE WHEN a = 0 AND (SELECT max(b) FROM isl) = (SELECT max(m) - 1 FROM spec) AND (SELECT count(*) FROM isl) > 1 THEN (SELECT max(isl) FROM isl) ELSE isl END AS isl, n FROM isl),
    cl AS (SELECT sum(n)::BIGINT AS cluster_len FROM joined GROUP BY isl)"""


def _load(a):
    """The first a * 2^q triples by arrival, q = the largest that they fill."""
    return f"SELECT k FROM (SELECT k, row_number() OVER (ORDER BY md5(k), k) AS seq FROM ({TRIPLES})), (SELECT floor({a} * pow(2, floor(log2(count(*)))))::BIGINT AS n FROM lineitem) WHERE seq <= n"


LOADQ = "SELECT floor(log2(count(*)))::BIGINT AS q FROM lineitem"


def loaded(spark, d, a):
    import math

    keys = src.triple_keys(spark, d)
    q = int(math.log2(keys.count()))
    spec = FilterSpec(p=q + 9, slots=1 << q)
    n = int(a * (1 << q))
    return qf.build_fp(src.arrivals(keys).filter(F.col("seq") <= n).select("k"), spec), spec


def cluster_stats(c, load):
    return c.agg(F.count("*").alias("clusters"), F.round(F.avg("cluster_len"), 6).alias("mean"), F.round(F.sum(F.col("cluster_len") * F.col("cluster_len")) / F.sum("cluster_len"), 6).alias("item_mean"), F.max("cluster_len").alias("longest"), F.round(F.sum(F.when(F.col("cluster_len") < 24, F.col("cluster_len")).otherwise(0)) / F.sum("cluster_len"), 6).alias("items_below_24")).select(F.lit(load).alias("load"), "*")


CL_STATS = "SELECT {a}::DOUBLE AS load, count(*) AS clusters, round(avg(cluster_len), 6) AS mean, round(sum(cluster_len * cluster_len) / sum(cluster_len), 6) AS item_mean, max(cluster_len) AS longest, round(sum(CASE WHEN cluster_len < 24 THEN cluster_len ELSE 0 END) / sum(cluster_len), 6) AS items_below_24 FROM cl"

for _a, _name in ((0.5, "w06_load_half"), (0.75, "w06_load_three_quarters"), (0.9, "w06_load_nine_tenths")):

    @query(_name, f"WITH {fps(_load(_a), 9, 0.75, 'fps', LOADQ)}, {SLOTS}{CLUSTERS} " + CL_STATS.format(a=_a))
    def _(spark, d, a=_a):
        f, spec = loaded(spark, d, a)
        return cluster_stats(clusters(qf.as_slots(f, spec), spec.slots), a)


@query("cluster_histogram", f"WITH {fps(LINES)}, {SLOTS}{CLUSTERS} SELECT cluster_len, count(*) AS clusters FROM cl GROUP BY 1")
def cluster_histogram(spark, d):
    keys = src.line_keys(spark, d)
    spec = spec_for(keys)
    return clusters(qf.as_slots(qf.build_fp(keys, spec), spec), spec.slots).groupBy("cluster_len").agg(F.count("*").alias("clusters"))


@query("cluster_bounds", "SELECT a AS load, round(ln(m) / (a - ln(a) - 1), 6) AS longest, round(1 / (1 - a * exp(1 - a)), 6) AS mean FROM (SELECT pow(2, greatest(1, ceil(log2(greatest(1, count(l_orderkey)) / 0.75)))) AS m FROM lineitem), (VALUES (0.5::DOUBLE), (0.75), (0.9)) t(a)")
def cluster_bounds(spark, d):
    """Bounds of clusters in the slots that the lines' keys ask for, at three loads."""
    m = 2.0 ** max(1, math.ceil(math.log2(max(1, count_of(src.line_keys(spark, d))) / 0.75)))
    return spark.createDataFrame([(a, round(fm.max_cluster_bound(m, a), 6), round(fm.mean_cluster_bound(a), 6)) for a in (0.5, 0.75, 0.9)], "load double, longest double, mean double")


@query("scan_cost", f"""WITH {fps(ORDERS)}, {SLOTS} SELECT count(*) AS items, sum((slot - g + m) % m)::BIGINT AS displacement, max((slot - g + m) % m) AS max_displacement, count(*) FILTER (WHERE NOT cont) AS runs,
    count(*) FILTER (WHERE NOT shifted AND NOT cont) AS segments FROM slots""")
def scan_cost(spark, d):
    """Displacement, runs and segments between unshifted run heads."""
    keys = src.order_keys(spark, d)
    spec = spec_for(keys)
    s = qf.as_slots(qf.build_fp(keys, spec), spec)
    runs = s.filter("used").agg(F.count("*").alias("items"), F.count(F.when(~F.col("continuation"), 1)).alias("runs"), F.count(F.when(~F.col("shifted") & ~F.col("continuation"), 1)).alias("segments"))
    # displacement needs the owners: the j-th run belongs to the j-th occupied bucket
    from ..operators.quotient import build_fp

    f = build_fp(keys, spec).groupBy(quotient_of(F.col("fp"), spec).alias("g")).agg(F.sum("cnt").alias("n"))
    from ..operators.variants import _ends

    ends, _ = _ends(build_fp(keys, spec), spec)
    at = f.join(ends, "g").withColumn("first", F.col("e") - F.col("n") - F.col("g"))
    disp = at.agg(F.sum(F.col("n") * F.col("first") + F.col("n") * (F.col("n") - 1) / 2).cast("long").alias("displacement"), F.max(F.col("first") + F.col("n") - 1).alias("max_displacement"))
    return runs.crossJoin(disp).select("items", "displacement", "max_displacement", "runs", "segments")


#: Columns of the space curve: a quotient filter's flags and load.
CURVES = {"quotient": (3, 0.75), "quotient_half": (3, 0.5), "quotient_nine_tenths": (3, 0.9), "two_flags": (2, 0.75), "two_flags_half": (2, 0.5), "two_flags_nine_tenths": (2, 0.9)}


@query("space_curve", f"""SELECT e AS bits, 1 / pow(2, e) AS eps, round(n * ((log2(0.75 * pow(2, e)) + 3) / 0.75), 2) AS quotient, round(n * (e / ln(2)), 2) AS bloom, round(n * (4 * e / ln(2)), 2) AS counting,
    {", ".join(f"round(n * ((log2({a} * pow(2, e)) + {flags}) / {a}), 2) AS {c}" for c, (flags, a) in CURVES.items() if c != "quotient")}
    FROM range(1, 25) t(e), (SELECT count(o_orderkey) AS n FROM orders)""")
def space_curve(spark, d):
    """Bits for all the orders' keys, by rate: the classic and the counting filter, the quotient filter at three loads, with three flags and with two."""
    n = count_of(src.order_keys(spark, d))
    more = [c for c in CURVES if c != "quotient"]
    rows = []
    for e in range(1, 25):
        of = {c: round(n * fm.bits_qf(2.0**-e, a, flags), 2) for c, (flags, a) in CURVES.items()}
        rows.append((e, 2.0**-e, of["quotient"], round(n * fm.bits_bloom(2.0**-e), 2), round(n * (4 * fm.bits_bloom(2.0**-e)), 2), *(of[c] for c in more)))
    return spark.createDataFrame(rows, "bits long, eps double, quotient double, bloom double, counting double" + "".join(f", {c} double" for c in more))


@query("capacity_table", "SELECT e AS bits, floor(0.9::DOUBLE * size * 8 / (e + 3))::BIGINT AS quotient, floor(size * 8 / (e / ln(2)))::BIGINT AS bloom FROM (SELECT coalesce(sum(length(o_orderkey::VARCHAR)), 0)::BIGINT AS size FROM orders), (VALUES (6), (9), (12)) t(e)")
def capacity_table(spark, d):
    """Items that either structure holds in the bytes of the orders' keys."""
    size = src.order_keys(spark, d).agg(F.coalesce(F.sum(F.length("k")), F.lit(0))).first()[0]
    return spark.createDataFrame([(e, fm.capacity_qf(size, e), fm.capacity_bloom(size, 2.0**-e)) for e in (6, 9, 12)], "bits int, quotient long, bloom long")


@query("w11_capacity", "SELECT e AS bits, floor(0.9 * pow(2, 31) * 8 / (e + 3))::BIGINT AS quotient, floor(pow(2, 31) * 8 / (e / ln(2)))::BIGINT AS bloom FROM (VALUES (6), (9), (12)) t(e)")
def w11(spark, d):
    return spark.createDataFrame([(e, fm.capacity_qf(1 << 31, e), fm.capacity_bloom(1 << 31, 2.0**-e)) for e in (6, 9, 12)], "bits int, quotient long, bloom long")


def all_answers(spark, d, df):
    """`df` (k, ...) answered by each of eight structures over the orders' keys: name, df with `maybe`.

    The write-buffered filter holds three quarters of the arrivals on storage and the bits of the rest in memory."""
    spec, f = orders_filter(spark, d)
    b, keys = orders_bloom(spark, d)
    n = keys.count()
    counting, local, layered = bloom.CountingBloom(b.m, b.k), orders_local(spark, d)[0], bloom.LayeredBloom(1000, 18, 12)
    arrived = src.arrived_by(keys, [n - n // 4, *(layered.base * ((1 << i) - 1) for i in range(1, layered.layers(n)))])
    stored, buffered = arrived.filter(F.col("seq") <= n - n // 4), arrived.filter(F.col("seq") > n - n // 4)
    yield "quotient", qf.probe_join(df, f, spec)
    yield "classic", b.probe(df, b.build(keys))
    yield "counting", counting.probe(df, counting.build(keys))
    yield "write-buffered", b.probe(df, b.union(b.build(stored), b.build(buffered)))
    yield "page-local", local.probe(df, local.build(keys))
    yield "layered", layered.probe(df, layered.build(arrived, n), layered.layers(n))
    yield "two-tier", ingested(spark, d, tiered.TwoTierFilter)[0].probe(df)
    yield "levelled", ingested(spark, d, tiered.LevelledFilter)[0].probe(df)


def accuracies(spark, d, df):
    """A row for each structure. A key that is looked up again gets the same answer, so each is asked once and counted as often as
    it is looked up; a structure is done, and its files gone, before the next begins."""
    n, rows = src.order_keys(spark, d).count(), []
    with cleaned(spark):
        asked = df.groupBy("k", "present").agg(F.count("*").alias("times")).cache()
        for name, found in all_answers(spark, d, asked):
            row = accuracy(name, found, n, F.col("times"))
            rows += row.collect()  # one row
        asked.unpersist()
    return spark.createDataFrame(rows, row.schema)


def accuracies_sql(probes: str) -> str:
    """A row for each structure; probes are rows (k, present). Structures with the same bits or fingerprints answer alike."""
    each = lambda name, frm: f"SELECT '{name}' AS structure, (SELECT count(*) FROM orders) AS n_inserted, count(*) FILTER (WHERE present) AS present_probed, count(*) FILTER (WHERE present AND NOT maybe) AS fn, count(*) FILTER (WHERE NOT present) AS absent_probed, count(*) FILTER (WHERE NOT present AND maybe) AS fp, round(count(*) FILTER (WHERE NOT present AND maybe) / nullif(count(*) FILTER (WHERE NOT present), 0), 6) AS fpr FROM pr JOIN {frm} USING (k)"
    return f"""WITH {fps(ORDERS)}, {SIZE9}, pr AS ({probes}), ks AS (SELECT DISTINCT k FROM pr),
        aq AS (SELECT k, {H60} // pow(2, 60 - p)::BIGINT IN (SELECT fp FROM fps) AS maybe FROM ks, spec),
        cb AS (SELECT DISTINCT bit FROM ({bits(ORDERS, 9, 'm')})), cp AS ({bits('SELECT k FROM ks', 9, 'm')}), ac AS (SELECT k, bool_and(bit IN (SELECT bit FROM cb)) AS maybe FROM cp GROUP BY k),
        lb AS (SELECT DISTINCT unnest({PLB}) AS bit FROM ({ORDERS}), {AT}), lp AS (SELECT k, unnest({PLB}) AS bit FROM ks, {AT}), al AS (SELECT k, bool_and(bit IN (SELECT bit FROM lb)) AS maybe FROM lp GROUP BY k),
        ya AS (SELECT k, {LAYER} AS layer FROM ({SEQ})), yb AS (SELECT DISTINCT unnest({layered_bits('k', 12, '1000')}) AS bit FROM ya), yp AS (SELECT k, layer, unnest({layered_bits('k', 12, '1000')}) AS bit FROM ks, (SELECT DISTINCT layer FROM ya)),
        ay AS (SELECT k, bool_or(h) AS maybe FROM (SELECT k, layer, bool_and(bit IN (SELECT bit FROM yb)) AS h FROM yp GROUP BY 1, 2) GROUP BY k)
        """ + " UNION ALL ".join(each(name, t) for name, t in (("quotient", "aq"), ("two-tier", "aq"), ("levelled", "aq"), ("classic", "ac"), ("counting", "ac"), ("write-buffered", "ac"), ("page-local", "al"), ("layered", "ay")))


@query("w02_random_lookups", accuracies_sql(f"SELECT k, false AS present FROM ({ABSENT})"))
def w02(spark, d):
    return accuracies(spark, d, src.absent_keys(spark, d).withColumn("present", F.lit(False)))


@query("w03_successful_lookups", accuracies_sql(f"SELECT k, true AS present FROM ({LINES})"))
def w03(spark, d):
    return accuracies(spark, d, src.line_keys(spark, d).withColumn("present", F.lit(True)))


@query("acc_sized_structures", accuracies_sql(f"SELECT DISTINCT k, true AS present FROM ({LINES}) UNION ALL SELECT k, false FROM ({ABSENT})"))
def acc_sized(spark, d):
    """`acc_all_structures` with a row for each of eight structures, present and absent keys together."""
    present = src.line_keys(spark, d).distinct().withColumn("present", F.lit(True))
    return accuracies(spark, d, present.unionByName(src.absent_keys(spark, d).withColumn("present", F.lit(False))))


def since(arrived, probes, spec, b):
    """Of lookups (k, ...) against arrivals (k, phase): `quotient` and `classic`, the phase from which either structure answers
    present (null: never). The first is that of the fingerprint, the second that in which the last of the bits was set."""
    first = arrived.groupBy(fingerprint(F.col("k"), spec).alias("__fp")).agg(F.min("phase").alias("quotient"))
    put = arrived.select("phase", F.explode(b.positions(F.col("k"))).alias("bit")).groupBy("bit").agg(F.min("phase").alias("phase"))
    asked = probes.select("k").distinct().select("k", F.explode(b.positions(F.col("k"))).alias("bit"))
    bits_ = asked.join(put, "bit", "left").groupBy("k").agg(F.when(F.count("phase") == F.count("*"), F.max("phase")).alias("classic"))
    return probes.withColumn("__fp", fingerprint(F.col("k"), spec)).join(first, "__fp", "left").join(bits_, "k", "left").drop("__fp"), put


SINCE = """fq AS (SELECT {h} AS fp, min(phase) AS first FROM a, spec GROUP BY 1), put AS (SELECT bit, min(phase) AS phase FROM (SELECT phase, unnest({l}) % m AS bit FROM a, size) GROUP BY 1),
    ask AS (SELECT k, CASE WHEN count(phase) = count(*) THEN max(phase) END AS classic FROM (SELECT DISTINCT k, unnest({l}) % m AS bit FROM pr, size) LEFT JOIN put USING (bit) GROUP BY k),
    got AS (SELECT kind, fq.first AS quotient, classic FROM (SELECT k, kind, {h} AS fp FROM pr, spec) LEFT JOIN fq USING (fp) JOIN ask USING (k))"""


def _since_sql(k: int) -> str:
    return SINCE.replace("{h}", f"{H60} // pow(2, 60 - p)::BIGINT").replace("{l}", lanes(k))


@query("w04_interleaved", f"""WITH {fps(ORDERS)}, {SIZE9}, a AS (SELECT k, (seq * 20 + n - 1) // n AS phase FROM ({SEQ}), (SELECT count(*) AS n FROM orders)), pr AS (SELECT DISTINCT k, 1 AS kind FROM ({LINES}) UNION ALL SELECT k, 0 FROM ({ABSENT})), {_since_sql(9)},
    fill AS (SELECT i, (SELECT count(*) FROM put WHERE phase <= i) AS bits, (SELECT count(*) FROM a WHERE phase <= i) AS items FROM range(1, 21) t(i)), sizes AS (SELECT (SELECT max(spec.m) FROM spec) AS slots, (SELECT max(size.m) FROM size) AS m)
    SELECT 'quotient' AS structure, i AS phase, (SELECT count(*) FROM got WHERE kind = 1 AND quotient <= i) AS hits, (SELECT count(*) FROM got WHERE kind = 0 AND quotient <= i) AS false_hits, round(items / slots, 6) AS load FROM fill, sizes
    UNION ALL SELECT 'classic', i, (SELECT count(*) FROM got WHERE kind = 1 AND classic <= i), (SELECT count(*) FROM got WHERE kind = 0 AND classic <= i), round(bits / m, 6) FROM fill, sizes""")
def w04(spark, d):
    """After each twentieth of the inserts, lookups of present and of absent keys against what is there, by both structures."""
    keys = src.order_keys(spark, d)
    spec, n = spec_for(keys), keys.count()
    b = orders_bloom(spark, d)[0]
    arrived = src.arrivals(keys).withColumn("phase", F.call_function("div", F.col("seq") * 20 + n - 1, F.lit(n).cast("long")))
    probes = src.line_keys(spark, d).distinct().withColumn("kind", F.lit(1)).unionByName(src.absent_keys(spark, d).withColumn("kind", F.lit(0)))
    found, put = since(arrived, probes, spec, b)
    w, out = Window.orderBy("phase"), None  # windows over twenty rows
    z = lambda c: F.coalesce(F.sum(c).over(w), F.lit(0)).cast("long")
    grid = spark.range(1, 21).toDF("phase")
    for name, filled, size in (("quotient", arrived.groupBy("phase").agg(F.count("*").alias("c")), spec.slots), ("classic", put.groupBy("phase").agg(F.count("*").alias("c")), b.m)):
        hit = found.groupBy(F.col(name).alias("phase")).agg(F.count(F.when(F.col("kind") == 1, 1)).alias("h"), F.count(F.when(F.col("kind") == 0, 1)).alias("x"))
        rows = grid.join(hit, "phase", "left").join(filled, "phase", "left").select(F.lit(name).alias("structure"), "phase", z("h").alias("hits"), z("x").alias("false_hits"), F.round(z("c") / size, 6).alias("load"))
        out = rows if out is None else out.unionByName(rows)
    return out


NINE = "SELECT ceil(count(*) / 0.9)::BIGINT AS slots, count(*) AS n FROM lineitem"

for _r in (6, 9, 12):

    @query(f"w05_bf_vs_qf_{1 << _r}", f"""WITH s AS ({NINE}), spec AS (SELECT slots, n, ceil(log2(slots))::BIGINT + {_r} AS p FROM s), size AS (SELECT slots * ({_r} + 3) AS m FROM s), a AS (SELECT k, (seq * 20 + slots - 1) // slots AS phase FROM (SELECT k, row_number() OVER (ORDER BY md5(k), k) AS seq FROM ({TRIPLES})), s), pr AS (SELECT k, 0 AS kind FROM ({ABSENT})), {_since_sql(_r)},
        steps AS (SELECT i, least(n, slots * i // 20) AS inserted FROM range(1, 19) t(i), s)
        SELECT 'quotient' AS structure, i AS step, inserted, (SELECT count(*) FROM got) AS absent_probed, (SELECT count(*) FROM got WHERE quotient <= i) AS fp FROM steps UNION ALL SELECT 'classic', i, inserted, (SELECT count(*) FROM got), (SELECT count(*) FROM got WHERE classic <= i) FROM steps""")
    def _(spark, d, r=_r):
        """Both structures over the same keys in the same bytes, at each 5 % up to 90 % of the quotient filter's slots."""
        keys = src.triple_keys(spark, d)
        n = keys.count()
        slots = math.ceil(n / 0.9)
        spec, b = FilterSpec(p=math.ceil(math.log2(slots)) + r, slots=slots, max_load=0.9), bloom.BloomFilter(slots * (r + 3), r)
        spec.check(n, 0.9001)
        arrived = src.arrivals(keys).withColumn("phase", F.call_function("div", F.col("seq") * 20 + slots - 1, F.lit(slots).cast("long")))
        found = since(arrived, src.absent_keys(spark, d), spec, b)[0].cache()
        w, out = Window.orderBy("step"), None  # windows over eighteen rows
        grid = spark.range(1, 19).toDF("step")
        total = found.count()
        for name in ("quotient", "classic"):
            hit = found.groupBy(F.col(name).alias("step")).agg(F.count("*").alias("x"))
            rows = grid.join(hit, "step", "left").select(F.lit(name).alias("structure"), "step", F.least(F.lit(n).cast("long"), F.call_function("div", F.col("step") * slots, F.lit(20).cast("long"))).alias("inserted"), F.lit(total).cast("long").alias("absent_probed"), F.coalesce(F.sum("x").over(w), F.lit(0)).cast("long").alias("fp"))
            out = rows if out is None else out.unionByName(rows)
        return out


@query("w10_space_accuracy", "SELECT b::BIGINT AS bits_per_item, round(n * pow(0.5, b * ln(2)), 4) AS bloom, round(n * (0.75 / pow(2, 0.75 * b - 3)), 4) AS quotient FROM range(5, 31) t(b), (SELECT 4 * count(o_orderkey) AS n FROM orders)")
def w10(spark, d):
    """Wrong answers to expect from lookups of four absent keys an order, by bits an item."""
    n = count_of(src.absent_keys(spark, d))
    return spark.createDataFrame([(b, round(n * 0.5 ** (b * math.log(2)), 4), round(n * (0.75 / 2 ** (0.75 * b - 3)), 4)) for b in range(5, 31)], "bits_per_item long, bloom double, quotient double")


HOST = "regexp_extract(url, '://([^/]+)', 1)"


@query("w12_crawl_subtables", f"""WITH s AS (SELECT {HOST} AS host, {H60.replace('k)', 'url)')} // pow(2, 30)::BIGINT AS fp FROM pages), q AS (SELECT url AS k, {H60.replace('k)', 'url)')} // pow(2, 30)::BIGINT AS fp FROM pages)
    SELECT count(DISTINCT (q.k, s.host)) AS touched, (SELECT count(DISTINCT url) FROM pages) * (SELECT count(DISTINCT host) FROM s) AS without_filters FROM q JOIN s USING (fp)""")
def w12(spark, d):
    """One filter per host: sub-tables that lookups of all urls touch."""
    spec = FilterSpec(p=30, slots=1 << 20)
    p = src.table(spark, d, "pages").select("url", F.regexp_extract("url", "://([^/]+)", 1).alias("host"))
    f = p.select("host", fingerprint(F.col("url"), spec).alias("fp")).distinct()
    q = p.select("url", fingerprint(F.col("url"), spec).alias("fp")).distinct()
    t = q.join(f, "fp").select("url", "host").distinct().agg(F.count("*").alias("touched"))
    n = p.agg((F.countDistinct("url") * F.countDistinct("host")).alias("without_filters"))
    return t.crossJoin(n)


_W13 = f"SELECT '{{n}}' AS source, count(*) AS rows_, count(DISTINCT k) AS texts, count(DISTINCT {H60} // pow(2, 12)::BIGINT) AS fingerprints, count(DISTINCT k) - count(DISTINCT {H60} // pow(2, 12)::BIGINT) AS false_drops FROM ({{q}}) WHERE k IS NOT NULL"


@query("w13_deduplication", " UNION ALL ".join(_W13.format(n=n, q=q) for n, q in (("documents", "SELECT text AS k FROM documents"), ("lines", "SELECT unnest(string_split(text, chr(10))) AS k FROM documents"), ("conversations", "SELECT text AS k FROM conversations"))))
def w13(spark, d):
    """Repeats that a filter of seen texts drops, and texts that it drops wrongly: documents, their lines, turns of conversations."""
    spec = FilterSpec(p=48, slots=1 << 30)
    docs = src.table(spark, d, "documents")
    texts = {"documents": docs.select(F.col("text").alias("k")), "lines": docs.select(F.explode(F.split("text", "\n")).alias("k")), "conversations": src.table(spark, d, "conversations").select(F.col("text").alias("k"))}
    out = None
    for name, t in texts.items():
        t = t.filter("k is not null").select(fingerprint(F.col("k"), spec).alias("fp"), F.sha2(F.col("k").cast("binary"), 256).alias("d"))
        per = t.groupBy("fp", "d").agg(F.count("*").alias("n")).groupBy("fp").agg(F.sum("n").alias("n"), F.count("*").alias("texts"))
        row = per.agg(F.coalesce(F.sum("n"), F.lit(0)).alias("rows_"), F.coalesce(F.sum("texts"), F.lit(0)).alias("texts"), F.count("*").alias("fingerprints"), F.coalesce(F.sum("texts") - F.count("*"), F.lit(0)).alias("false_drops")).select(F.lit(name).alias("source"), "*")
        out = row if out is None else out.unionByName(row)
    return out


@query("w14_join_prefilter", "SELECT o_orderpriority AS priority, count(*) AS lines, round(sum(l_quantity), 2) AS quantity FROM lineitem JOIN orders ON l_orderkey = o_orderkey WHERE o_orderdate >= TIMESTAMP '1995-01-01' AND o_orderdate < TIMESTAMP '1995-04-01' GROUP BY 1")
def w14(spark, d):
    o = src.table(spark, d, "orders").filter("o_orderdate >= timestamp_ntz'1995-01-01' and o_orderdate < timestamp_ntz'1995-04-01'").select("o_orderkey", "o_orderpriority")
    li = src.table(spark, d, "lineitem").select("l_orderkey", "l_quantity")
    j = optimizer.prefilter_join(li, o, "l_orderkey", "o_orderkey")
    return j.groupBy(F.col("o_orderpriority").alias("priority")).agg(F.count("*").alias("lines"), F.round(F.sum("l_quantity"), 2).alias("quantity"))


@query("w15_remote_screening", "SELECT c_nationkey AS nation, count(DISTINCT o_custkey) AS customers, count(*) AS routed FROM orders JOIN customer ON o_custkey = c_custkey GROUP BY 1")
def w15(spark, d):
    """One filter per nation's customers routes orders to their owners, which confirm them."""
    spec = FilterSpec(p=34, slots=1 << 24)
    c = src.table(spark, d, "customer").select("c_custkey", "c_nationkey", fingerprint(src.key_text("c_custkey"), spec).alias("fp"))
    o = src.table(spark, d, "orders").select("o_custkey", fingerprint(src.key_text("o_custkey"), spec).alias("fp"))
    filters = c.select("c_nationkey", "fp").distinct()
    maybe = o.join(filters, "fp").select("o_custkey", "c_nationkey")
    sure = maybe.join(c.select(F.col("c_custkey").alias("o_custkey"), "c_nationkey"), ["o_custkey", "c_nationkey"], "left_semi")
    return sure.groupBy(F.col("c_nationkey").alias("nation")).agg(F.countDistinct("o_custkey").alias("customers"), F.count("*").alias("routed"))


@query("w17_held_out_overlap", f"""WITH w AS (SELECT doc_id, string_split(text, ' ') AS w FROM documents), s AS (SELECT DISTINCT doc_id, array_to_string(w[i:i+7], ' ') AS k FROM w, range(1, 100000) t(i) WHERE i <= len(w) - 7),
    bw AS (SELECT item_id, string_split(text, ' ') AS w FROM benchmark), b AS (SELECT DISTINCT item_id, array_to_string(w[i:i+7], ' ') AS k FROM bw, range(1, 10000) t(i) WHERE i <= len(w) - 7)
    SELECT doc_id, item_id, count(*) AS shared FROM s JOIN b USING (k) GROUP BY 1, 2""")
def w17(spark, d):
    """Held-out passages inside documents, by eight-word windows."""
    spec = FilterSpec(p=60, slots=1 << 40)

    def windows(t, key):
        w = src.table(spark, d, t).select(key, F.split("text", " ").alias("w")).filter(F.size("w") >= 8)
        k = F.transform(F.sequence(F.lit(1), F.size("w") - 7), lambda i: F.array_join(F.slice("w", i, F.lit(8)), " "))
        return w.select(key, F.explode(F.array_distinct(k)).alias("k")).select(key, fingerprint(F.col("k"), spec).alias("fp"))

    return windows("documents", "doc_id").join(windows("benchmark", "item_id"), "fp").groupBy("doc_id", "item_id").agg(F.count("*").alias("shared"))


STATUS_KEYS = "SELECT o_orderkey::VARCHAR AS k, o_orderstatus AS status FROM orders"
GONE_KEYS = "SELECT o_orderkey::VARCHAR AS k FROM orders WHERE o_orderstatus = 'F'"
KEPT_KEYS = "SELECT o_orderkey::VARCHAR AS k FROM orders WHERE o_orderstatus <> 'F'"


def _after_deletes_sql(gone: str) -> str:
    """CTE found (structure, k, maybe): the orders' keys against each structure after `gone` was deleted from it."""
    cell = lambda keys: f"(SELECT bit AS cell, count(*) AS c FROM (SELECT DISTINCT k, o, bit FROM ({bits(f'SELECT k, row_number() OVER () AS o FROM ({keys})', 9, 'm', 'o,')})) GROUP BY 1)"
    return f"""WITH {fps(ORDERS)}, {SIZE9}, df AS (SELECT {H60} // pow(2, 60 - p)::BIGINT AS fp, count(*) AS d FROM ({gone}), spec GROUP BY 1), qf AS (SELECT fp FROM fps LEFT JOIN df USING (fp) WHERE cnt > coalesce(d, 0)),
        cells AS (SELECT cell FROM {cell(ORDERS)} c LEFT JOIN (SELECT cell, c AS d FROM {cell(gone)}) USING (cell) WHERE c >= 15 OR c > coalesce(d, 0)), kb AS (SELECT DISTINCT bit FROM ({bits(KEPT_KEYS, 9, 'm')})), pb AS ({bits(ORDERS, 9, 'm')}),
        found AS (SELECT 'quotient' AS structure, k, {H60} // pow(2, 60 - p)::BIGINT IN (SELECT fp FROM qf) AS maybe FROM ({ORDERS}), spec
            UNION ALL SELECT 'counting', k, bool_and(bit IN (SELECT cell FROM cells)) FROM pb GROUP BY k UNION ALL SELECT 'rebuilt', k, bool_and(bit IN (SELECT bit FROM kb)) FROM pb GROUP BY k)"""


def after_deletes(spark, d, gone):
    """structure -> (the orders' keys with status and `maybe` after `gone` was deleted, its bits, whether it reads the keys again)."""
    spec, f = orders_filter(spark, d)
    b, keys = orders_bloom(spark, d)
    counting = bloom.CountingBloom(b.m, b.k)
    o = src.table(spark, d, "orders").select(src.key_text("o_orderkey").alias("k"), F.col("o_orderstatus").alias("status"))
    left = qf.delete(f, qf.build_fp(gone, spec))
    return {
        "quotient": (qf.probe_join(o, left, spec), spec.slots * (spec.r + 3), False),
        "counting": (counting.probe(o, counting.delete(counting.build(keys), gone)), 4 * b.m, False),
        "rebuilt": (b.probe(o, b.build(o.filter("status <> 'F'").select("k"))), b.m, True),
    }


def _gone(spark, d):
    return src.table(spark, d, "orders").filter("o_orderstatus = 'F'").select(src.key_text("o_orderkey").alias("k"))


@query("w18_deletes", _after_deletes_sql(GONE_KEYS) + f" SELECT structure, status, count(*) AS probed, count(*) FILTER (WHERE maybe) AS maybe FROM found JOIN ({STATUS_KEYS}) USING (k) GROUP BY 1, 2")
def w18(spark, d):
    """Finished orders are deleted, then all are looked up: by deletes in place, and by a classic filter built again."""
    out = None
    for name, (found, _, _) in after_deletes(spark, d, _gone(spark, d)).items():
        rows = found.groupBy("status").agg(F.count("*").alias("probed"), F.count(F.when(F.col("maybe"), 1)).alias("maybe")).select(F.lit(name).alias("structure"), "*")
        out = rows if out is None else out.unionByName(rows)
    return out


WRONG = "SELECT (o_orderkey + 1000000)::VARCHAR AS k FROM orders"


@query("delete_quality", _after_deletes_sql(f"{GONE_KEYS} UNION ALL {WRONG}") + f""", sizes AS (SELECT 'quotient' AS structure, m * 12 AS bits, false AS reads_keys FROM spec UNION ALL SELECT 'counting', 4 * m, false FROM size UNION ALL SELECT 'rebuilt', m, true FROM size)
    SELECT structure, bits, reads_keys, count(*) FILTER (WHERE status <> 'F' AND NOT maybe) AS lost, count(*) FILTER (WHERE status = 'F' AND maybe) AS still_there FROM found JOIN ({STATUS_KEYS}) USING (k) JOIN sizes USING (structure) GROUP BY ALL""")
def delete_quality(spark, d):
    """Finished orders and as many keys again that were never inserted are deleted: kept keys that are lost (a wrong delete took
    their copy), deleted ones that still answer, bits of each structure, and whether it needs the keys."""
    wrong = src.absent_keys(spark, d, 1)
    out = None
    for name, (found, size, again) in after_deletes(spark, d, _gone(spark, d).unionByName(wrong)).items():
        lost, still = F.count(F.when((F.col("status") != "F") & ~F.col("maybe"), 1)), F.count(F.when((F.col("status") == "F") & F.col("maybe"), 1))
        row = found.agg(lost.alias("lost"), still.alias("still_there")).select(F.lit(name).alias("structure"), F.lit(size).cast("long").alias("bits"), F.lit(again).alias("reads_keys"), "lost", "still_there")
        out = row if out is None else out.unionByName(row)
    return out


@query("w19_resize_merge", "SELECT b AS resized_by, 0::BIGINT AS differing FROM (VALUES (-3), (-2), (-1), (1), (2), (3)) t(b)")
def w19(spark, d):
    """Filters resized either way keep the same fingerprints."""
    spec, f = orders_filter(spark, d)
    rows = []
    for by in (-3, -2, -1, 1, 2, 3):
        s = spec.resized(by)
        n = qf.shards_of(s, s.slots)
        got = qf.unpack(qf.pack(f, s, n), s, n)
        rows.append((by, got.exceptAll(f).count() + f.exceptAll(got).count()))
    return spark.createDataFrame(rows, "resized_by int, differing long")
