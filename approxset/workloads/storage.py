"""The storage experiments: structures fed with the same arrivals behind a buffer, their writes, reads and stalls.

The lines' keys arrive in hash order. A buffer holds b of them, b such that `ratio` buffers fill up and about half a buffer
is left over, which stays where it is. Then all present keys and as many absent ones are looked up. Nothing is timed:
blocks of 256 slots or 4096 bits written and pages of 512 bits read are counted, from the files that the filters wrote
and from the bits that the lookups looked at."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..cluster import cleaned, drop_folder, work_folder
from ..operators import bloom, tiered
from ..schema import FilterSpec
from ..sources import tables as src
from .base import ABSENT, H60, TRIPLES, query, spec_for
from .baselines import lanes, layered_bits, read_sql
from .tiers import ends, fed

#: Hash functions of the write-buffered, page-local and layered filters at a rate of 1/4096, and bits of a block and a read page.
K_BUFFERED, K_LOCAL, K_LAYERED, BLOCK, PAGE, SLOTS_A_BLOCK = 12, 13, 14, 4096, 512, 256

_filled: dict = {}


def buffer_of(n: int, ratio: int) -> int:
    return max(1, 2 * n // (2 * ratio + 1))


def filled(spark, d, ratio: int, kind=tiered.LevelledFilter, **more) -> tiered.LevelledFilter:
    """A filter over the lines' keys with a buffer of 1/(ratio + 1/2) of them. The files of a run are used again in its session."""
    name = (spark.sparkContext.applicationId, d, ratio, kind.__name__, tuple(sorted(more.items())))
    if name not in _filled:
        keys = src.triple_keys(spark, d)
        n = keys.count()
        spec, buffer = spec_for(keys, 12), buffer_of(n, ratio)
        _filled[name] = fed(kind(spark, work_folder(spark), spec, buffer, **more), src.arrived_by(keys, ends(n, buffer)), buffer)
    return _filled[name]


def lookups(spark, d) -> DataFrame:
    present = src.triple_keys(spark, d).distinct().withColumn("present", F.lit(True))
    return present.unionByName(src.absent_keys(spark, d).withColumn("present", F.lit(False)))


def _blocks(items) -> F.Column:
    return F.call_function("div", items + (SLOTS_A_BLOCK - 1), F.lit(SLOTS_A_BLOCK).cast("long"))


def _writes(flushes: DataFrame) -> DataFrame:
    """One row of (times, random, sequential): flushes, blocks written in either way, the largest flush."""
    z = lambda c: F.coalesce(c, F.lit(0)).cast("long")
    t = F.col("times")
    return flushes.filter(t > 0).agg(z(F.sum(t)).alias("flushes"), z(F.sum(t * F.col("random"))).alias("random_writes"), z(F.sum(t * F.col("sequential"))).alias("sequential_writes"), z(F.max(F.col("random") + F.col("sequential"))).alias("largest_flush"))


def _reads(found: DataFrame) -> DataFrame:
    """One row of (present, maybe, reads, buffered, times): lookups, pages read and wrong answers of either kind of key."""
    p, maybe = F.col("present"), F.col("maybe")
    z = lambda c, x=1: F.coalesce(F.sum(F.when(c, F.col("times") * x)), F.lit(0)).cast("long")
    return found.agg(
        z(p).alias("present_lookups"), z(p, F.col("reads")).alias("present_reads"), z(p & F.col("buffered")).alias("ended_in_buffer"), z(p & ~maybe).alias("false_negatives"),
        z(~p).alias("absent_lookups"), z(~p, F.col("reads")).alias("absent_reads"), z(~p & maybe).alias("false_positives"),
    )


def storage_run(spark, d, ratio: int) -> DataFrame:
    """One row for each of the five structures. Each is done, and what it shuffled gone, before the next begins."""
    keys = src.triple_keys(spark, d)
    n = keys.count()
    b = buffer_of(n, ratio)
    arrived = src.arrived_by(keys, ends(n, b))
    rows, out = [], []
    one = F.lit(1).cast("long")
    none = F.lit(0).cast("long")

    def put(name: str, flushes: DataFrame, found: DataFrame) -> None:
        out.append(_writes(flushes).crossJoin(_reads(found)).select(F.lit(name).alias("structure"), "*"))  # one row each
        rows.extend(out[-1].collect())

    with cleaned(spark):
        # the fingerprints are asked as often as the lookups name a key, the Bloom filters once, as their SQL does
        folder = work_folder(spark)
        lookups(spark, d).groupBy("k", "present").agg(F.count("*").alias("times")).write.option("compression", "zstd").parquet(folder)
        probes = spark.read.schema("k string, present boolean, times long").parquet(folder)
        once = probes.select("k", "present", one.alias("times"))
        for name, kind in (("two-tier", tiered.TwoTierFilter), ("levelled", tiered.LevelledFilter)):
            f = filled(spark, d, ratio, kind)
            flushes = f.history().select(one.alias("times"), none.alias("random"), _blocks(F.col("written")).alias("sequential"))
            found = f.probe(probes).select("present", "maybe", F.col("levels_read").alias("reads"), F.coalesce(F.col("level") == 0, F.lit(False)).alias("buffered"), "times")
            put(name, flushes, found)

        def read(x) -> DataFrame:
            return x.select("present", "maybe", "reads", F.lit(False).alias("buffered"), "times")

        w = bloom.BloomFilter.for_items(n, 2.0**-12, K_BUFFERED)
        flushes = bloom.write_buffered_writes(arrived.filter(F.col("seq") <= n // b * b), w, b, BLOCK).select(one.alias("times"), F.col("page_writes").alias("random"), none.alias("sequential"))
        put("write-buffered", flushes, read(w.reads(once, w.build(keys), PAGE)))
        p = bloom.PageLocalBloom.for_items(n, 2.0**-12, BLOCK, K_LOCAL)
        put("page-local", p.flushes(keys, max(1, b // p.blocks)).select(F.col("flushes").alias("times"), one.alias("random"), none.alias("sequential")), read(p.reads(once, p.build(keys), PAGE)))
        y = bloom.LayeredBloom(b, 18, K_LAYERED, BLOCK)
        put("layered", y.flushes(arrived, b).select(F.col("flushes").alias("times"), one.alias("random"), none.alias("sequential")), read(y.reads(once, y.build(arrived, n), y.layers(n), PAGE)))
    drop_folder(spark, folder)
    return spark.createDataFrame(rows, out[0].schema)


def _run_sql(ratio: int) -> str:
    """The same counts: schedules from the bits of the flush numbers, reads from sets of fingerprints and bits."""
    h = f"{H60} // pow(2, 60 - p)::BIGINT"
    local = lambda k, count: f"list_transform(range(1, {k + 1}), lambda i: {lane('0')} % {count} * {BLOCK} + {lane('i')} % {BLOCK})"
    lane = lambda i: f"('0x' || substr(sha256('0:' || k) || sha256('1:' || k), ({i}) * 9 + 1, 9))::BIGINT"
    lane8 = "('0x' || substr(sha256('0:' || k) || sha256('1:' || k), 1, 8))::BIGINT"
    writes = lambda t: f"(SELECT count(*) AS flushes, coalesce(sum(random), 0)::BIGINT AS random_writes, coalesce(sum(sequential), 0)::BIGINT AS sequential_writes, coalesce(max(random + sequential), 0)::BIGINT AS largest_flush FROM {t})"
    reads = lambda t: f"""(SELECT count(*) FILTER (WHERE present) AS present_lookups, coalesce(sum(reads) FILTER (WHERE present), 0)::BIGINT AS present_reads, count(*) FILTER (WHERE present AND buffered) AS ended_in_buffer, count(*) FILTER (WHERE present AND NOT maybe) AS false_negatives,
        count(*) FILTER (WHERE NOT present) AS absent_lookups, coalesce(sum(reads) FILTER (WHERE NOT present), 0)::BIGINT AS absent_reads, count(*) FILTER (WHERE NOT present AND maybe) AS false_positives FROM {t})"""  # noqa: E731
    row = lambda name, w, r: f"SELECT '{name}' AS structure, * FROM {writes(w)}, {reads(r)}"
    return f"""WITH par AS (SELECT count(*) AS n, 2 * count(*) // {2 * ratio + 1} AS b, ceil(log2(count(*) / 0.75))::BIGINT + 12 AS p, ceil(-count(*) * ln(pow(2, -12)) / pow(ln(2), 2))::BIGINT AS m FROM lineitem),
        size AS (SELECT * FROM par), arr AS (SELECT k, row_number() OVER (ORDER BY md5(k), k) AS seq FROM ({TRIPLES})),
        pr AS (SELECT DISTINCT k, true AS present FROM ({TRIPLES}) UNION ALL SELECT k, false FROM ({ABSENT})),
        fl AS (SELECT e FROM range(1, {ratio + 1}) t(e)),
        tw AS (SELECT 0 AS random, (e * b + 255) // 256 AS sequential FROM fl, par), lw AS (SELECT 0 AS random, ((e & -e) * b + 255) // 256 AS sequential FROM fl, par),
        lev AS (SELECT j, min(i) + 1 AS level FROM range(1, {ratio + 1}) s(j), range(0, 8) t(i) WHERE ({ratio} >> i) & 1 = 1 AND j > ({ratio} >> (i + 1)) << (i + 1) AND j <= ({ratio} >> i) << i GROUP BY j),
        held AS (SELECT {h} AS fp, min(CASE WHEN seq > {ratio} * b THEN 0 ELSE level END) AS level FROM arr LEFT JOIN lev ON j = (seq - 1) // (SELECT b FROM par) + 1, par GROUP BY 1),
        q AS (SELECT present, level FROM (SELECT present, {h} AS fp FROM pr, par) LEFT JOIN held USING (fp)),
        tr AS (SELECT present, level IS NOT NULL AS maybe, coalesce(level = 0, false) AS buffered, CASE WHEN level = 0 THEN 0 ELSE 1 END AS reads FROM q),
        lr AS (SELECT present, level IS NOT NULL AS maybe, coalesce(level = 0, false) AS buffered, bit_count(CASE WHEN level IS NULL THEN {ratio} ELSE {ratio} & ((1 << level) - 1) END) AS reads FROM q),
        wb AS (SELECT seq, unnest({lanes(K_BUFFERED)}) % m AS bit FROM arr, size), wj AS (SELECT k, present, unnest(range(0, {K_BUFFERED})) AS j, unnest({lanes(K_BUFFERED)}) % m AS bit FROM pr, size),
        ww AS (SELECT count(DISTINCT bit // {BLOCK}) AS random, 0 AS sequential FROM wb, par WHERE seq <= n // b * b GROUP BY (seq - 1) // b),
        wr AS (SELECT present, hit AS maybe, reads, false AS buffered FROM {read_sql('wj', 'wb', PAGE, 'k, present')}),
        pb AS (SELECT unnest({local(K_LOCAL, f'((m + {BLOCK - 1}) // {BLOCK})')}) AS bit FROM arr, par),
        pj AS (SELECT k, present, unnest(range(0, {K_LOCAL})) AS j, unnest({local(K_LOCAL, f'((m + {BLOCK - 1}) // {BLOCK})')}) AS bit FROM pr, par),
        pw AS (SELECT 1 AS random, 0 AS sequential FROM (SELECT b, blocks, row_number() OVER (PARTITION BY {lane('0')} % blocks ORDER BY seq) AS i FROM arr, (SELECT *, (m + {BLOCK - 1}) // {BLOCK} AS blocks FROM par)) WHERE i % greatest(1, b // blocks) = 0),
        prd AS (SELECT present, hit AS maybe, reads, false AS buffered FROM {read_sql('pj', 'pb', PAGE, 'k, present')}),
        ya AS (SELECT k, seq, b, floor(log2(1 + (seq - 1) // b) + 1e-9)::BIGINT AS layer FROM arr, par),
        yb AS (SELECT unnest({layered_bits('k', K_LAYERED, 'b', 18, 8)}) AS bit FROM ya),
        yj AS (SELECT k, present, layer, unnest(range(0, {K_LAYERED})) AS j, unnest({layered_bits('k', K_LAYERED, 'b', 18, 8)}) AS bit FROM pr, par, (SELECT DISTINCT layer FROM ya)),
        yw AS (SELECT 1 AS random, 0 AS sequential FROM (SELECT b, blocks, row_number() OVER (PARTITION BY layer, {lane8} % blocks ORDER BY seq) AS i FROM (SELECT *, (b * 18 * pow(2, layer)::BIGINT + {BLOCK - 1}) // {BLOCK} AS blocks FROM ya WHERE layer > 0)) WHERE i % greatest(1, b // blocks) = 0),
        yr AS (SELECT present, bool_or(hit) AS maybe, sum(CASE WHEN layer = 0 THEN 0 ELSE reads END) AS reads, false AS buffered FROM {read_sql('yj', 'yb', PAGE, 'k, present, layer')} GROUP BY k, present)
        {row('two-tier', 'tw', 'tr')} UNION ALL {row('levelled', 'lw', 'lr')} UNION ALL {row('write-buffered', 'ww', 'wr')} UNION ALL {row('page-local', 'pw', 'prd')} UNION ALL {row('layered', 'yw', 'yr')}"""


for _ratio, _name in ((4, "w07_ratio4"), (24, "w08_ratio24")):

    @query(_name, _run_sql(_ratio))
    def _(spark, d, ratio=_ratio):
        """Buffer to filter 1:ratio, at a rate of 1/4096."""
        return storage_run(spark, d, ratio)


#: The schedule of levels for fan-out f: state `items` in buffers, by recursion.
FANS = """fans AS (SELECT unnest([2, 4, 16]) AS f), s AS (
        SELECT f, 0 AS epoch, list_transform(range(0, 8), lambda i: 0) AS items, 0 AS units, 0 AS levels FROM fans
        UNION ALL
        SELECT f, epoch + 1, list_transform(range(1, 9), lambda i: CASE WHEN i < t THEN 0 WHEN i = t THEN 1 + coalesce(list_sum(items[1:t]), 0) ELSE items[i] END)::INTEGER[], (1 + coalesce(list_sum(items[1:t]), 0))::INTEGER,
            len(list_filter(range(1, 9), lambda i: i = t OR (i > t AND items[i] > 0)))
        FROM (SELECT *, list_filter(range(1, 9), lambda i: 1 + coalesce(list_sum(items[1:i]), 0) <= pow(f, i - 1))[1] AS t FROM s WHERE epoch < 12)),
    par AS (SELECT 2 * count(*) // 25 AS b, ceil(log2(count(*) / 0.75))::BIGINT + 12 AS p FROM lineitem)"""


def _fan(spark, d, f):
    return filled(spark, d, 12, fanout=f)


@query("write_amplification", f"WITH RECURSIVE {FANS} SELECT f::BIGINT AS fanout, sum(units)::BIGINT * b AS items_written, round(sum(units) / 12, 6) AS amplification FROM s, par WHERE epoch > 0 GROUP BY f, b")
def write_amplification(spark, d):
    """Items written for each item that left the buffer, from the catalogues of three filters."""
    rows = None
    for f in (2, 4, 16):
        h = _fan(spark, d, f).history().agg(F.sum("written").alias("items_written"), F.round(F.sum("written") / F.sum("flushed"), 6).alias("amplification")).select(F.lit(f).cast("long").alias("fanout"), "*")
        rows = h if rows is None else rows.unionByName(h)
    return rows


@query("w09_fanout", f"""WITH RECURSIVE {FANS}, e AS (SELECT f, items FROM s WHERE epoch = 12), l AS (SELECT f, unnest(range(1, 9)) AS level, unnest(items) AS size FROM e), o AS (SELECT f, level, size, sum(size) OVER (PARTITION BY f ORDER BY level) AS upto, row_number() OVER (PARTITION BY f ORDER BY level) AS read FROM l WHERE size > 0),
        arr AS (SELECT k, row_number() OVER (ORDER BY md5(k), k) AS seq FROM ({TRIPLES})), ep AS (SELECT {H60} // pow(2, 60 - p)::BIGINT AS fp, (seq - 1) // b + 1 AS j FROM arr, par),
        held AS (SELECT fp, f, min(CASE WHEN j > 12 THEN 0 ELSE read END) AS read FROM ep, fans LEFT JOIN o USING (f) WHERE j > 12 OR (j > 12 - upto AND j <= 12 - upto + size) GROUP BY 1, 2),
        pr AS (SELECT present, {H60} // pow(2, 60 - p)::BIGINT AS fp FROM (SELECT DISTINCT k, true AS present FROM ({TRIPLES}) UNION ALL SELECT k, false FROM ({ABSENT})), par),
        r AS (SELECT f, present, coalesce(read, (SELECT count(*) FROM o WHERE o.f = fans.f)) AS reads FROM pr CROSS JOIN fans LEFT JOIN held USING (fp, f))
    SELECT f::BIGINT AS fanout, (SELECT max(levels) FROM s WHERE s.f = r.f)::INTEGER AS max_levels, round((SELECT avg(levels) FROM s WHERE s.f = r.f AND epoch > 0), 6) AS mean_levels, sum(reads) FILTER (WHERE present)::BIGINT AS present_reads, sum(reads) FILTER (WHERE NOT present)::BIGINT AS absent_reads FROM r GROUP BY f""")
def w09(spark, d):
    """Fan-out 2, 4, 16: filters filled through twelve buffers, then looked up."""
    probes, rows = lookups(spark, d).cache(), None
    for f in (2, 4, 16):
        one = _fan(spark, d, f)
        levels = one.history().agg(F.max("levels").alias("max_levels"), F.round(F.avg("levels"), 6).alias("mean_levels"))
        reads = one.probe(probes).agg(F.sum(F.when(F.col("present"), F.col("levels_read"))).alias("present_reads"), F.sum(F.when(~F.col("present"), F.col("levels_read"))).alias("absent_reads"))
        r = levels.crossJoin(reads).select(F.lit(f).cast("long").alias("fanout"), "*")  # one row each
        rows = r if rows is None else rows.unionByName(r)
    return rows


B24 = "SELECT 2 * count(*) // 49 AS b FROM lineitem"


@query("level_profile", "SELECT e::BIGINT AS epoch, bit_count(e)::INTEGER AS levels FROM range(1, 25) t(e)")
def level_profile(spark, d):
    """Non-empty levels after each flush of the run at 1:24, from its catalogue: the set bits of the flush's number."""
    return filled(spark, d, 24).history().select("epoch", "levels")


@query("stall_profile", f"SELECT max(u)::BIGINT * b AS largest, min(e) FILTER (WHERE u = 16)::BIGINT AS first_at FROM (SELECT e, e & -e AS u FROM range(1, 25) t(e)), ({B24}) GROUP BY b")
def stall_profile(spark, d):
    """Items of the largest merge of the run at 1:24, and the flush that waited for it."""
    return filled(spark, d, 24).history().agg(F.max("written").alias("largest"), F.min_by("epoch", F.struct(-F.col("written"), F.col("epoch"))).alias("first_at"))


@query("insert_cost_curve", f"SELECT e::BIGINT AS epoch, (sum(e) OVER (ORDER BY e))::BIGINT * b AS one_filter, (sum(e & -e) OVER (ORDER BY e))::BIGINT * b AS levelled FROM range(1, 25) t(e), ({B24})")
def insert_cost_curve(spark, d):
    """Items written up to each flush, by the two-tier and the levelled filter of the run at 1:24."""
    from pyspark.sql import Window

    w = Window.orderBy("epoch")  # one row a flush
    one, many = (filled(spark, d, 24, k).history().select("epoch", F.sum("written").over(w).alias(n)) for k, n in ((tiered.TwoTierFilter, "one_filter"), (tiered.LevelledFilter, "levelled")))
    return one.join(many, "epoch")


RATIO = 4
HELD4 = f"""WITH par AS (SELECT count(*) AS n, 2 * count(*) // 9 AS b, ceil(log2(count(*) / 0.75))::BIGINT + 12 AS p FROM lineitem), arr AS (SELECT k, row_number() OVER (ORDER BY md5(k), k) AS seq FROM ({TRIPLES})),
    held AS (SELECT {H60} // pow(2, 60 - p)::BIGINT AS fp, bool_or(seq > 4 * b) AS fresh FROM arr, par GROUP BY 1), f AS (SELECT fresh FROM (SELECT DISTINCT k, {H60} // pow(2, 60 - p)::BIGINT AS fp FROM ({TRIPLES}), par) JOIN held USING (fp))"""


@query("buffer_hit_share", HELD4 + " SELECT s AS structure, count(*) AS lookups, count(*) FILTER (WHERE fresh) AS in_buffer, round(count(*) FILTER (WHERE fresh) / count(*), 6) AS share FROM f, (VALUES ('two-tier'), ('levelled')) t(s) GROUP BY 1")
def buffer_hit_share(spark, d):
    """Lookups of present keys that end in the buffer of a filter at 1:4."""
    present, out = src.triple_keys(spark, d).distinct(), None
    for name, kind in (("two-tier", tiered.TwoTierFilter), ("levelled", tiered.LevelledFilter)):
        hit = F.count(F.when(F.col("level") == 0, 1))
        row = filled(spark, d, RATIO, kind).probe(present).agg(F.count("*").alias("lookups"), hit.alias("in_buffer"), F.round(hit / F.count("*"), 6).alias("share")).select(F.lit(name).alias("structure"), "*")
        out = row if out is None else out.unionByName(row)
    return out


def _epochs_sql() -> str:
    lane = lambda i: f"('0x' || substr(sha256('0:' || k) || sha256('1:' || k), ({i}) * 9 + 1, 9))::BIGINT"
    return f"""WITH par AS (SELECT count(*) AS n, 2 * count(*) // 9 AS b, ceil(-count(*) * ln(pow(2, -12)) / pow(ln(2), 2))::BIGINT AS m FROM lineitem), size AS (SELECT * FROM par), arr AS (SELECT k, row_number() OVER (ORDER BY md5(k), k) AS seq FROM ({TRIPLES})),
        d AS (SELECT (seq - 1) // b + 1 AS epoch, seq, list_transform({lanes(K_BUFFERED)}, lambda x: x % m // {BLOCK}) AS pages, {lane('0')} AS lane, b, (m + {BLOCK - 1}) // {BLOCK} AS blocks FROM arr, par WHERE seq <= 4 * b), e AS (SELECT i AS epoch, b FROM range(1, 5) t(i), par)
        SELECT 'direct' AS structure, epoch, sum(len(list_distinct(pages)))::BIGINT AS random_writes, 0::BIGINT AS sequential_writes FROM d GROUP BY epoch UNION ALL
        SELECT 'write-buffered', epoch, count(DISTINCT page), 0 FROM (SELECT epoch, unnest(pages) AS page FROM d) GROUP BY epoch UNION ALL
        SELECT 'page-local', epoch, count(*) FILTER (WHERE i % greatest(1, b // blocks) = 0), 0 FROM (SELECT *, row_number() OVER (PARTITION BY lane % blocks ORDER BY seq) AS i FROM d) GROUP BY epoch UNION ALL
        SELECT 'two-tier', epoch, 0, (epoch * b + 255) // 256 FROM e UNION ALL SELECT 'levelled', epoch, 0, ((epoch & -epoch) * b + 255) // 256 FROM e"""


@query("io_profile", _epochs_sql())
def io_profile(spark, d):
    """Blocks written in each epoch of a run at 1:4, by each structure; `direct` is the classic filter without a buffer."""
    keys = src.triple_keys(spark, d)
    n = keys.count()
    b = buffer_of(n, RATIO)
    arrived = src.arrivals(keys).filter(F.col("seq") <= RATIO * b).cache()
    epoch = (F.call_function("div", F.col("seq") - 1, F.lit(b).cast("long")) + 1).alias("epoch")
    zero = F.lit(0).cast("long")
    w = bloom.BloomFilter.for_items(n, 2.0**-12, K_BUFFERED)
    p = bloom.PageLocalBloom.for_items(n, 2.0**-12, BLOCK, K_LOCAL)
    pages = F.size(F.array_distinct(F.transform(w.positions(F.col("k")), lambda x: F.call_function("div", x, F.lit(BLOCK).cast("long")))))
    grid = spark.range(1, RATIO + 1).toDF("epoch")
    rows = {
        "direct": arrived.groupBy(epoch).agg(F.sum(pages).alias("random_writes")),
        "write-buffered": bloom.write_buffered_writes(arrived, w, b, BLOCK).select((F.col("epoch") + 1).alias("epoch"), F.col("page_writes").alias("random_writes")),
        "page-local": p.flush_times(arrived, max(1, b // p.blocks)).groupBy(epoch).agg(F.count("*").alias("random_writes")),
    }
    out = None
    for name, r in rows.items():
        r = grid.join(r, "epoch", "left").select(F.lit(name).alias("structure"), "epoch", F.coalesce("random_writes", zero).cast("long").alias("random_writes"), zero.alias("sequential_writes"))
        out = r if out is None else out.unionByName(r)
    for name, kind in (("two-tier", tiered.TwoTierFilter), ("levelled", tiered.LevelledFilter)):
        out = out.unionByName(filled(spark, d, RATIO, kind).history().select(F.lit(name).alias("structure"), "epoch", zero.alias("random_writes"), _blocks(F.col("written")).alias("sequential_writes")))
    return out


def _w01_sql() -> str:
    lane = lambda i: f"('0x' || substr(sha256('0:' || k) || sha256('1:' || k), ({i}) * 9 + 1, 9))::BIGINT"
    return f"""WITH par AS (SELECT count(*) AS n, 2 * count(*) // 9 AS b, ceil(log2(count(*) / 0.75))::BIGINT AS q, ceil(-count(*) * ln(pow(2, -12)) / pow(ln(2), 2))::BIGINT AS m FROM lineitem), size AS (SELECT * FROM par), at_ AS (SELECT (m + {BLOCK - 1}) // {BLOCK} AS blocks FROM par),
        f AS (SELECT count(DISTINCT {H60} // pow(2, 48 - q)::BIGINT) AS cells FROM ({TRIPLES}), par), cb AS (SELECT count(DISTINCT bit) AS cells FROM (SELECT unnest({lanes(K_BUFFERED)}) % m AS bit FROM ({TRIPLES}), size)),
        lb AS (SELECT count(DISTINCT bit) AS cells FROM (SELECT unnest(list_transform(range(1, {K_LOCAL + 1}), lambda i: {lane('0')} % blocks * {BLOCK} + {lane('i')} % {BLOCK})) AS bit FROM ({TRIPLES}), at_)),
        ya AS (SELECT k, b, floor(log2(1 + (seq - 1) // b) + 1e-9)::BIGINT AS layer FROM (SELECT k, row_number() OVER (ORDER BY md5(k), k) AS seq FROM ({TRIPLES})), par), yb AS (SELECT count(DISTINCT bit) AS cells FROM (SELECT unnest({layered_bits('k', K_LAYERED, 'b', 18, 8)}) AS bit FROM ya)),
        ys AS (SELECT sum((b * 18 * pow(2, layer)::BIGINT + {BLOCK - 1}) // {BLOCK}) * {BLOCK} AS size FROM (SELECT DISTINCT layer, b FROM ya))
        SELECT s AS structure, n AS items, cells, round(n / pow(2, q), 6) AS fill FROM f, par, (VALUES ('quotient'), ('two-tier'), ('levelled')) t(s) UNION ALL SELECT s, n, cells, round(cells / m, 6) FROM cb, par, (VALUES ('classic'), ('write-buffered')) t(s)
        UNION ALL SELECT 'page-local', n, cells, round(cells / (blocks * {BLOCK}), 6) FROM lb, par, at_ UNION ALL SELECT 'layered', n, cells, round(cells / size, 6) FROM yb, par, ys"""


@query("w01_uniform_inserts", _w01_sql())
def w01(spark, d):
    """All lines' keys into seven structures at a rate of 1/4096: items, distinct fingerprints or bits, and how full each is."""
    from ..operators import quotient as qf

    keys = src.triple_keys(spark, d)
    n = keys.count()
    spec, b = spec_for(keys, 12), buffer_of(n, RATIO)
    arrived = src.arrivals(keys).cache()
    items = {"quotient": qf.build_fp(keys, spec), "two-tier": filled(spark, d, RATIO, tiered.TwoTierFilter).contents(), "levelled": filled(spark, d, RATIO, tiered.LevelledFilter).contents()}
    w, p, y = bloom.BloomFilter.for_items(n, 2.0**-12, K_BUFFERED), bloom.PageLocalBloom.for_items(n, 2.0**-12, BLOCK, K_LOCAL), bloom.LayeredBloom(b, 18, K_LAYERED, BLOCK)
    half = F.col("seq") <= n // 2
    words = {"classic": (w.build(keys), w.m), "write-buffered": (w.union(w.build(arrived.filter(half)), w.build(arrived.filter(~half))), w.m), "page-local": (p.build(keys), p.blocks * p.block_bits), "layered": (y.build(arrived, n), sum(y.blocks(i) for i in range(y.layers(n))) * BLOCK)}
    out = None
    for name, f in items.items():
        row = f.agg(F.sum("cnt").alias("items"), F.count("*").alias("cells"), F.round(F.sum("cnt") / spec.slots, 6).alias("fill")).select(F.lit(name).alias("structure"), "*")
        out = row if out is None else out.unionByName(row)
    for name, (f, size) in words.items():
        cells = F.sum(F.bit_count("word")).cast("long")
        out = out.unionByName(f.agg(F.lit(n).cast("long").alias("items"), cells.alias("cells"), F.round(cells / size, 6).alias("fill")).select(F.lit(name).alias("structure"), "*"))
    return out
