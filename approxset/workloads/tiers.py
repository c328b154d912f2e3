"""Two-tier and levelled filters over epochs of arrivals."""

from __future__ import annotations

from pyspark.sql import functions as F

from ..operators import quotient as qf
from ..operators import tiered
from ..sources import tables as src
from .base import ABSENT, H60, LINES, ORDERS, count_of, fps, query, spec_for
from ..cluster import cleaned, drop_folder, work_folder
from .membership import _probed


def fed(f: tiered.LevelledFilter, arrived, buffer: int):
    """The filter after arrivals (k, seq), one batch for each `buffer` of them; the last may be less and is held.

    The batches' fingerprints are written once, and files that a flush has replaced are deleted: nobody else reads the filter yet."""
    spark, folder = f.spark, work_folder(f.spark)
    with cleaned(spark):
        qf.build_fp(arrived, f.spec, F.call_function("div", F.col("seq") - 1, F.lit(buffer).cast("long")).alias("epoch")).write.partitionBy("epoch").parquet(folder)
        epochs = spark.read.schema("fp long, cnt long, epoch long").parquet(folder).select("epoch").distinct().collect()  # one row an epoch
        for (e,) in sorted(epochs):
            f.ingest_fps(spark.read.schema("fp long, cnt long").parquet(f"{folder}/epoch={e}"), batch=f"epoch {e}")
            f.vacuum()
    drop_folder(spark, folder)
    return f


def ends(n: int, buffer: int) -> list[int]:
    """The last arrival of each full buffer."""
    return list(range(buffer, n + 1, buffer))


def ingested(spark, d, kind, epochs=6, deletes=False, buffer=None, **more):
    """A filter fed with the orders' keys in `epochs` buffers by arrival."""
    keys = src.order_keys(spark, d)
    n = keys.count()
    buffer = buffer or -(-n // epochs)
    arrived = src.arrived_by(keys, ends(n, buffer))
    f = fed(kind(spark, work_folder(spark), spec_for(keys), buffer, **more), arrived, buffer)
    if deletes:
        gone = src.table(spark, d, "orders").filter("o_orderstatus = 'F'").select(src.key_text("o_orderkey").alias("k"))
        f.delete(gone, batch="delete")
    return f, arrived


CONTENTS = f"WITH {fps(ORDERS)} SELECT fp, cnt FROM fps"
LEFT = f"WITH {fps(ORDERS)}, kept AS (SELECT {H60} // pow(2, 60 - p)::BIGINT AS fp, count(*) AS cnt FROM (SELECT o_orderkey::VARCHAR AS k FROM orders WHERE o_orderstatus <> 'F'), spec GROUP BY 1) SELECT fp, cnt FROM kept"

for _n, _k in (("tqf", tiered.TwoTierFilter), ("lqf", tiered.LevelledFilter)):

    @query(f"{_n}_contents", CONTENTS)
    def _(spark, d, k=_k):
        return ingested(spark, d, k)[0].contents()

    @query(f"{_n}_delete", LEFT)
    def _(spark, d, k=_k):
        return ingested(spark, d, k, deletes=True)[0].contents()


ARR = f"SELECT k, row_number() OVER (ORDER BY md5(k), k) AS seq FROM ({ORDERS})"
#: After six epochs with fan-out 2: levels 2 (epochs 5, 6) and 3 (1 to 4).
LEVELLED = f"""WITH {fps(ORDERS)}, n AS (SELECT (count(*) + 5) // 6 AS b FROM orders), a AS (SELECT k, CASE WHEN (seq - 1) // b >= 4 THEN 2 ELSE 3 END AS level FROM ({ARR}), n),
    lv AS (SELECT {H60} // pow(2, 60 - p)::BIGINT AS fp, min(level)::INTEGER AS level FROM a, spec GROUP BY 1),
    pb AS (SELECT k, {H60} // pow(2, 60 - p)::BIGINT AS fp FROM (SELECT DISTINCT k FROM ({LINES}) UNION ALL {ABSENT}), spec)"""


@query("lqf_probe_levels", LEVELLED + " SELECT k, level IS NOT NULL AS maybe, level, CASE WHEN level = 2 THEN 1 ELSE 2 END::BIGINT AS levels_read FROM pb LEFT JOIN lv USING (fp)")
def lqf_probe_levels(spark, d):
    return ingested(spark, d, tiered.LevelledFilter)[0].probe(_probed(spark, d))


@query("lqf_precheck", LEVELLED + """, b AS (SELECT DISTINCT fp // width AS g, level FROM (SELECT {h} // pow(2, 60 - p)::BIGINT AS fp, level, width FROM a, spec)), occ AS (SELECT g, list(level) AS lvs FROM b GROUP BY g)
    SELECT count(*) AS probes, sum(CASE WHEN lvs IS NULL THEN 0 WHEN pb.level IS NULL THEN len(lvs) ELSE len(list_filter(lvs, lambda x: x <= pb.level)) END)::BIGINT AS levels_read
    FROM (SELECT pb.*, lv.level, pb.fp // width AS g FROM pb LEFT JOIN lv USING (fp), spec) pb LEFT JOIN occ USING (g)""".replace("{h}", H60))
def lqf_precheck(spark, d):
    """Reads that a bucket bitmap per level saves."""
    return ingested(spark, d, tiered.LevelledFilter)[0].probe(_probed(spark, d), precheck=True).agg(F.count("*").alias("probes"), F.sum("levels_read").alias("levels_read"))


#: Six full buffers and a rest of half a buffer: the rest is held.
HELD = f"""WITH {fps(ORDERS)}, n AS (SELECT 2 * count(*) // 13 AS b FROM orders), a AS (SELECT k, seq > 6 * b AS fresh FROM ({ARR}), n),
    t AS (SELECT {H60} // pow(2, 60 - p)::BIGINT AS fp, bool_or(fresh) AS fresh FROM a, spec GROUP BY 1), pb AS (SELECT k, {H60} // pow(2, 60 - p)::BIGINT AS fp FROM (SELECT DISTINCT k FROM ({LINES}) UNION ALL {ABSENT}), spec)"""


@query("tqf_probe_tiers", HELD + """ SELECT CASE WHEN fresh IS NULL THEN 'none' WHEN fresh THEN 'buffer' ELSE 'storage' END AS tier, count(*) AS probes, count(*) FILTER (WHERE fresh IS NULL OR NOT fresh) AS storage_reads FROM pb LEFT JOIN t USING (fp) GROUP BY 1""")
def tqf_probe_tiers(spark, d):
    """Where lookups of a filter end that holds a buffer: there, without a read, or in its one stored level."""
    keys = src.order_keys(spark, d)
    f, _ = ingested(spark, d, tiered.TwoTierFilter, buffer=2 * keys.count() // 13)
    tier = F.when(~F.col("maybe"), "none").when(F.col("level") == 0, "buffer").otherwise("storage")
    return f.probe(_probed(spark, d)).groupBy(tier.alias("tier")).agg(F.count("*").alias("probes"), F.sum("levels_read").alias("storage_reads"))


@query("lqf_equivalence", "SELECT 0::BIGINT AS only_levels, 0::BIGINT AS only_one")
def lqf_equivalence(spark, d):
    """The levels' fingerprints are those of one filter over everything."""
    f, _ = ingested(spark, d, tiered.LevelledFilter)
    a, b = f.contents(), qf.build_fp(src.order_keys(spark, d), f.spec)
    return spark.createDataFrame([(a.exceptAll(b).count(), b.exceptAll(a).count())], "only_levels long, only_one long")


@query("lqf_compact", CONTENTS)
def lqf_compact(spark, d):
    f, _ = ingested(spark, d, tiered.LevelledFilter)
    f.compact()
    return f.contents()


@query("lqf_schedule", "SELECT epoch, target, (units * b)::BIGINT AS items FROM (VALUES (1, 1, 1), (2, 2, 2), (3, 1, 1), (4, 3, 4), (5, 1, 1), (6, 2, 2), (7, 1, 1), (8, 4, 8)) t(epoch, target, units), (SELECT count(o_orderkey) // 8 AS b FROM orders)")
def lqf_schedule(spark, d):
    """The level that each flush goes to and the items it writes, where the orders' keys fill eight buffers."""
    b = count_of(src.order_keys(spark, d)) // 8
    return spark.createDataFrame([(e, t, u * b) for e, t, u, _ in tiered.merge_schedule(8, 2)], "epoch int, target int, items long")


FANOUT = "SELECT f::BIGINT AS fanout, (u * b)::BIGINT AS items, round(u / 24, 6) AS amplification, x::BIGINT AS max_levels, round(y / 24, 6) AS mean_levels FROM (VALUES (2, 68, 4, 54), (4, 78, 3, 48), (16, 114, 3, 40)) t(f, u, x, y), (SELECT count(o_orderkey) // 24 AS b FROM orders)"


@query("lqf_fanout_sweep", FANOUT)
def lqf_fanout_sweep(spark, d):
    """Items written by fan-out, where the orders' keys fill 24 buffers."""
    b, rows = count_of(src.order_keys(spark, d)) // 24, []
    for f in (2, 4, 16):
        s = tiered.merge_schedule(24, f)
        rows.append((f, b * sum(x[2] for x in s), round(sum(x[2] for x in s) / 24, 6), max(x[3] for x in s), round(sum(x[3] for x in s) / 24, 6)))
    return spark.createDataFrame(rows, "fanout long, items long, amplification double, max_levels long, mean_levels double")


@query("lqf_deamortised", """WITH RECURSIVE q AS (SELECT 0 AS epoch, 0 AS done, 0 AS waiting UNION ALL
        SELECT epoch + 1, least(6, waiting + new), waiting + new - least(6, waiting + new) FROM (SELECT *, CASE WHEN epoch % 2 = 1 THEN 16 ELSE 0 END AS new FROM q) WHERE epoch < 12)
    SELECT epoch::BIGINT AS epoch, done::BIGINT AS done, waiting::BIGINT AS waiting FROM q WHERE epoch > 0""")
def lqf_deamortised(spark, d):
    """Merge work of each flush where a merge is 16 tasks of which a flush does 6 at most: every second flush queues a merge."""
    return ingested(spark, d, tiered.DeamortisedFilter, epochs=12, per_flush=6)[0].progress()


@query("lqf_deamortised_contents", CONTENTS)
def lqf_deamortised_contents(spark, d):
    """Read while merges are waiting: sources and outputs of half-done merges together."""
    return ingested(spark, d, tiered.DeamortisedFilter, epochs=4, per_flush=6)[0].contents()


@query("tqf_page_writes", f"""WITH {fps(ORDERS)}, n AS (SELECT (count(*) + 5) // 6 AS b FROM orders), a AS (SELECT (seq - 1) // b AS epoch, {H60} // pow(2, 60 - p)::BIGINT // width // 256 AS page FROM ({ARR}), n, spec)
    SELECT epoch, count(DISTINCT page) AS page_writes, sum(count(*)) OVER (ORDER BY epoch)::BIGINT AS units_rewritten FROM a GROUP BY epoch""")
def tqf_page_writes(spark, d):
    """Storage pages each flush touches, and items of a whole rewrite."""
    from pyspark.sql import Window

    from ..functions.fingerprint import fingerprint, quotient_of

    keys = src.order_keys(spark, d)
    spec, b = spec_for(keys), -(-keys.count() // 6)
    a = src.arrivals(keys).select(F.call_function("div", F.col("seq") - 1, F.lit(b).cast("long")).alias("epoch"), F.call_function("div", quotient_of(fingerprint(F.col("k"), spec), spec), F.lit(256).cast("long")).alias("page"))
    g = a.groupBy("epoch").agg(F.countDistinct("page").alias("page_writes"), F.count("*").alias("n"))
    return g.select("epoch", "page_writes", F.sum("n").over(Window.orderBy("epoch")).alias("units_rewritten"))
