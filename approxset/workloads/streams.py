"""Filters over streams; each result equals its batch twin over the same rows."""

from __future__ import annotations

import uuid

from pyspark.sql import functions as F

from ..operators import quotient as qf
from ..operators import tiered
from ..sources import tables as src
from ..streaming import jobs
from .base import H60, fps, query, spec_for
from ..cluster import work_folder

USERS = "SELECT user_id::VARCHAR AS k FROM events"
EVENTS = "SELECT event_id::VARCHAR AS k FROM events"


def _fps(keys):
    return f"WITH {fps(keys)} SELECT fp, cnt FROM fps"


for _n, _k in (("st_ingest_tqf", tiered.TwoTierFilter), ("st_ingest_lqf", tiered.LevelledFilter)):

    @query(_n, _fps(EVENTS))
    def _(spark, d, k=_k):
        """Each micro-batch fills and flushes a buffer; a replayed batch changes nothing."""
        e = src.table(spark, d, "events")
        keys = e.select(src.key_text("event_id").alias("k"))
        folder = work_folder(spark)
        f = k(spark, f"{folder}/filter", spec_for(keys), -(-keys.count() // 5))
        jobs.ingest(jobs.feed(spark, e, f"{folder}/in", 5), f, "event_id", f"{folder}/checkpoint")
        return f.contents()


WINDOW = "SELECT {w} AS start, event_type, count(*) AS n FROM events GROUP BY 1, 2"


@query("st_tumbling", "SELECT epoch(date_trunc('hour', ts))::BIGINT AS start, event_type, count(*) AS n FROM events GROUP BY 1, 2")
def st_tumbling(spark, d):
    return jobs.windowed(spark, src.table(spark, d, "events"), work_folder(spark), F.window("ts", "1 hour"))


@query("st_sliding", "SELECT epoch(date_trunc('hour', ts))::BIGINT - i * 3600 AS start, event_type, count(*) AS n FROM events, range(0, 2) t(i) GROUP BY 1, 2")
def st_sliding(spark, d):
    return jobs.windowed(spark, src.table(spark, d, "events"), work_folder(spark), F.window("ts", "2 hours", "1 hour"))


@query("st_session", """WITH e AS (SELECT user_id, ts, ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts) <= INTERVAL 30 MINUTE AS joins FROM events),
    s AS (SELECT user_id, ts, count(*) FILTER (WHERE joins IS NOT TRUE) OVER (PARTITION BY user_id ORDER BY ts RANGE UNBOUNDED PRECEDING) AS i FROM e)
    SELECT epoch_us(min(ts)) AS start, user_id, count(*) AS n FROM s GROUP BY user_id, i""")
def st_session(spark, d):
    return jobs.sessions(spark, src.table(spark, d, "events"), work_folder(spark))


LATE, FILES = 2, 5
LO, HI = f"lo + (hi - lo + 1) * {LATE} // {FILES}", f"lo + (hi - lo + 1) * {LATE + 1} // {FILES}"


@query("st_late", f"""WITH b AS (SELECT min(event_id) AS lo, max(event_id) AS hi FROM events)
    SELECT epoch(date_trunc('hour', ts))::BIGINT AS start, count(*) AS n FROM events, b WHERE event_id < {LO} OR event_id >= {HI} GROUP BY 1""")
def st_late(spark, d):
    """The third of five files comes last: its windows are closed, so all its rows are dropped."""
    return jobs.hourly_without_late(spark, src.table(spark, d, "events"), work_folder(spark), LATE)


@query("st_stream_join", "SELECT a.event_id AS click, b.event_id AS purchase FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_type = 'click' AND b.event_type = 'purchase' AND b.ts BETWEEN a.ts AND a.ts + INTERVAL 1 HOUR")
def st_stream_join(spark, d):
    return jobs.purchases_after_clicks(spark, src.table(spark, d, "events"), work_folder(spark))


@query("st_interleaved", f"""WITH b AS (SELECT min(o_orderkey) AS lo, max(o_orderkey) AS hi FROM orders),
    o AS (SELECT o_orderkey, (SELECT count(*) FROM range(1, {FILES}) t(i) WHERE o_orderkey - lo >= (hi - lo + 1) * i // {FILES}) AS batch FROM orders, b),
    spec AS (SELECT greatest(1, ceil(log2(count(*) / 0.75)))::BIGINT + 9 AS p FROM orders),
    put AS (SELECT {H60.replace('k)', 'o_orderkey::VARCHAR)')} // pow(2, 60 - p)::BIGINT AS fp, min(batch) AS batch FROM o, spec GROUP BY 1),
    ask AS (SELECT o_orderkey, batch, (o_orderkey + i * (hi - lo + 1) // 2)::VARCHAR AS k FROM o, b, range(0, 3) t(i))
    SELECT o_orderkey AS event_id, k, coalesce(put.batch <= ask.batch, false) AS maybe FROM ask, spec LEFT JOIN put ON fp = {H60} // pow(2, 60 - p)::BIGINT""")
def st_interleaved(spark, d):
    """Each batch inserts its orders, then looks up them, keys half the domain on, and keys outside."""
    o = src.table(spark, d, "orders").select(F.col("o_orderkey").alias("event_id"), F.col("o_orderdate").alias("ts"))
    lo, hi = o.agg(F.min("event_id"), F.max("event_id")).first()
    puts = o.select("*", F.lit("insert").alias("op"), src.key_text("event_id").alias("k"))
    asks = o.select("*", F.lit("lookup").alias("op"), F.explode(F.array(*[(F.col("event_id") + i * (hi - lo + 1) // 2).cast("string") for i in range(3)])).alias("k"))
    folder = work_folder(spark)
    f = tiered.LevelledFilter(spark, f"{folder}/filter", spec_for(puts), -(-o.count() // FILES))
    return jobs.interleaved(spark, puts.unionByName(asks), f, folder, FILES)


@query("st_dedup_exact", "SELECT DISTINCT event_id FROM events")
def st_dedup_exact(spark, d):
    """A file delivered twice."""
    return jobs.deduplicated(spark, src.table(spark, d, "events"), work_folder(spark))


@query("st_dedup_filter", "SELECT event_id FROM events")
def st_dedup_filter(spark, d):
    """First sightings by a packed filter per shard in the state store; at 48 bits none is dropped by a shared fingerprint here."""
    return jobs.filtered(spark, src.table(spark, d, "events"), work_folder(spark))


CUST = "SELECT c_custkey::VARCHAR AS k FROM customer"


@query("st_static_probe", f"WITH {fps(CUST)} SELECT event_id, coalesce({H60.replace('k)', 'user_id::VARCHAR)')} // pow(2, 60 - p)::BIGINT IN (SELECT fp FROM fps), false) AS maybe FROM events, spec")
def st_static_probe(spark, d):
    """Events against a stored filter of the customers, loaded again for each batch."""
    keys = src.table(spark, d, "customer").select(src.key_text("c_custkey").alias("k"))
    spec, path = spec_for(keys), f"{work_folder(spark)}/customers"
    qf.save(qf.pack(qf.build_fp(keys, spec), spec, 8), spec, 8, path)
    return jobs.probed(spark, src.table(spark, d, "events"), work_folder(spark), "user_id", lambda: qf.load(spark, path))


@query("st_new_vs_seen", "SELECT day, count(*) AS users, count(*) FILTER (WHERE day = first) AS new_users FROM (SELECT DISTINCT user_id, epoch(date_trunc('day', ts))::BIGINT AS day, min(epoch(date_trunc('day', ts))::BIGINT) OVER (PARTITION BY user_id) AS first FROM events) GROUP BY 1")
def st_new_vs_seen(spark, d):
    """A day's users, and those that no earlier day has seen: filters in state pass the first sighting of a user on a day, and
    of a user at all."""
    e = src.table(spark, d, "events").select("event_id", "ts", "user_id", F.unix_seconds(F.date_trunc("day", F.col("ts").cast("timestamp"))).alias("day"))
    days = jobs.sightings(spark, e, work_folder(spark), ["user_id", "day"], "event_id long, day long").groupBy("day").agg(F.count("*").alias("users"))
    new = jobs.sightings(spark, e, work_folder(spark), ["user_id"], "event_id long, day long").groupBy("day").agg(F.count("*").alias("new_users"))
    return days.join(new, "day", "left").select("day", "users", F.coalesce("new_users", F.lit(0)).alias("new_users"))


@query("st_sliding_seen", f"""WITH e AS (SELECT DISTINCT user_id, epoch(date_trunc('day', ts))::BIGINT // 86400 AS day FROM events)
    SELECT a.day, count(*) AS users, count(*) FILTER (WHERE EXISTS (SELECT 1 FROM e b WHERE b.user_id = a.user_id AND b.day BETWEEN a.day - 2 AND a.day - 1)) AS seen FROM e a GROUP BY 1""")
def st_sliding_seen(spark, d):
    """Users seen in the last two days: daily panes are merged, and subtracted when they leave the window."""
    return jobs.sliding_seen(spark, src.table(spark, d, "events"), work_folder(spark))


@query("w16_stream_users", "SELECT event_type, count(*) AS events, count(DISTINCT user_id) AS users FROM events GROUP BY 1")
def w16(spark, d):
    """Events and users by type from a stream that brings a file twice: one filter has seen the events, one the users of a type."""
    e = src.table(spark, d, "events").select("event_id", "ts", "user_id", "event_type")
    events = jobs.sightings(spark, e, work_folder(spark), ["event_id"], "event_id long, event_type string").groupBy("event_type").agg(F.count("*").alias("events"))
    users = jobs.sightings(spark, e, work_folder(spark), ["event_type", "user_id"], "event_id long, event_type string").groupBy("event_type").agg(F.count("*").alias("users"))
    return events.join(users, "event_type")
