"""Structured Streaming jobs over a table fed as files, run until the input is drained."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..cluster import ship
from ..sources.tables import key_text

#: Fingerprint bits of filters in state, and the load at which their slots double.
BITS, MAX_LOAD = 48, 0.75


def feed(spark: SparkSession, events: DataFrame, folder: str, files: int, again: int | None = None, late: int | None = None, closing: bool = False) -> DataFrame:
    """The events as a stream of files by id range, timestamps with zone.

    `again` delivers a file twice, `late` delivers it after the others, `closing` ends with one row of a year later, without
    id, type or user, which moves the watermark past every window."""
    lo, hi = events.agg(F.min("event_id"), F.max("event_id")).first()
    d = events.withColumn("ts", F.col("ts").cast("timestamp"))
    order = [*(i for i in range(files) if i != late), *(i for i in (again, late) if i is not None)]
    for i in order:
        a, b = lo + (hi - lo + 1) * i // files, lo + (hi - lo + 1) * (i + 1) // files
        d.filter((F.col("event_id") >= a) & (F.col("event_id") < b)).coalesce(1).write.mode("append").parquet(folder)
    if closing:
        end = d.agg((F.max("ts") + F.expr("INTERVAL 366 DAYS")).alias("ts"))
        end.select(*[F.col(f.name) if f.name == "ts" else F.lit(None).cast(f.dataType).alias(f.name) for f in d.schema]).coalesce(1).write.mode("append").parquet(folder)
    return spark.readStream.schema(d.schema).option("maxFilesPerTrigger", 1).parquet(folder)


def stream(spark, events, folder, files=5, again=None, late=None, closing=False) -> DataFrame:
    return feed(spark, events, f"{folder}/in", files, again, late, closing)


def drained(query: DataFrame, folder: str, mode: str = "append") -> DataFrame:
    """Run to the end of the input into Parquet (append) and read it."""
    spark = query.sparkSession
    q = query.writeStream.format("parquet").option("path", f"{folder}/out").option("checkpointLocation", f"{folder}/checkpoint").outputMode(mode).trigger(availableNow=True).start()
    q.awaitTermination()
    return spark.read.schema(query.schema).parquet(f"{folder}/out")


def ingest(source: DataFrame, target, key: str, checkpoint: str) -> None:
    """Micro-batches into a tiered filter; the batch's id is committed with its contents, so a replay is skipped."""

    def put(batch: DataFrame, batch_id: int) -> None:
        target.ingest(batch.select(key_text(key).alias("k")), batch=f"stream {batch_id}")

    source.writeStream.foreachBatch(put).option("checkpointLocation", checkpoint).trigger(availableNow=True).start().awaitTermination()


def windowed(spark, events, folder, window) -> DataFrame:
    """Counts per window and type; update mode through foreachBatch keeps the last count of each window."""
    s = stream(spark, events, folder).withWatermark("ts", "2 days")
    counts = s.groupBy(window.alias("w"), "event_type").agg(F.count("*").alias("n")).select(F.unix_seconds("w.start").alias("start"), "event_type", "n")

    def put(batch: DataFrame, batch_id: int) -> None:
        batch.withColumn("batch", F.lit(batch_id)).write.mode("overwrite").parquet(f"{folder}/out/batch={batch_id}")

    counts.writeStream.outputMode("update").foreachBatch(put).option("checkpointLocation", f"{folder}/checkpoint").trigger(availableNow=True).start().awaitTermination()
    out = spark.read.schema("start long, event_type string, n long, batch int").option("recursiveFileLookup", "true").parquet(f"{folder}/out")
    return out.groupBy("start", "event_type").agg(F.max_by("n", "batch").alias("n"))


def sessions(spark, events, folder, gap: str = "30 minutes") -> DataFrame:
    """A user's events at most `gap` apart; a session leaves the state when the watermark passes its end.

    No filter by user: Catalyst would push it below the watermark and take the closing row away."""
    s = stream(spark, events, folder, closing=True).withWatermark("ts", "2 days")
    w = s.groupBy(F.session_window("ts", gap).alias("w"), "user_id").agg(F.count("*").alias("n"))
    return drained(w.select(F.unix_micros("w.start").alias("start"), "user_id", "n"), folder)


def hourly_without_late(spark, events, folder, late: int) -> DataFrame:
    """Hourly counts under a watermark of one hour; rows of windows that are already closed are dropped."""
    s = stream(spark, events, folder, late=late, closing=True).withWatermark("ts", "1 hour")
    w = s.groupBy(F.window("ts", "1 hour").alias("w")).agg(F.count("event_id").alias("n"))
    return drained(w.select(F.unix_seconds("w.start").alias("start"), "n").filter("n > 0"), folder)


def purchases_after_clicks(spark, events, folder, within: str = "1 HOUR") -> DataFrame:
    """Stream-stream join by user inside an interval; the watermarks bound both sides' state."""
    s = stream(spark, events, folder)
    c = s.filter("event_type = 'click'").select(F.col("event_id").alias("click"), F.col("user_id").alias("cu"), F.col("ts").alias("ct")).withWatermark("ct", "2 days")
    p = s.filter("event_type = 'purchase'").select(F.col("event_id").alias("purchase"), F.col("user_id").alias("pu"), F.col("ts").alias("pt")).withWatermark("pt", "2 days")
    return drained(c.join(p, F.expr(f"cu = pu AND pt >= ct AND pt <= ct + INTERVAL {within}")).select("click", "purchase"), folder)


def interleaved(spark, ops: DataFrame, target, folder, files: int = 5) -> DataFrame:
    """Rows (event_id, ts, op, k): a batch's inserts go into the filter, then its lookups are answered.

    A replayed batch inserts nothing twice and overwrites its own answers."""

    def put(batch: DataFrame, batch_id: int) -> None:
        target.ingest(batch.filter("op = 'insert'").select("k"), batch=f"stream {batch_id}")
        target.probe(batch.filter("op = 'lookup'").select("event_id", "k")).select("event_id", "k", "maybe").write.mode("overwrite").parquet(f"{folder}/out/batch={batch_id}")

    feed(spark, ops, f"{folder}/in", files).writeStream.foreachBatch(put).option("checkpointLocation", f"{folder}/checkpoint").trigger(availableNow=True).start().awaitTermination()
    return spark.read.schema("event_id long, k string, maybe boolean").option("recursiveFileLookup", "true").parquet(f"{folder}/out")


def deduplicated(spark, events, folder) -> DataFrame:
    s = stream(spark, events, folder, 5, again=2).withWatermark("ts", "30 days")
    return drained(s.dropDuplicatesWithinWatermark(["event_id"]).select("event_id"), folder)


def sorted_state(fps) -> bytes:
    """Sorted fingerprints of `BITS` bits, with repeats, as one packed filter whose slots are a power of two at `MAX_LOAD`."""
    from ..functions.udfs import encode

    q = max(6, int(len(fps) / MAX_LOAD).bit_length())
    return encode(fps, 0, 1 << q, BITS - q, 1 << (BITS - q))


def known(fps, state):
    """Whether each fingerprint is in the sorted state."""
    import numpy as np

    at = np.searchsorted(state, fps)
    return (at < len(state)) & (state[np.minimum(at, max(len(state) - 1, 0))] == fps) if len(state) else np.zeros(len(fps), bool)


def keyed(s: DataFrame, *key: str, shards: int = 0) -> DataFrame:
    """The stream with `shard` and `fp` of a key: a shard's filter grows with its keys, and hashes deal keys evenly."""
    h = F.xxhash64(*key)
    return s.withColumn("shard", F.pmod(F.shiftrightunsigned(h, 40), F.lit(shards or max(8, int(s.sparkSession.conf.get("spark.sql.shuffle.partitions")))))).withColumn("fp", F.pmod(h, F.lit(1 << BITS)))


def first_sightings(s: DataFrame, order: str, carry: str) -> DataFrame:
    """Of the stream (shard, fp, ...), the columns `carry` (a schema) of the rows whose fingerprint wasn't there before.

    Each shard's state is one packed quotient filter. A batch sorts its rows by `order`, looks all up at once, and
    adds what is new; where the load passes `MAX_LOAD`, a bit of the remainder becomes one of the quotient."""
    import numpy as np
    import pandas as pd
    from pyspark.sql.streaming.state import GroupStateTimeout

    names = [c.split(" ")[0] for c in carry.split(", ")]

    def first(key, batches, state):
        from approxset.functions.udfs import decode

        seen = decode(bytes(state.get[0])) if state.exists else np.zeros(0, np.int64)
        rows = pd.concat(list(batches)).sort_values(order, kind="stable")
        fp, at = np.unique(rows["fp"].to_numpy(), return_index=True)
        new = ~known(fp, seen)
        state.update((sorted_state(np.sort(np.concatenate([seen, fp[new]]))),))
        yield rows.iloc[np.sort(at[new])][names]

    s = s.select("shard", "fp", *dict.fromkeys([order, *names]))
    return s.groupBy("shard").applyInPandasWithState(first, carry, "filter binary", "append", GroupStateTimeout.NoTimeout)


def filtered(spark, events, folder, shards: int = 0) -> DataFrame:
    """First sightings of event ids, of which a file comes twice: false positives may drop, repeats never pass."""
    ship(spark)
    return drained(first_sightings(keyed(stream(spark, events, folder, 5, again=2), "event_id", shards=shards), "event_id", "event_id long"), folder)


def sightings(spark, events, folder, key: list[str], carry: str) -> DataFrame:
    """First sightings of the key in the order of event ids, with the columns `carry`; a file comes twice."""
    ship(spark)
    return drained(first_sightings(keyed(stream(spark, events, folder, 5, again=2), *key), "event_id", carry), folder)


def sliding_seen(spark, events, folder, days: int = 2) -> DataFrame:
    """(day, users, seen): a day's users, and how many of them the `days` days before have seen.

    A shard's state is a pane for each day, a packed filter of its users, and the merged filter of the closed panes in
    the window, a multiset. When a day begins, the pane before it is merged in, and panes that leave the window are
    subtracted: one copy of each of their users is deleted. Rows of closed days come too late and are dropped."""
    import numpy as np
    import pandas as pd
    from pyspark.sql.streaming.state import GroupStateTimeout

    ship(spark)

    def slide(key, batches, state):
        from approxset.functions.udfs import decode

        none = np.zeros(0, np.int64)
        panes, merged = {}, none
        if state.exists:
            kept, payloads, whole = state.get
            panes = {int(d): decode(bytes(p)) for d, p in zip(kept, payloads, strict=True)}
            merged = decode(bytes(whole))
        rows = pd.concat(list(batches))
        out = []
        for day, fps in sorted(rows.groupby("day")["fp"]):
            now = max(panes, default=None)
            if now is not None and day < now:
                continue
            if now is not None and day > now:
                merged = np.sort(np.concatenate([merged, panes[now]]))
            for old in [d for d in panes if d < day - days]:
                gone = panes.pop(old)
                merged = np.delete(merged, np.searchsorted(merged, gone))  # one copy each
            mine = panes.get(day, none)
            fp = np.unique(fps.to_numpy())
            fp = fp[~known(fp, mine)]
            out.append((day, len(fp), int(known(fp, merged).sum())))
            panes[day] = np.sort(np.concatenate([mine, fp]))
        order = sorted(panes)
        state.update((order, [sorted_state(panes[d]) for d in order], sorted_state(merged)))
        yield pd.DataFrame(out, columns=["day", "users", "seen"])

    s = keyed(stream(spark, events, folder), "user_id").withColumn("day", F.unix_date(F.col("ts").cast("date")).cast("long"))
    parts = s.select("shard", "fp", "day").groupBy("shard").applyInPandasWithState(slide, "day long, users long, seen long", "days array<long>, panes array<binary>, merged binary", "append", GroupStateTimeout.NoTimeout)
    return drained(parts, folder).groupBy("day").agg(F.sum("users").alias("users"), F.sum("seen").alias("seen"))


def probed(spark, events, folder, key: str, load) -> DataFrame:
    """Rows of a stream against a stored filter, which each batch loads anew (`load() -> packed, spec, shards`) and broadcasts
    under the size check of `probe_broadcast`."""
    from ..operators.quotient import probe_broadcast

    def put(batch: DataFrame, batch_id: int) -> None:
        packed, spec, shards = load()
        probe_broadcast(batch.select("event_id", key_text(key).alias("k")), packed, spec, shards).select("event_id", "maybe").write.mode("overwrite").parquet(f"{folder}/out/batch={batch_id}")

    stream(spark, events, folder).writeStream.foreachBatch(put).option("checkpointLocation", f"{folder}/checkpoint").trigger(availableNow=True).start().awaitTermination()
    return spark.read.schema("event_id long, maybe boolean").option("recursiveFileLookup", "true").parquet(f"{folder}/out")
