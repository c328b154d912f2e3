"""Quotient-filter variants of r + 2 bits a slot: synchronizers, a reserved remainder, ordering inside runs.

Shards are laid out in a line: a shard has as many slots as its last item needs and one empty slot behind it, so no run wraps.
Payloads hold (occupied, continuation, remainder) a slot and are read by lookups or decoded; each is tested by an exact
round trip and by lookups against the fingerprints."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..cluster import ship
from ..functions.fingerprint import fingerprint, quotient_of
from ..schema import FilterSpec, FilterSpecMismatch
from .quotient import bits_of, merge, shards_of, words_of

RANGES = 64
NAMES = "shard long, n long, slots long, payload binary, entries binary"


def _ends(fps: DataFrame, spec: FilterSpec) -> tuple[DataFrame, int]:
    """(g, last slot used by the bucket plus one, unwrapped) and how many slots wrap round.

    The items before a bucket and the running maximum give its end, as in the layout; both prefixes are taken inside
    ranges of buckets and shifted by the ranges before (`RANGES` rows)."""
    m = spec.slots
    heads = fps.groupBy(quotient_of(F.col("fp"), spec).alias("g")).agg(F.sum("cnt").alias("n"))
    order = Window.partitionBy("range").orderBy("g")
    h = heads.withColumn("range", F.call_function("div", F.col("g") * RANGES, F.lit(m).cast("long"))).withColumn("before", F.coalesce(F.sum("n").over(order.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)))
    h = h.withColumn("run", F.max(F.col("g") - F.col("before")).over(order))
    t = h.groupBy("range").agg(F.sum("n").alias("total"), F.max("run").alias("top"))
    prior = Window.orderBy("range").rowsBetween(Window.unboundedPreceding, -1)
    t = t.withColumn("base", F.coalesce(F.sum("total").over(prior), F.lit(0))).withColumn("high", F.max(F.col("top") - F.col("base")).over(prior))
    every = Window.partitionBy()
    t = t.withColumn("wrapped", F.greatest(F.lit(0).cast("long"), F.sum("total").over(every) + F.max(F.col("top") - F.col("base")).over(every) - m))
    j = h.join(F.broadcast(t.select("range", "base", "high", "wrapped")), "range")
    end = F.col("base") + F.col("before") + F.col("n") + F.greatest(F.col("wrapped"), F.col("run") - F.col("base"), F.coalesce("high", "wrapped"))
    return j.select("g", end.alias("e")), t.agg(F.coalesce(F.max("wrapped"), F.lit(0))).first()[0]


def offsets(fps: DataFrame, spec: FilterSpec, spacing: int) -> DataFrame:
    """(sync_idx, o): how far the first free slot for bucket sync_idx * spacing lies beyond it."""
    ends, wrapped = _ends(fps, spec)
    entries = max(1, spec.slots // spacing)
    per = ends.select(F.call_function("div", F.col("g"), F.lit(spacing).cast("long")).alias("idx"), "e").groupBy("idx").agg(F.max("e").alias("e"))
    grid = fps.sparkSession.range(spec.slots // spacing).select(F.col("id").alias("idx"))
    d = grid.join(per, "idx", "left").withColumn("range", F.call_function("div", F.col("idx") * RANGES, F.lit(entries).cast("long")))
    before = Window.partitionBy("range").orderBy("idx").rowsBetween(Window.unboundedPreceding, -1)
    tops = d.groupBy("range").agg(F.max("e").alias("top"))
    tops = tops.select("range", F.max("top").over(Window.orderBy("range").rowsBetween(Window.unboundedPreceding, -1)).alias("prior"))  # RANGES rows
    d = d.withColumn("mine", F.max("e").over(before)).join(F.broadcast(tops), "range")
    first = F.greatest(F.coalesce(F.greatest("mine", "prior"), F.lit(wrapped)), F.lit(0)).cast("long")
    return d.select(F.col("idx").alias("sync_idx"), F.greatest(F.lit(0).cast("long"), first - F.col("idx") * spacing).alias("o"))


def synchronizers(fps: DataFrame, spec: FilterSpec, spacing: int, bits: int) -> DataFrame:
    """(sync_idx, offset_): saturated at 2^bits - 1, where a reader steps back to the entry before."""
    return offsets(fps, spec, spacing).select("sync_idx", F.least("o", F.lit((1 << bits) - 1).cast("long")).alias("offset_"))


def sync_sweep(fps: DataFrame, spec: FilterSpec, spacings: tuple[int, ...], bits: tuple[int, ...]) -> DataFrame:
    """spacing, bits, saturated, entries, bits_a_slot (two flags and the entries' share): one row a pair."""
    out = None
    for spacing in spacings:
        o = offsets(fps, spec, spacing)
        grid = o.select("o", F.explode(F.array(*[F.lit(b) for b in bits])).alias("bits"))
        rows = grid.groupBy("bits").agg(F.count(F.when(F.col("o") >= F.pow(F.lit(2.0), "bits") - 1, 1)).alias("saturated"), F.count("*").alias("entries"))
        rows = rows.select(F.lit(spacing).alias("spacing"), "bits", "saturated", "entries", F.round(2 + F.col("bits") / spacing, 6).alias("bits_a_slot"))
        out = rows if out is None else out.unionByName(rows)
    return out


def line(g: np.ndarray) -> np.ndarray:
    """Slots of sorted quotients in a line."""
    i = np.arange(len(g))
    return i + np.maximum.accumulate(g - i) if len(g) else i


def _flags(g: np.ndarray, per: int) -> tuple[np.ndarray, int, np.ndarray, np.ndarray, np.ndarray]:
    """Slots of the items, number of slots, and per slot: continuation, occupied, used."""
    s = line(g)
    m = max(per, int(s[-1]) + 1 if len(s) else 0) + 1
    cont, occ, used = np.zeros(m, bool), np.zeros(m, bool), np.zeros(m, bool)
    if len(g):
        cont[s] = np.append(False, g[1:] == g[:-1])
        occ[g] = used[s] = True
    return s, m, cont, occ, used


def _join(stored: np.ndarray, cont: np.ndarray, occ: np.ndarray, r: int) -> bytes:
    return bits_of(stored.astype(np.uint64) | cont.astype(np.uint64) << np.uint64(r) | occ.astype(np.uint64) << np.uint64(r + 1), r + 2)


def _split(payload: bytes, m: int, r: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    words = words_of(payload, m, r + 2)
    return (words & np.uint64((1 << r) - 1)).astype(np.int64), (words >> np.uint64(r) & np.uint64(1)).astype(bool), (words >> np.uint64(r + 1) & np.uint64(1)).astype(bool)


def _owned(stored: np.ndarray, cont: np.ndarray, occ: np.ndarray, used: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(quotients, stored values): the j-th run in the line belongs to the j-th occupied bucket."""
    at = np.flatnonzero(used)
    return (np.flatnonzero(occ)[np.cumsum(~cont[at]) - 1], stored[at]) if len(at) else (at, at)


class Sync:
    """An entry of `bits` bits every `spacing` buckets says where the bucket's first item would lie, as an offset from the bucket;
    it replaces the shifted flag. A saturated entry says nothing: a reader steps back to the one before, at worst to
    bucket 0. Empty slots need no mark: a run starts at the later of its bucket and the end of the run before."""

    def __init__(self, spacing: int = 64, bits: int = 5):
        self.spacing, self.bits = spacing, bits

    def encode(self, g, rem, per: int, r: int) -> tuple[int, bytes, bytes]:
        s, m, cont, occ, _ = _flags(g, per)
        stored = np.zeros(m, np.int64)
        stored[s] = rem
        at = np.arange(0, per, self.spacing)
        first = np.searchsorted(g, at)
        free = np.where(first > 0, s[np.maximum(first - 1, 0)] + 1, 0) if len(g) else np.zeros(len(at), np.int64)
        entries = np.minimum(np.maximum(free - at, 0), (1 << self.bits) - 1)
        return m, _join(stored, cont, occ, r), bits_of(entries.astype(np.uint64), self.bits)

    def _start(self, entries: bytes, per: int, bucket: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """For each bucket the synchronized bucket to start from, and where its items begin."""
        e = words_of(entries, -(-per // self.spacing), self.bits).astype(np.int64)
        i = np.arange(len(e))
        usable = np.maximum.accumulate(np.where((e < (1 << self.bits) - 1) | (i == 0), i, 0))[bucket // self.spacing]
        return usable * self.spacing, usable * self.spacing + np.where(usable > 0, e[usable], 0)

    def probe(self, m: int, payload: bytes, entries: bytes, per: int, r: int, g: np.ndarray, rem: np.ndarray) -> np.ndarray:
        """Lookups in step with each other: skip the runs between the entry and the bucket, then look through its run."""
        stored, cont, occ = _split(payload, m, r)
        out = np.zeros(len(g), bool)
        stops = np.where(np.append(cont[1:], False), m, np.arange(1, m + 1))
        after = np.minimum.accumulate(stops[::-1])[::-1]  # the first slot from i + 1 on that doesn't continue
        following = np.minimum.accumulate(np.append(np.where(occ, np.arange(m), m), m)[::-1])[::-1]  # the first occupied bucket from i on
        live = np.flatnonzero(occ[g])
        bucket, at = self._start(entries, per, g[live])
        bucket = following[bucket]
        while len(todo := np.flatnonzero(bucket < g[live])):
            at[todo] = after[np.maximum(at[todo], bucket[todo])]
            bucket[todo] = following[bucket[todo] + 1]
        at = np.maximum(at, g[live])
        stop = after[at]
        while len(live):
            hit = stored[at] == rem[live]
            out[live[hit]] = True
            more = ~hit & (at + 1 < stop) & (stored[at] <= rem[live])
            live, at, stop = live[more], at[more] + 1, stop[more]
        return out

    def decode(self, m: int, payload: bytes, entries: bytes, per: int, r: int):
        """Runs in line: each starts at the later of its bucket and the end of the run before."""
        stored, cont, occ = _split(payload, m, r)
        buckets = np.flatnonzero(occ)
        after = np.minimum.accumulate(np.where(np.append(cont[1:], False), m, np.arange(1, m + 1))[::-1])[::-1]
        g, at, end = [], [], 0
        for b in buckets.tolist():
            start = max(b, end)
            end = int(after[start])
            g.append(np.full(end - start, b))
            at.append(np.arange(start, end))
        return (np.concatenate(g), stored[np.concatenate(at)]) if g else (buckets, buckets)


class Reserved:
    """A stored zero means empty and remainders are stored plus one; so the fingerprints' space has one value a slot less."""

    def encode(self, g, rem, per: int, r: int) -> tuple[int, bytes, bytes]:
        s, m, cont, occ, _ = _flags(g, per)
        stored = np.zeros(m, np.int64)
        stored[s] = rem + 1
        return m, _join(stored, cont, occ, r), b""

    def decode(self, m: int, payload: bytes, entries: bytes, per: int, r: int):
        stored, cont, occ = _split(payload, m, r)
        g, x = _owned(stored, cont, occ, stored > 0)
        return g, x - 1


class Ordered:
    """Runs ascend, so a continuation that descends can't be one: it marks an empty slot, and so does a continuation behind an
    empty slot. An empty slot stores 0 there. Only a run of zeros has no room below it: its last remainder is
    stored as the largest value, and the empty slot behind it as 1, which still descends and says so."""

    def encode(self, g, rem, per: int, r: int) -> tuple[int, bytes, bytes]:
        if r < 2:
            raise ValueError("needs remainders of two bits")
        s, m, cont, occ, used = _flags(g, per)
        stored = np.zeros(m, np.int64)
        stored[s] = rem
        cont = cont | ~used
        behind = np.flatnonzero(used[:-1] & ~used[1:])  # last slots before empty ones
        zero = behind[stored[behind] == 0]
        stored[zero], stored[zero + 1] = (1 << r) - 1, 1
        return m, _join(stored, cont, occ, r), b""

    def decode(self, m: int, payload: bytes, entries: bytes, per: int, r: int):
        stored, cont, occ = _split(payload, m, r)
        down = cont & np.append(True, stored[1:] < stored[:-1])  # a continuation in the first slot follows nothing
        since = np.cumsum(down)
        head = np.maximum.accumulate(np.where(~cont, np.arange(m), -1))
        empty = cont & (since > np.where(head >= 0, since[head], 0))
        first = np.flatnonzero(empty & np.append(False, ~empty[:-1]) & (stored == 1))
        stored[first - 1] = 0
        return _owned(stored, cont, occ, ~empty)


def pack_variant(fps: DataFrame, spec: FilterSpec, coder, shards: int | None = None) -> DataFrame:
    """(shard, n, slots, payload, entries): r + 2 bits a slot and, with synchronizers, their entries."""
    ship(fps.sparkSession)
    shards = shards or shards_of(spec, spec.slots)
    per, width, r = -(-spec.slots // shards), spec.width, spec.r

    def run(key, table):
        fp = np.sort(np.repeat(table["fp"].to_numpy(), table["cnt"].to_numpy()))
        shard = key[0].as_py()
        m, payload, entries = coder.encode(fp // width - shard * per, fp % width, per, r)
        return pa.table({"shard": pa.array([shard], pa.int64()), "n": pa.array([len(fp)], pa.int64()), "slots": pa.array([m], pa.int64()), "payload": [payload], "entries": [entries]})

    return fps.withColumn("shard", F.call_function("div", quotient_of(F.col("fp"), spec), F.lit(per).cast("long"))).groupBy("shard").applyInArrow(run, NAMES)


def unpack_variant(packed: DataFrame, spec: FilterSpec, coder, shards: int | None = None) -> DataFrame:
    """(fp, cnt) back from the payloads."""
    ship(packed.sparkSession)
    shards = shards or shards_of(spec, spec.slots)
    per, width, r = -(-spec.slots // shards), spec.width, spec.r

    def run(batches):
        for b in batches:
            for x in b.to_pylist():
                g, rem = coder.decode(x["slots"], x["payload"], x["entries"], per, r)
                out, cnt = np.unique((g + x["shard"] * per) * width + rem, return_counts=True)
                yield pa.RecordBatch.from_arrays([pa.array(out, pa.int64()), pa.array(cnt, pa.int64())], names=["fp", "cnt"])

    return packed.select("shard", "slots", "payload", "entries").mapInArrow(run, "fp long, cnt long")


def probe_variant(df: DataFrame, packed: DataFrame, spec: FilterSpec, coder: Sync, shards: int | None = None) -> DataFrame:
    """df with `maybe`: keys move to their shard and are looked up in its payload, through the entries."""
    ship(df.sparkSession)
    shards = shards or shards_of(spec, spec.slots)
    per, width, r = -(-spec.slots // shards), spec.width, spec.r
    names = df.columns
    d = df.withColumn("__fp", fingerprint(F.col("k"), spec)).withColumn("__shard", F.coalesce(F.call_function("div", quotient_of(F.col("__fp"), spec), F.lit(per).cast("long")), F.lit(-1).cast("long")))
    schema = df.withColumn("maybe", F.lit(True)).schema

    def run(left, right):
        left = left.select([*names, "__fp"]).combine_chunks()
        hit = np.zeros(len(left), bool)
        for x in right.select(["shard", "slots", "payload", "entries"]).to_pylist():
            fp = left["__fp"].to_numpy()
            hit = coder.probe(x["slots"], x["payload"], x["entries"], per, r, fp // width - x["shard"] * per, fp % width)
        return left.drop_columns(["__fp"]).append_column("maybe", pa.array(hit))

    return d.groupBy("__shard").cogroup(packed.groupBy("shard")).applyInArrow(run, schema)


def merge_reserved(a: DataFrame, b: DataFrame, left: FilterSpec, right: FilterSpec) -> DataFrame:
    """Filters with a reserved remainder merge only if their slots take the same values."""
    if (left.width, left.slots) != (right.width, right.slots):
        raise FilterSpecMismatch(f"widths {left.width} and {right.width}")
    return merge(a, b)
