"""The quotient filter in its three equal faces: fingerprint relation, slot relation, packed shards.

Fingerprint face: (fp, cnt). Slot face: (slot, remainder, occupied, shifted, continuation), one ring. Packed face:
(shard, n, payload), r + 3 bits a slot, each shard a ring of its own over a contiguous range of quotients."""

from __future__ import annotations

import dataclasses
import json
import uuid

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..cluster import ship
from ..functions.fingerprint import fingerprint, quotient_of, remainder_of
from ..schema import FilterSpec

BROADCAST_BYTES = 64 << 20


def build_fp(keys: DataFrame, spec: FilterSpec, *by: Column) -> DataFrame:
    """(fp, cnt) of a column k, for each group of `by` apart; null keys are never inserted; set mode keeps one copy."""
    d = keys.filter("k is not null").groupBy(*by, fingerprint(F.col("k"), spec).alias("fp")).agg(F.count("*").alias("cnt"))
    return d.withColumn("cnt", F.lit(1).cast("long")) if spec.mode == "set" else d


def as_buckets(fps: DataFrame, spec: FilterSpec) -> DataFrame:
    """The open hash table: quotient, remainders (ascending, joined by commas, repeated by count), n."""
    d = fps.select(quotient_of(F.col("fp"), spec).alias("quotient"), remainder_of(F.col("fp"), spec).alias("rem"), "cnt")
    runs = d.groupBy("quotient").agg(F.sort_array(F.collect_list(F.struct("rem", "cnt"))).alias("l"), F.sum("cnt").alias("n"))
    texts = F.flatten(F.transform("l", lambda x: F.array_repeat(x["rem"].cast("string"), x["cnt"].cast("int"))))
    return runs.select("quotient", F.array_join(texts, ",").alias("remainders"), "n")


def as_slots(fps: DataFrame, spec: FilterSpec, ranges: int = 64) -> DataFrame:
    """slot, remainder, occupied, shifted, continuation of all used slots and of all empty ones whose bucket is occupied.

    A sort and a running maximum instead of sequential inserts: item i of the sorted fingerprints with quotient g_i lies at
    i + max over j <= i of (g_j - j), corrected once for what wraps round the ring. Both prefixes are taken inside
    quotient ranges and joined with the ranges' summaries (at most `ranges` rows)."""
    m = spec.slots
    items = fps.select("fp", F.explode(F.sequence(F.lit(1).cast("long"), F.col("cnt"))).alias("copy")).select(quotient_of(F.col("fp"), spec).alias("g"), remainder_of(F.col("fp"), spec).alias("remainder"), "copy")
    items = items.withColumn("range", F.call_function("div", F.col("g") * ranges, F.lit(m).cast("long")))
    order = Window.partitionBy("range").orderBy("g", "remainder", "copy")
    local = items.withColumn("i", (F.row_number().over(order) - 1).cast("long"))
    local = local.withColumn("run", F.max(F.col("g") - F.col("i")).over(order.rowsBetween(Window.unboundedPreceding, 0)))
    local = local.withColumn("continuation", F.coalesce(F.lag("g").over(order) == F.col("g"), F.lit(False)))
    tops = local.groupBy("range").agg(F.count("*").alias("n"), F.max("run").alias("top"))
    before = Window.orderBy("range").rowsBetween(Window.unboundedPreceding, -1)
    tops = tops.withColumn("base", F.coalesce(F.sum("n").over(before), F.lit(0))).withColumn("high", F.max(F.col("top") - F.col("base")).over(before))
    every = Window.partitionBy()
    tops = tops.withColumn("wrapped", F.greatest(F.lit(0).cast("long"), F.sum("n").over(every) - 1 + F.max(F.col("top") - F.col("base")).over(every) - m + 1))
    placed = local.join(F.broadcast(tops.select("range", "base", "high", "wrapped")), "range")
    at = F.col("base") + F.col("i") + F.greatest(F.col("wrapped"), F.col("run") - F.col("base"), F.coalesce("high", "wrapped"))
    used = placed.select(F.pmod(at, F.lit(m)).alias("slot"), "remainder", "g", (at != F.col("g")).alias("shifted"), "continuation")
    buckets = items.select(F.col("g").alias("slot")).distinct().withColumn("occ", F.lit(True))
    both = used.join(buckets, "slot", "full")
    return both.select("slot", "remainder", F.coalesce("occ", F.lit(False)).alias("occupied"), F.coalesce("shifted", F.lit(False)).alias("shifted"), F.coalesce("continuation", F.lit(False)).alias("continuation"), F.col("g").isNotNull().alias("used"))


def decode(slots: DataFrame, spec: FilterSpec, ranges: int = 64) -> DataFrame:
    """(fp, cnt) back from the slot face: after an empty slot, the j-th run belongs to the j-th occupied bucket in ring order.

    Both orders are counted inside ranges of the ring and shifted by the counts of the ranges before (`ranges` rows)."""
    m = spec.slots
    used = slots.filter("used").select("slot").withColumn("next", F.pmod(F.col("slot") + 1, F.lit(m)))
    cut = used.join(used.select(F.col("slot").alias("s2")), used["next"] == F.col("s2"), "left_anti").agg(F.min("next").alias("cut"))  # an empty slot
    ring = slots.crossJoin(F.broadcast(cut)).withColumn("pos", F.pmod(F.col("slot") - F.col("cut"), F.lit(m)))  # one row
    ring = ring.withColumn("range", F.call_function("div", F.col("pos") * ranges, F.lit(m).cast("long"))).withColumn("head", (F.col("used") & ~F.col("continuation")).cast("long"))
    before = Window.orderBy("range").rowsBetween(Window.unboundedPreceding, -1)
    tops = ring.groupBy("range").agg(F.sum("head").alias("heads"), F.sum(F.col("occupied").cast("long")).alias("owners"))
    z = lambda c: F.coalesce(F.sum(c).over(before), F.lit(0))
    placed = ring.join(F.broadcast(tops.select("range", z("heads").alias("heads"), z("owners").alias("owners"))), "range")
    w = Window.partitionBy("range").orderBy("pos")
    placed = placed.withColumn("run", F.col("heads") + F.sum("head").over(w)).withColumn("owner", F.col("owners") + F.sum(F.col("occupied").cast("long")).over(w))
    owners = placed.filter("occupied").select(F.col("slot").alias("quotient"), F.col("owner").alias("run"))
    return placed.filter("used").join(owners, "run").select((F.col("quotient") * spec.width + F.col("remainder")).alias("fp")).groupBy("fp").agg(F.count("*").alias("cnt"))


def layout(g: np.ndarray, m: int) -> np.ndarray:
    """Slots of sorted quotients on a ring of m slots."""
    i = np.arange(len(g))
    s = i + np.maximum.accumulate(g - i) if len(g) else i
    over = int((s >= m).sum())
    return (i + np.maximum(over, np.maximum.accumulate(g - i))) % m if len(g) else s


def bits_of(words: np.ndarray, width: int) -> bytes:
    """The low `width` bits of each word, one after the other; a byte a bit at most in between."""
    bits = np.empty((len(words), width), np.uint8)
    for j in range(width):
        bits[:, j] = (words >> np.uint64(j)) & np.uint64(1)
    return np.packbits(bits.ravel(), bitorder="little").tobytes()


def words_of(payload: bytes, m: int, width: int) -> np.ndarray:
    bits = np.unpackbits(np.frombuffer(payload, np.uint8), count=m * width, bitorder="little").reshape(m, width)
    words = np.zeros(m, np.uint64)
    for j in range(width):
        words |= bits[:, j].astype(np.uint64) << np.uint64(j)
    return words


def pack_ring(g: np.ndarray, rem: np.ndarray, m: int, r: int) -> bytes:
    """r + 3 bits a slot: occupied, shifted, continuation, remainder."""
    if len(g) >= m:
        from ..schema import FilterFull

        raise FilterFull(f"{len(g)} items in a ring of {m}")
    raw = layout(g, m)
    words = np.zeros(m, np.uint64)
    if len(g):
        cont = np.append(False, g[1:] == g[:-1])
        words[raw] = rem.astype(np.uint64) | (cont.astype(np.uint64) << np.uint64(r)) | ((raw != g).astype(np.uint64) << np.uint64(r + 1))
        words[np.unique(g)] |= np.uint64(1) << np.uint64(r + 2)
    return bits_of(words, r + 3)


def unpack_ring(payload: bytes, m: int, r: int) -> tuple[np.ndarray, np.ndarray]:
    """(quotients, remainders), sorted."""
    words = words_of(payload, m, r + 3)
    rem = words & np.uint64((1 << r) - 1)
    cont, shifted, occ = ((words >> np.uint64(r + i)) & np.uint64(1) for i in range(3))
    # an item is there where the slot is shifted or continues, or is occupied and holds its own run's head
    used = (shifted | cont | occ).astype(bool)
    if not used.any():
        return np.zeros(0, np.int64), np.zeros(0, np.int64)
    start = (int(np.flatnonzero(~used)[0]) + 1) % m
    order = (np.arange(m) + start) % m
    o = order[used[order]]
    run = np.cumsum(cont[o] == 0) - 1
    owners = order[occ[order].astype(bool)]
    g, x = owners[run].astype(np.int64), rem[o].astype(np.int64)
    back = np.lexsort((x, g))
    return g[back], x[back]


def shards_of(spec: FilterSpec, items: int, per_shard: int = 1 << 15) -> int:
    return max(1, min(spec.slots, -(-items // per_shard)))


def pack(fps: DataFrame, spec: FilterSpec, shards: int) -> DataFrame:
    """(shard, n, payload). A shard is a contiguous range of quotients on a ring with an eighth of spare slots."""
    ship(fps.sparkSession)
    per = -(-spec.slots // shards)
    kind, width = spec.r, spec.width

    def run(key, table):
        fp, cnt = table["fp"].to_numpy(), table["cnt"].to_numpy()
        fp = np.sort(np.repeat(fp, cnt))
        shard = key[0].as_py()
        g = fp // width - shard * per
        ring = ring_size(per, len(fp))
        return pa.table({"shard": pa.array([shard], pa.int64()), "n": pa.array([len(fp)], pa.int64()), "ring": pa.array([ring], pa.int64()), "payload": [pack_ring(g, fp % width, ring, kind)]})

    return fps.withColumn("shard", F.call_function("div", quotient_of(F.col("fp"), spec), F.lit(per).cast("long"))).groupBy("shard").applyInArrow(run, "shard long, n long, ring long, payload binary")


def ring_size(per: int, items: int) -> int:
    return max(per + per // 8 + 8, items + items // 8 + 8)


def _fps_of(shard: int, ring: int, payload: bytes, per: int, spec: FilterSpec) -> np.ndarray:
    g, rem = unpack_ring(payload, ring, spec.r)
    return (g + shard * per) * spec.width + rem


def unpack(packed: DataFrame, spec: FilterSpec, shards: int) -> DataFrame:
    ship(packed.sparkSession)
    per = -(-spec.slots // shards)

    def run(batches):
        for b in batches:
            for r in b.to_pylist():
                fp, cnt = np.unique(_fps_of(r["shard"], r["ring"], r["payload"], per, spec), return_counts=True)
                yield pa.RecordBatch.from_arrays([pa.array(fp, pa.int64()), pa.array(cnt, pa.int64())], names=["fp", "cnt"])

    return packed.select("shard", "ring", "payload").mapInArrow(run, "fp long, cnt long")


def probe_join(df: DataFrame, fps: DataFrame, spec: FilterSpec) -> DataFrame:
    """df with `maybe`: a semi join with a flag, left to Catalyst; a null key is absent."""
    hit = fps.select(F.col("fp").alias("__fp"), F.lit(True).alias("__hit"))
    return df.withColumn("__fp", fingerprint(F.col("k"), spec)).join(hit, "__fp", "left").select(*df.columns, F.coalesce("__hit", F.lit(False)).alias("maybe"))


def might_contain(packed: DataFrame, key: str, spec: FilterSpec, shards: int) -> bool:
    """One key: its shard alone is read, and in it the one cluster that its bucket's run can lie in."""
    fp = packed.sparkSession.range(1).select(fingerprint(F.lit(key), spec)).first()[0]
    per = -(-spec.slots // shards)
    g, rem = divmod(fp, spec.width)
    row = packed.filter(F.col("shard") == g // per).select("ring", "payload").first()  # one shard
    return row is not None and scan_cluster(bytes(row["payload"]), row["ring"], spec.r, g - g // per * per, rem)


def scan_cluster(payload: bytes, m: int, r: int, bucket: int, remainder: int) -> bool:
    """Whether the bucket's run holds the remainder, from the flags of its cluster.

    Going left over shifted slots counts the runs that begin before the bucket's own; going right skips as many."""
    width = r + 3

    def slot(i: int) -> int:
        lo = i % m * width
        return int.from_bytes(payload[lo >> 3 : (lo + width + 7) >> 3], "little") >> (lo & 7) & ((1 << width) - 1)

    continues, shifted, occupied = (1 << (r + i) for i in range(3))
    if not slot(bucket) & occupied:
        return False
    at, runs = bucket, 0
    while slot(at) & shifted:
        at -= 1
        runs += bool(slot(at) & occupied)
    while runs:
        at += 1
        runs -= not slot(at) & continues
    while True:
        stored = slot(at) & ((1 << r) - 1)
        if stored == remainder:
            return True
        at += 1
        if stored > remainder or not slot(at) & continues:  # runs ascend
            return False


def probe_broadcast(df: DataFrame, packed: DataFrame, spec: FilterSpec, shards: int) -> DataFrame:
    """df with `maybe`: packed shards go to all tasks if what they decode to (8 bytes an item, once a Python worker) is small
    enough, and df doesn't move; beyond the size, by shard."""
    ship(df.sparkSession)
    size = packed.agg(F.coalesce(F.sum(F.col("n") * 8), F.lit(0))).first()[0]
    if size > BROADCAST_BYTES:
        return probe_shard(df, packed, spec, shards)
    per = -(-spec.slots // shards)
    sent = df.sparkSession.sparkContext.broadcast([(r["shard"], r["ring"], bytes(r["payload"])) for r in packed.collect()])
    name = uuid.uuid4().hex
    d = df.withColumn("__fp", fingerprint(F.col("k"), spec))
    schema = df.withColumn("maybe", F.lit(True)).schema

    def run(batches):
        from approxset.operators import quotient

        known = quotient.decoded_once(name, lambda: [_fps_of(s, ring, payload, per, spec) for s, ring, payload in sent.value])
        for b in batches:
            yield _flagged(b, known)

    return d.mapInArrow(run, schema)


_decoded: dict[str, np.ndarray] = {}


def decoded_once(name: str, parts) -> np.ndarray:
    """The sorted fingerprints of a broadcast filter; a Python worker keeps those of the last one."""
    if name not in _decoded:
        _decoded.clear()
        p = parts()
        _decoded[name] = np.sort(np.concatenate(p)) if p else np.zeros(0, np.int64)
    return _decoded[name]


def _flagged(b, known: np.ndarray):
    col = b.column(b.num_columns - 1)
    fp = col.fill_null(-1).to_numpy(zero_copy_only=False)
    at = np.searchsorted(known, fp)
    hit = (at < len(known)) & (known[np.minimum(at, max(len(known) - 1, 0))] == fp) if len(known) else np.zeros(len(fp), bool)
    return pa.RecordBatch.from_arrays([*b.columns[:-1], pa.array(hit)], names=[*b.schema.names[:-1], "maybe"])


def probe_shard(df: DataFrame, packed: DataFrame, spec: FilterSpec, shards: int) -> DataFrame:
    """df with `maybe`: keys move once to their shard; fingerprints are hashes, so shards are even whatever the keys."""
    per = -(-spec.slots // shards)
    names = df.columns
    d = df.withColumn("__fp", fingerprint(F.col("k"), spec)).withColumn("__shard", F.coalesce(F.call_function("div", quotient_of(F.col("__fp"), spec), F.lit(per).cast("long")), F.lit(-1).cast("long")))
    schema = df.withColumn("maybe", F.lit(True)).schema

    def run(left, right):
        known = np.zeros(0, np.int64)
        for r in right.select(["shard", "ring", "payload"]).to_pylist():
            known = _fps_of(r["shard"], r["ring"], r["payload"], per, spec)
        left = left.select([*names, "__fp"]).combine_chunks()
        out = [_flagged(b, np.sort(known)) for b in left.to_batches()]
        return pa.Table.from_batches(out) if out else left.drop_columns(["__fp"]).append_column("maybe", pa.array([], pa.bool_()))

    return d.groupBy("__shard").cogroup(packed.groupBy("shard")).applyInArrow(run, schema)


def insert(fps: DataFrame, more: DataFrame) -> DataFrame:
    return merge(fps, more)


def insert_packed(packed: DataFrame, more: DataFrame, spec: FilterSpec, shards: int) -> DataFrame:
    """Packed shards with the fingerprints `more` (fp, cnt) put in: only shards that get some are unpacked and packed again."""
    per = -(-spec.slots // shards)
    delta = more.withColumn("shard", F.call_function("div", quotient_of(F.col("fp"), spec), F.lit(per).cast("long")))
    names = delta.select("shard").distinct()
    touched = packed.join(names, "shard", "left_semi")
    rebuilt = pack(merge(unpack(touched, spec, shards), more), spec, shards)
    return packed.join(names, "shard", "left_anti").select(*rebuilt.columns).unionByName(rebuilt)


def merge(*filters: DataFrame) -> DataFrame:
    """Counts add up; filters of any slot number with the same p merge without rehashing."""
    d = filters[0].select("fp", "cnt")
    for f in filters[1:]:
        d = d.unionByName(f.select("fp", "cnt"))
    return d.groupBy("fp").agg(F.sum("cnt").alias("cnt"))


def delete(fps: DataFrame, gone: DataFrame, strict: bool = False) -> DataFrame:
    """Each copy in `gone` takes one copy; what isn't there is left alone. With `strict`, any of it is an error instead."""
    if strict and (missing := underflow(fps, gone).agg(F.coalesce(F.sum("missing"), F.lit(0))).first()[0]):
        raise ValueError(f"{missing} copies to delete aren't there; `underflow` lists them")
    g = gone.select("fp", F.col("cnt").alias("d"))
    return fps.join(g, "fp", "left").select("fp", (F.col("cnt") - F.coalesce("d", F.lit(0))).alias("cnt")).filter("cnt > 0")


def underflow(fps: DataFrame, gone: DataFrame) -> DataFrame:
    """(fp, missing): copies in `gone` beyond those that are there."""
    return gone.join(fps.select("fp", F.col("cnt").alias("c")), "fp", "left").select("fp", (F.col("cnt") - F.coalesce("c", F.lit(0))).alias("missing")).filter("missing > 0")


def save(packed: DataFrame, spec: FilterSpec, shards: int, path: str) -> None:
    """Shards under `path`, with a descriptor of one row beside them."""
    spark = packed.sparkSession
    packed.repartition(F.col("shard")).sortWithinPartitions("shard").write.mode("overwrite").parquet(f"{path}/shards")
    spark.createDataFrame([(json.dumps(dataclasses.asdict(spec)), shards)], "spec string, shards int").coalesce(1).write.mode("overwrite").parquet(f"{path}/descriptor")


def load(spark, path: str, spec: FilterSpec | None = None) -> tuple[DataFrame, FilterSpec, int]:
    """The packed shards, their spec and number. With `spec`, a filter of another kind is an error."""
    row = spark.read.schema("spec string, shards int").parquet(f"{path}/descriptor").first()
    found = FilterSpec(**json.loads(row["spec"]))
    if spec is not None:
        found.same_space(spec)
    return spark.read.schema("shard long, n long, ring long, payload binary").parquet(f"{path}/shards"), found, row["shards"]


def guarded(keys: DataFrame, spec: FilterSpec) -> DataFrame:
    """`build_fp` behind the load limit: FilterFull where the keys pass `spec.max_load` of the slots."""
    f = build_fp(keys, spec)
    spec.check(f.agg(F.coalesce(F.sum("cnt"), F.lit(0))).first()[0], spec.max_load)
    return f


def intersect_filters(a: DataFrame, b: DataFrame) -> DataFrame:
    return a.join(b.select("fp", F.col("cnt").alias("c2")), "fp").select("fp", F.least("cnt", "c2").alias("cnt"))


def subtract_filters(a: DataFrame, b: DataFrame) -> DataFrame:
    return delete(a, b)
