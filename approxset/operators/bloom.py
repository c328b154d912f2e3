"""Bloom-family baselines as relations: classic, counting, write-buffered, page-local, layered.

All keep their bits as (word_idx, word) and answer by the key itself: a key's positions are one array, computed once from one
digest. Words of a checked size go to all tasks, and keys don't move; beyond it, the bits of the distinct keys meet the words
by a shuffle. A page-local filter needs neither: a key has one block, so keys and blocks meet in one equi-join."""

from __future__ import annotations

import hashlib
import math
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..cluster import ship
from ..functions.fingerprint import digest_lanes, once

WORD = 32
#: Words that a task fills and that are broadcast at most (192 MB), and bits of a page of them.
BROADCAST_WORDS, PAGE_BITS = 48 << 20, 1 << 18
#: Layers of a layered filter lie 2^40 bits apart.
APART = 40


def _div(a: Column, b: int) -> Column:
    return F.call_function("div", a, F.lit(b).cast("long"))


def _words_of(bits: DataFrame) -> DataFrame:
    at = F.pmod("bit", F.lit(WORD)).cast("int")
    return bits.groupBy(_div(F.col("bit"), WORD).alias("word_idx")).agg(F.bit_or(F.call_function("shiftleft", F.lit(1).cast("long"), at)).alias("word"))


def lanes_of(keys: pa.Array, lanes: int, width: int) -> np.ndarray:
    """`digest_lanes` of non-null keys, one row each: a lane lies within eight bytes of the 64 of the digests."""
    n, sha = len(keys), hashlib.sha256
    out = np.empty((n, lanes), np.int64, order="F")
    if not n:
        return out
    raw = np.frombuffer(b"".join([sha(x + k).digest() for k in keys.cast(pa.binary()).to_pylist() for x in (b"0:", b"1:")]) + bytes(8), np.uint8)
    for i in range(lanes):
        byte, odd = divmod(i * width, 2)
        word = np.ndarray((n,), ">u8", raw, byte, (64,)).astype(np.uint64)
        out[:, i] = (word >> np.uint64(64 - 4 * (odd + width))) & np.uint64((1 << 4 * width) - 1)
    return out


def put_bits(dense: np.ndarray, bits: np.ndarray) -> None:
    for j in range(8):  # one value a pass, so that repeated bytes are no matter
        dense[bits[bits & 7 == j] >> 3] |= np.uint8(1 << j)


def _room(bits: int) -> np.ndarray:
    return np.zeros(-(-bits // PAGE_BITS) * PAGE_BITS // 8, np.uint8)


def _pages(filled: dict[int, np.ndarray]):
    """(page, bits) of the pages of dense groups that hold any bit."""
    for g, dense in filled.items():
        dense = dense.reshape(-1, PAGE_BITS // 8)
        for at in np.array_split(some := np.flatnonzero(dense.any(axis=1)), -(-len(some) // 64) or 1):
            yield pa.RecordBatch.from_arrays([pa.array((g << APART) // PAGE_BITS + at, pa.int64()), pa.array([dense[i].tobytes() for i in at], pa.binary())], names=["page", "bits"])


def _merged(pages: DataFrame) -> DataFrame:
    def run(key, table):
        bits = np.frombuffer(table["bits"][0].as_py(), np.uint8).copy()
        for x in table["bits"][1:]:
            bits |= np.frombuffer(x.as_py(), np.uint8)
        return pa.table({"page": pa.array([key[0].as_py()], pa.int64()), "bits": pa.array([bits.tobytes()], pa.binary())})

    return pages.groupBy("page").applyInArrow(run, "page long, bits binary")


def _of_pages(pages: DataFrame) -> DataFrame:
    """(word_idx, word) of merged pages, which the frame carries as `pages`."""

    def run(batches):
        for b in batches:
            for page, bits in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), strict=True):
                word = np.frombuffer(bits, "<u4")
                at = np.flatnonzero(word)
                yield pa.RecordBatch.from_arrays([pa.array(page * (PAGE_BITS // WORD) + at, pa.int64()), pa.array(word[at].astype(np.int64))], names=["word_idx", "word"])

    out = pages.mapInArrow(run, "word_idx long, word long")
    out.pages = pages
    return out


def _pages_of_words(words: DataFrame) -> DataFrame:
    """Pages of any words relation."""
    if hasattr(words, "pages"):
        return words.pages

    def run(key, table):
        word = np.zeros(PAGE_BITS // WORD, "<u4")
        word[table["word_idx"].to_numpy() % len(word)] = table["word"].to_numpy()
        return pa.table({"page": pa.array([key[0].as_py()], pa.int64()), "bits": pa.array([word.tobytes()], pa.binary())})

    return words.select(F.col("word_idx").cast("long"), F.col("word").cast("long")).groupBy(_div(F.col("word_idx"), PAGE_BITS // WORD).alias("page")).applyInArrow(run, "page long, bits binary")


def _fewer(d: DataFrame) -> DataFrame:
    """As many partitions as cores: each task fills a whole filter."""
    return d.coalesce(max(1, d.sparkSession.sparkContext.defaultParallelism))


def filled(keys: DataFrame, form, layer: tuple[Column, list[int]] | None = None) -> DataFrame:
    """(word_idx, word) of keys (k), of which each task fills dense bits of its own. `layer`: a key's group, and all groups' bits."""
    ship(keys.sparkSession)
    sizes = layer[1] if layer else [form.size()]
    d = _fewer(keys.filter("k is not null").select(F.col("k").cast("string").alias("k"), (layer[0] if layer else F.lit(0)).cast("long").alias("g")))

    def run(batches):
        dense: dict[int, np.ndarray] = {}
        for b in batches:
            lanes, group = form.lanes_of(b.column(0)), b.column(1).to_numpy()
            for g in np.unique(group).tolist():
                if g not in dense:
                    dense[g] = _room(sizes[g])
                mine = lanes[group == g]
                first = form.first(mine, g)
                for j in range(form.k):
                    put_bits(dense[g], form.place(mine, first, j))
        yield from _pages(dense)

    return _of_pages(_merged(d.mapInArrow(run, "page long, bits binary")))


def answers(df: DataFrame, words: DataFrame, form, groups: int = 1, read_bits: int = 0, free: int = 0) -> DataFrame:
    """df with `__hits` (groups of k positions whose bits are all set; 0 for a null key) and `__reads` (pages of `read_bits` bits
    looked at: in each group those up to its first clear bit, each once; the first `free` groups lie in memory; 0 without `read_bits`).

    Dense bits of a checked size go to all tasks and keys don't move; beyond it, keys meet the words by a shuffle."""
    sizes = [form.size(g) for g in range(groups)]
    if sum(sizes) > BROADCAST_WORDS * WORD:
        return _answers_shuffled(df, words, form.all_positions(F.col("k"), groups), form.k, read_bits or WORD, free)
    spark = df.sparkSession
    ship(spark)
    known = [_room(n) for n in sizes]
    pages = _pages_of_words(words).toArrow()
    for page, bits in zip(pages["page"].to_pylist(), pages["bits"], strict=True):
        g, at = divmod(page * PAGE_BITS, 1 << APART)
        known[g][at // 8 : (at + PAGE_BITS) // 8] = np.frombuffer(bits.as_buffer(), np.uint8)
    del pages
    sent = spark.sparkContext.broadcast(known)
    schema = df.withColumn("__hits", F.lit(0)).withColumn("__reads", F.lit(0).cast("long")).schema

    def run(batches):
        dense, k = sent.value, form.k
        for b in batches:
            found = b.column(b.num_columns - 1)
            some = np.flatnonzero(found.is_valid().to_numpy(zero_copy_only=False))
            lanes = form.lanes_of(found.drop_null())
            hits, reads = np.zeros(len(found), np.int32), np.zeros(len(found), np.int64)
            for g in range(groups):
                first, left, seen = form.first(lanes, g), np.arange(len(some)), []
                for j in range(k):  # a lookup stops at its first clear bit
                    bit = form.place(lanes[left], first[left], j)
                    if read_bits and g >= free:
                        page = bit // read_bits
                        new = np.ones(len(left), bool)
                        for x in seen:
                            new &= x != page
                        reads[some[left[new]]] += 1
                        seen.append(page)
                    on = dense[g][bit >> 3] >> (bit & 7).astype(np.uint8) & 1 == 1
                    left, seen = left[on], [x[on] for x in seen]
                hits[some[left]] += 1
            yield pa.RecordBatch.from_arrays([*b.columns[:-1], pa.array(hits), pa.array(reads)], names=schema.names)

    return df.withColumn("__key", F.col("k").cast("string")).mapInArrow(run, schema)


def _answers_shuffled(df: DataFrame, words: DataFrame, positions: Column, k: int, read_bits: int, free: int) -> DataFrame:
    asked = df.filter("k is not null").select("k").distinct().select("k", F.posexplode(positions).alias("__at", "__bit"))
    asked = asked.withColumn("word_idx", _div(F.col("__bit"), WORD)).join(words.select("word_idx", F.col("word").alias("__word")), "word_idx", "left")
    mask = F.call_function("shiftleft", F.lit(1).cast("long"), F.pmod("__bit", F.lit(WORD)).cast("int"))
    bit = F.coalesce(F.col("__word"), F.lit(0)).bitwiseAND(mask) != 0
    group = asked.groupBy("k", _div(F.col("__at"), k).alias("__g")).agg(F.sort_array(F.collect_list(F.struct("__at", _div(F.col("__bit"), read_bits).alias("page"), bit.alias("set")))).alias("l"))  # k entries
    clear = F.array_position(F.transform("l", lambda x: x["set"]), F.lit(False))
    looked = F.slice(F.transform("l", lambda x: x["page"]), 1, F.when(clear == 0, k).otherwise(clear).cast("int"))
    found = group.select("k", (clear == 0).cast("int").alias("__hit"), F.when(F.col("__g") >= free, F.size(F.array_distinct(looked))).otherwise(0).alias("__read")).groupBy("k").agg(F.sum("__hit").cast("int").alias("__hits"), F.sum("__read").alias("__reads"))
    return df.join(found, "k", "left").select(*df.columns, F.coalesce("__hits", F.lit(0)).alias("__hits"), F.coalesce("__reads", F.lit(0)).cast("long").alias("__reads"))


@dataclass(frozen=True)
class BloomFilter:
    """m bits, k independent hashes, each a 36-bit lane of the 512-bit digest."""

    m: int
    k: int

    @classmethod
    def for_items(cls, n: int, eps: float, k: int | None = None) -> BloomFilter:
        """Optimal k = (m/n) ln 2 at the size that gives eps."""
        m = max(8, math.ceil(-n * math.log(eps) / math.log(2) ** 2))
        return cls(m, k or max(1, round(m / max(n, 1) * math.log(2))))

    def positions(self, key: Column) -> Column:
        return F.transform(digest_lanes(key, self.k), lambda x: F.pmod(x, F.lit(self.m)))

    def all_positions(self, key: Column, groups: int) -> Column:
        return self.positions(key)

    def size(self, group: int = 0) -> int:
        return self.m

    def lanes_of(self, keys: pa.Array) -> np.ndarray:
        return lanes_of(keys, self.k, 9)

    def first(self, lanes: np.ndarray, group: int) -> np.ndarray:
        return np.zeros(len(lanes), np.int64)

    def place(self, lanes: np.ndarray, first: np.ndarray, j: int) -> np.ndarray:
        """The j-th position of each key, within its group."""
        return lanes[:, j] % self.m

    def build(self, keys: DataFrame) -> DataFrame:
        """(word_idx, word) of 32 bits each."""
        if self.size() <= BROADCAST_WORDS * WORD:
            return filled(keys, self)
        return _words_of(keys.filter("k is not null").select(F.explode(self.positions(F.col("k"))).alias("bit")))

    def reads(self, df: DataFrame, words: DataFrame, page_bits: int) -> DataFrame:
        """df with `maybe` and `reads`: pages of `page_bits` bits that the lookup looks at."""
        out = answers(df, words, self, read_bits=page_bits)
        return out.select(*df.columns, (F.col("__hits") > 0).alias("maybe"), F.col("__reads").alias("reads"))

    def probe(self, df: DataFrame, words: DataFrame) -> DataFrame:
        """df with `maybe`: all k bits set; a null key is absent."""
        return answers(df, words, self).select(*df.columns, (F.col("__hits") > 0).alias("maybe"))

    @staticmethod
    def union(*words: DataFrame) -> DataFrame:
        if all(hasattr(w, "pages") for w in words):
            d = words[0].pages
            for w in words[1:]:
                d = d.unionByName(w.pages)
            return _of_pages(_merged(d))
        d = words[0]
        for w in words[1:]:
            d = d.unionByName(w)
        return d.groupBy("word_idx").agg(F.bit_or("word").alias("word"))


@dataclass(frozen=True)
class CountingBloom(BloomFilter):
    """4-bit saturating counters: four times a Bloom filter's space."""

    cap: int = 15

    def _cells(self, keys: DataFrame) -> DataFrame:
        """(cell, c) of the keys' distinct cells, not yet capped."""
        if self.size() > BROADCAST_WORDS * 4:  # as many bytes as the words of a broadcast
            return keys.filter("k is not null").select(F.explode(F.array_distinct(self.positions(F.col("k")))).alias("cell")).groupBy("cell").agg(F.count("*").alias("c"))
        size, room = self.size(), PAGE_BITS // 8
        ship(keys.sparkSession)

        def count(batches):
            dense, most = np.zeros(-(-size // room) * room, np.uint8), 255
            full: dict[int, int] = {}
            for b in batches:
                at = np.sort(np.stack([self.place(lanes, lanes[:, 0], j) for lanes in [self.lanes_of(b.column(0))] for j in range(self.k)], axis=1), axis=1)
                new = np.ones(at.shape, bool)
                new[:, 1:] = at[:, 1:] != at[:, :-1]  # a key counts once in a cell
                cell, n = np.unique(at[new], return_counts=True)
                n = n + dense[cell]
                for c, x in zip(cell[n > most].tolist(), n[n > most].tolist(), strict=True):  # beyond a byte
                    full[c] = full.get(c, 0) + x
                dense[cell] = np.where(n > most, 0, n)
            dense = dense.reshape(-1, room)
            for i in np.flatnonzero(dense.any(axis=1)):
                yield pa.RecordBatch.from_pydict({"page": pa.array([i], pa.int64()), "counts": pa.array([dense[i].tobytes()], pa.binary()), "cell": pa.array([None], pa.int64()), "c": pa.array([None], pa.int64())})
            if full:
                cell = np.array(list(full), np.int64)
                yield pa.RecordBatch.from_pydict({"page": pa.array(cell // room), "counts": pa.array([None] * len(cell), pa.binary()), "cell": pa.array(cell), "c": pa.array(list(full.values()), pa.int64())})

        def add(key, table):
            total = np.zeros(room, np.int64)
            for x, cell, c in zip(table["counts"], table["cell"].to_pylist(), table["c"].to_pylist(), strict=True):
                if cell is None:
                    total += np.frombuffer(x.as_buffer(), np.uint8)
                else:
                    total[cell % room] += c
            at = np.flatnonzero(total)
            return pa.table({"cell": pa.array(key[0].as_py() * room + at, pa.int64()), "c": pa.array(total[at], pa.int64())})

        d = _fewer(keys.filter("k is not null").select(F.col("k").cast("string").alias("k")))
        return d.mapInArrow(count, "page long, counts binary, cell long, c long").groupBy("page").applyInArrow(add, "cell long, c long")

    def build(self, keys: DataFrame) -> DataFrame:
        return self._cells(keys).select("cell", F.least("c", F.lit(self.cap)).cast("long").alias("c"))

    def delete(self, cells: DataFrame, keys: DataFrame) -> DataFrame:
        """Subtracts, but leaves saturated counters."""
        d = self._cells(keys).withColumnRenamed("c", "d")
        left = F.when(F.col("c") >= self.cap, F.col("c")).otherwise(F.greatest(F.col("c") - F.coalesce("d", F.lit(0)), F.lit(0)))
        return cells.join(d, "cell", "left").select("cell", left.cast("long").alias("c")).filter("c > 0")

    def probe(self, df: DataFrame, cells: DataFrame) -> DataFrame:
        bits, size = cells.filter("c > 0").select(F.col("cell").cast("long").alias("bit")), self.size()
        if size > BROADCAST_WORDS * WORD:
            return super().probe(df, _words_of(bits))

        def run(batches):
            dense = _room(size)
            for b in batches:
                put_bits(dense, b.column(0).to_numpy())
            yield from _pages({0: dense})

        ship(df.sparkSession)
        return super().probe(df, _of_pages(_merged(_fewer(bits).mapInArrow(run, "page long, bits binary"))))


@dataclass(frozen=True)
class PageLocalBloom:
    """One lane chooses a block of `block_bits`; k lanes choose bits inside it."""

    blocks: int
    block_bits: int
    k: int

    @classmethod
    def for_items(cls, n: int, eps: float, block_bits: int = 4096, k: int | None = None) -> PageLocalBloom:
        """As many blocks as hold the bits of a classic filter of n and eps."""
        b = BloomFilter.for_items(n, eps, k)
        return cls(-(-b.m // block_bits), block_bits, b.k)

    def block(self, key: Column) -> Column:
        return F.pmod(digest_lanes(key, 1)[0], F.lit(self.blocks))

    def _local(self, lanes: Column) -> Column:
        return F.transform(F.slice(lanes, 2, self.k), lambda x: F.pmod(x, F.lit(self.block_bits)))

    def positions(self, key: Column) -> Column:
        def place(lanes):
            return once(F.pmod(lanes[0], F.lit(self.blocks)) * self.block_bits, lambda base: F.transform(self._local(lanes), lambda x: base + x))

        return once(digest_lanes(key, self.k + 1), place)

    build, all_positions = BloomFilter.build, BloomFilter.all_positions

    def size(self, group: int = 0) -> int:
        return self.blocks * self.block_bits

    def lanes_of(self, keys: pa.Array) -> np.ndarray:
        return lanes_of(keys, self.k + 1, 9)

    def first(self, lanes: np.ndarray, group: int) -> np.ndarray:
        return lanes[:, 0] % self.blocks * self.block_bits

    def place(self, lanes: np.ndarray, first: np.ndarray, j: int) -> np.ndarray:
        return first + lanes[:, j + 1] % self.block_bits

    def reads(self, df: DataFrame, words: DataFrame, page_bits: int) -> DataFrame:
        """df with `maybe` and `reads`: the block's pages of `page_bits` bits up to the first clear bit."""
        return self._answered(df, words, page_bits).select(*df.columns, F.col("__maybe").alias("maybe"), F.col("__reads").alias("reads"))

    def _answered(self, df: DataFrame, words: DataFrame, page_bits: int) -> DataFrame:
        """df with `__maybe` and `__reads`. Beyond the size of a broadcast:

        Blocks are rows of one array each, and a batch of lookups meets them in one join on the block, so that each block
        is read once a batch however many lookups were delayed for it."""
        if self.size() <= BROADCAST_WORDS * WORD:
            out = answers(df, words, self, read_bits=page_bits)
            return out.select(*df.columns, (F.col("__hits") > 0).alias("__maybe"), "__reads")
        per = self.block_bits // WORD
        pages = words.groupBy(_div(F.col("word_idx"), per).alias("__block")).agg(F.map_from_entries(F.collect_list(F.struct(F.pmod("word_idx", F.lit(per)).cast("int"), "word"))).alias("m"))  # `per` entries
        pages = pages.select("__block", F.transform(F.sequence(F.lit(0), F.lit(per - 1)), lambda i: F.coalesce(F.col("m")[i], F.lit(0).cast("long"))).alias("__words"))
        asked = df.withColumn("__lanes", digest_lanes(F.col("k"), self.k + 1)).withColumn("__block", F.pmod(F.col("__lanes")[0], F.lit(self.blocks))).withColumn("__local", self._local(F.col("__lanes"))).drop("__lanes")
        met = asked.join(pages, "__block", "left")
        is_set = F.transform("__local", lambda x: F.coalesce(F.call_function("shiftright", F.get("__words", _div(x, WORD).cast("int")), F.pmod(x, F.lit(WORD)).cast("int")).bitwiseAND(F.lit(1).cast("long")), F.lit(0).cast("long")))
        met = met.withColumn("__clear", F.coalesce(F.array_position(is_set, F.lit(0).cast("long")), F.lit(1).cast("long")))
        looked = F.slice(F.transform("__local", lambda x: _div(x, page_bits)), 1, F.when(F.col("__clear") == 0, self.k).otherwise(F.col("__clear")).cast("int"))
        return met.select(*df.columns, (F.col("__clear") == 0).alias("__maybe"), F.when(F.col("k").isNull(), 0).otherwise(F.size(F.array_distinct(looked))).cast("long").alias("__reads"))

    def probe(self, df: DataFrame, words: DataFrame) -> DataFrame:
        return self._answered(df, words, self.block_bits).select(*df.columns, F.col("__maybe").alias("maybe"))

    def delayed(self, asked: DataFrame, words: DataFrame, batch: int) -> tuple[DataFrame, DataFrame]:
        """Lookups (k, seq) held back until `batch` have gathered: the answers, and (batch, lookups, block_reads): each batch
        reads each of its blocks once."""
        held = asked.select(_div(F.col("seq") - 1, batch).alias("batch"), self.block(F.col("k")).alias("block"))
        cost = held.groupBy("batch", "block").agg(F.count("*").alias("n")).groupBy("batch").agg(F.sum("n").alias("lookups"), F.count("*").alias("block_reads"))
        return self.probe(asked, words), cost

    def flushes(self, arrived: DataFrame, cap: int) -> DataFrame:
        """Of (k, seq): block, full sub-buffer flushes, items left at the end."""
        n = arrived.select(self.block(F.col("k")).alias("block")).groupBy("block").agg(F.count("*").alias("n"))
        return n.select("block", _div(F.col("n"), cap).alias("flushes"), F.pmod("n", F.lit(cap)).cast("long").alias("left"))

    def flush_times(self, arrived: DataFrame, cap: int) -> DataFrame:
        """(block, seq): the arrivals that fill a block's sub-buffer of `cap` items, each of which writes the block once."""
        from pyspark.sql import Window

        w = Window.partitionBy("block").orderBy("seq")
        d = arrived.select(self.block(F.col("k")).alias("block"), "seq").withColumn("i", F.row_number().over(w))
        return d.filter(F.col("i") % cap == 0).select("block", "seq")

    def group_flushes(self, arrived: DataFrame, buffer: int, group: int, shards: int = 1) -> DataFrame:
        """(shard, flush, first_block, items): when a buffer is full, the `group` adjacent sub-buffers that hold most go out
        (the first of equals). Flush 0 is what is still held at the end, one row a group that holds any.

        A choice depends on all before it, so a buffer is one sequence. `shards` buffers, each over a range of blocks,
        run in parallel; only (group, seq) moves, and a task keeps one count per group."""
        groups = -(-self.blocks // group)
        per = -(-groups // shards)
        d = arrived.select(_div(self.block(F.col("k")), group).alias("g"), "seq").withColumn("shard", _div(F.col("g"), per))

        def run(batches):
            held: dict[int, np.ndarray] = {}
            count: dict[int, int] = {}
            total: dict[int, int] = {}
            for b in batches:
                out = []
                for s, g in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), strict=True):
                    h = held.setdefault(s, np.zeros(per, np.int64))
                    h[g - s * per] += 1
                    total[s] = total.get(s, 0) + 1
                    if total[s] == buffer:
                        i = int(h.argmax())
                        count[s] = count.get(s, 0) + 1
                        out.append((s, count[s], (s * per + i) * group, int(h[i])))
                        total[s] -= int(h[i])
                        h[i] = 0
                yield rows(out)
            yield rows([(s, 0, (s * per + i) * group, int(n)) for s, h in held.items() for i, n in enumerate(h) if n])

        def rows(out):
            return pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in (list(zip(*out, strict=True)) or [()] * 4)], names=["shard", "flush", "first_block", "items"])

        return d.select("shard", "g", "seq").repartition(shards, "shard").sortWithinPartitions("shard", "seq").mapInArrow(run, "shard long, flush long, first_block long, items long")


def write_buffered_writes(arrived: DataFrame, bloom: BloomFilter, buffer: int, page_bits: int) -> DataFrame:
    """(epoch, page_writes): distinct blocks that the bits buffered in an epoch touch. Each task marks them in dense bits."""
    ship(arrived.sparkSession)
    d = _fewer(arrived.filter("k is not null").select(F.col("k").cast("string").alias("k"), _div(F.col("seq") - 1, buffer).alias("epoch")))

    def run(batches):
        marked: dict[int, np.ndarray] = {}
        for b in batches:
            lanes, epoch = bloom.lanes_of(b.column(0)), b.column(1).to_numpy()
            for e in np.unique(epoch).tolist():
                mine = lanes[epoch == e]
                dense = marked.setdefault(e, _room(-(-bloom.size() // page_bits)))
                for j in range(bloom.k):
                    put_bits(dense, bloom.place(mine, bloom.first(mine, 0), j) // page_bits)
        yield from _pages(marked)

    words = _of_pages(_merged(d.mapInArrow(run, "page long, bits binary")))
    return words.groupBy(_div(F.col("word_idx") * WORD, 1 << APART).alias("epoch")).agg(F.sum(F.bit_count("word")).cast("long").alias("page_writes"))


def layer_of(seq: Column, base: int) -> Column:
    """Layers double; only the newest takes inserts."""
    return F.floor(F.log2(1 + _div(seq - 1, base).cast("double")) + 1e-9).cast("long")


@dataclass(frozen=True)
class LayeredBloom:
    """A stack of page-local filters: layer i takes base * 2^i items and has as many blocks as `bits_per_key` asks for.

    Layer 0 is the phase in memory; the others lie on storage, and only the newest takes inserts, through equal
    sub-buffers of its blocks. A lookup asks all layers."""

    base: int
    bits_per_key: int
    k: int
    block_bits: int = 4096

    def blocks(self, layer: int) -> int:
        return -(-(self.base * self.bits_per_key << layer) // self.block_bits)

    def layers(self, n: int) -> int:
        """Layers that n items fill."""
        return int(math.log2(1 + max(n - 1, 0) // self.base) + 1e-9) + 1

    def _lanes(self, key: Column) -> Column:
        return digest_lanes(key, self.k + 1, min(9, 128 // (self.k + 1)))

    def size(self, group: int = 0) -> int:
        return self.blocks(group) * self.block_bits

    def lanes_of(self, keys: pa.Array) -> np.ndarray:
        return lanes_of(keys, self.k + 1, min(9, 128 // (self.k + 1)))

    def first(self, lanes: np.ndarray, group: int) -> np.ndarray:
        return lanes[:, 0] % self.blocks(group) * self.block_bits

    def place(self, lanes: np.ndarray, first: np.ndarray, j: int) -> np.ndarray:
        return first + lanes[:, j + 1] % self.block_bits

    def all_positions(self, key: Column, groups: int) -> Column:
        def local(lanes, i):
            return once(self._first(lanes, F.lit(i), F.lit(self.blocks(i)).cast("long")), lambda first: F.transform(F.slice(lanes, 2, self.k), lambda x: first + F.pmod(x, F.lit(self.block_bits))))

        return once(self._lanes(key), lambda lanes: F.concat(*[local(lanes, i) for i in range(groups)]))

    def _blocks(self, layer: Column) -> Column:
        bits = F.call_function("shiftleft", F.lit(self.base * self.bits_per_key).cast("long"), layer.cast("int"))
        return _div(bits + (self.block_bits - 1), self.block_bits)

    def _first(self, lanes: Column, layer: Column, blocks: Column) -> Column:
        """The key's block's first bit: layers lie 2^40 bits apart."""
        return layer.cast("long") * (1 << 40) + F.pmod(lanes[0], blocks) * self.block_bits

    def build(self, arrived: DataFrame, items: int | None = None) -> DataFrame:
        """(word_idx, word) of all layers of (k, seq); `items`, if known, is the last seq."""
        sizes = [self.size(i) for i in range(self.layers(items))] if items is not None else []
        if sizes and sum(sizes) <= BROADCAST_WORDS * WORD:
            return filled(arrived, self, (layer_of(F.col("seq"), self.base), sizes))
        d = arrived.filter("k is not null").select(layer_of(F.col("seq"), self.base).alias("layer"), self._lanes(F.col("k")).alias("lanes"))
        d = d.select(self._first(F.col("lanes"), F.col("layer"), self._blocks(F.col("layer"))).alias("first"), F.explode(F.slice("lanes", 2, self.k)).alias("lane"))
        return _words_of(d.select((F.col("first") + F.pmod("lane", F.lit(self.block_bits))).alias("bit")))

    def reads(self, df: DataFrame, words: DataFrame, layers: int, page_bits: int) -> DataFrame:
        """df with `hits` (layers that hold all k bits), `maybe`, and `reads`: pages of all layers but the one in memory; these
        take the place of columns of the same names."""
        return answers(df, words, self, layers, page_bits, 1).select(*[c for c in df.columns if c not in ("hits", "maybe", "reads")], F.col("__hits").alias("hits"), (F.col("__hits") > 0).alias("maybe"), F.col("__reads").alias("reads"))

    def probe(self, df: DataFrame, words: DataFrame, layers: int) -> DataFrame:
        """df with `maybe` and how many layers say so."""
        return self.reads(df, words, layers, 0).drop("reads")

    def flushes(self, arrived: DataFrame, buffer: int) -> DataFrame:
        """(layer, block, flushes) after the phase in memory: how often a block is written, as `flush_times` lists them."""
        d = arrived.filter(F.col("seq") > self.base).select(layer_of(F.col("seq"), self.base).alias("layer"), self._lanes(F.col("k"))[0].alias("lane"))
        d = d.withColumn("blocks", self._blocks(F.col("layer"))).groupBy("layer", "blocks", F.pmod("lane", F.col("blocks")).alias("block")).agg(F.count("*").alias("n"))
        cap = F.greatest(F.lit(1).cast("long"), F.call_function("div", F.lit(buffer).cast("long"), F.col("blocks")))
        return d.select("layer", "block", F.call_function("div", F.col("n"), cap).alias("flushes"))

    def flush_times(self, arrived: DataFrame, buffer: int) -> DataFrame:
        """(layer, block, seq): the arrivals after the phase in memory that fill a sub-buffer, of which a layer's blocks share
        `buffer` items equally; each writes one block."""
        from pyspark.sql import Window

        d = arrived.filter(F.col("seq") > self.base).select("seq", layer_of(F.col("seq"), self.base).alias("layer"), self._lanes(F.col("k"))[0].alias("lane"))
        d = d.withColumn("blocks", self._blocks(F.col("layer"))).withColumn("block", F.pmod("lane", F.col("blocks")))
        i = F.row_number().over(Window.partitionBy("layer", "block").orderBy("seq"))
        cap = F.greatest(F.lit(1).cast("long"), F.call_function("div", F.lit(buffer).cast("long"), F.col("blocks")))
        return d.withColumn("i", i).filter(F.col("i") % cap == 0).select("layer", "block", "seq")


def jvm_bloom(df: DataFrame, col: str, n: int, eps: float):
    """Spark's own sketch (classic sessions only): a second implementation to compare with."""
    return df._jdf.stat().bloomFilter(col, n, eps)
