"""Exact deduplication against a minimal perfect hash of historical distinct digests.

The history's distinct digests (pre-aggregated, so a group of copies is one row) are dealt into buckets by a digest
prefix. Each bucket gets a minimal perfect hash: levels of bit arrays in which every digest that hits a bit alone
keeps it, the others going to the next level; the rank of a digest's bit is its slot. A slot holds the full digest,
the winner's locator (its document id) and the group's size. Lookups find the slot and compare all 32 bytes:
members get their winner; nonmembers are grouped among themselves.

Digests that hold more than 1/`hot_share` of the history (so fewer than `hot_share` of them: a size bound by
arithmetic) are looked up in many copies of a small bucket of their own, so that no task gets a whole hot group.

Defined results: a null text counts as empty; equal texts are those with equal bytes; the largest document id stays
(null ids lose to all others); repeated rows with the same id are copies of each other, of which each carries
`kept` where its id is the winner's, while `keep_one_of_each` lets one of them stay; an empty table gives no rows.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import cut, documents, partitions, ship, text_of

#: Rows that a bucket holds on average at most: a task's Python memory doesn't grow with the data.
BUCKET_ROWS = 100_000
_SEEDS = np.arange(1, 65, dtype=np.uint64) * np.uint64(0x9E3779B97F4A7C15)


class PerfectHash:
    """Minimal perfect hash over distinct 32-byte digests, given as an (n, 4) array of 64-bit words."""

    def __init__(self, keys: np.ndarray, gamma: float = 2.0):
        self.levels: list[np.ndarray] = []
        rest = keys
        while len(rest):
            assert len(self.levels) < 64, "digests repeat"
            m = (int(gamma * len(rest)) + 64) & ~63
            at = self._at(rest, len(self.levels), m)
            alone = np.bincount(at, minlength=m) == 1
            self.levels.append(alone)
            rest = rest[~alone[at]]
        self.bases = np.cumsum([0] + [int(x.sum()) for x in self.levels])
        # set bits before each block of 64: an eighth of a byte a bit beside the bits themselves
        self.ranks = [np.concatenate([[0], np.cumsum(x.reshape(-1, 64).sum(axis=1, dtype=np.int64))[:-1]]) for x in self.levels]

    @staticmethod
    def _at(keys: np.ndarray, level: int, m: int) -> np.ndarray:
        h = keys[:, level % 4] ^ _SEEDS[level]
        h = (h ^ (h >> np.uint64(31))) * np.uint64(0xBF58476D1CE4E5B9)
        h = (h ^ (h >> np.uint64(29))) * np.uint64(0x94D049BB133111EB)
        return ((h ^ (h >> np.uint64(32))) % np.uint64(m)).astype(np.int64)

    def _rank(self, level: int, at: np.ndarray) -> np.ndarray:
        """Set bits of a level before each position."""
        inside = self.levels[level].reshape(-1, 64)[at >> 6] & (np.arange(64) < (at & 63)[:, None])
        return self.ranks[level][at >> 6] + inside.sum(axis=1)

    def slots(self, keys: np.ndarray) -> np.ndarray:
        """A slot for each key; -1 where no level holds its bit. A nonmember may get a slot: compare the digest."""
        out = np.full(len(keys), -1, np.int64)
        rest = np.arange(len(keys))
        for i, bits in enumerate(self.levels):
            if not len(rest):
                break
            at = self._at(keys[rest], i, len(bits))
            hit = bits[at]
            out[rest[hit]] = self.bases[i] + self._rank(i, at[hit])
            rest = rest[~hit]
        return out


def _words(col) -> np.ndarray:
    """Binary digests of 32 bytes as an (n, 4) array."""
    if isinstance(col, pa.ChunkedArray):
        col = col.combine_chunks() if col.num_chunks else pa.array([], col.type)
    return np.frombuffer(b"".join(col.to_pylist()), np.uint64).reshape(-1, 4)


def _lookup(left, right):
    """Rows of a bucket against its index."""
    rows, known = _words(left["digest"]), _words(right["digest"])
    keep, size = np.zeros(len(rows), np.int64), np.zeros(len(rows), np.int64)
    member = np.zeros(len(rows), bool)
    null_winner = np.zeros(len(rows), bool)
    if len(known) and len(rows):
        h = PerfectHash(known)
        order = np.empty(len(known), np.int64)
        order[h.slots(known)] = np.arange(len(known))  # slot -> its full digest, locator and size
        slot = h.slots(rows)
        at = order[np.maximum(slot, 0)]
        member = (slot >= 0) & (known[at] == rows).all(axis=1)
        winner = right["keep_id"].combine_chunks()
        keep = winner.fill_null(0).to_numpy(zero_copy_only=False)[at]
        null_winner = winner.is_null().to_numpy(zero_copy_only=False)[at]
        size = right["n"].to_numpy()[at]
    return pa.table({"doc_id": left["doc_id"], "digest": left["digest"], "keep_id": pa.array(keep, pa.int64(), mask=~member | null_winner), "n": pa.array(size, pa.int64(), mask=~member)})


def distinct_digests(docs: DataFrame, text: str = "text", key: str = "doc_id") -> DataFrame:
    """digest, keep_id (largest id), n: one row per distinct text."""
    return _digested(docs, text, key).groupBy("digest").agg(F.max("doc_id").alias("keep_id"), F.count("*").alias("n"))


def _digested(docs: DataFrame, text: str, key: str) -> DataFrame:
    return docs.select(F.col(key).cast("long").alias("doc_id"), F.unhex(F.sha2(text_of(text).cast("binary"), 256)).alias("digest"))


def exact_duplicates(docs: DataFrame, history: DataFrame | None = None, text: str = "text", key: str = "doc_id", hot_share: int = 1000, copies: int = 64) -> DataFrame:
    """doc_id, digest, keep_id, n (group size) for every row of `docs`.

    `history` has columns digest, keep_id, n as `distinct_digests` gives them; by default that of `docs` itself."""
    spark = docs.sparkSession
    ship(spark)
    rows = _digested(docs, text, key)
    index = cut(distinct_digests(docs, text, key) if history is None else history.select("digest", "keep_id", "n"), "digest-index")
    total, distinct = index.agg(F.coalesce(F.sum("n"), F.lit(0)), F.count("*")).first()
    buckets = max(partitions(spark) * 4, max(total, distinct) // BUCKET_ROWS)
    hot = index.filter(F.col("n") > max(total / hot_share, 1)).select("digest", F.lit(True).alias("hot"))  # fewer than hot_share rows
    bucket = F.pmod(F.hash("digest"), F.lit(buckets))
    index = index.join(F.broadcast(hot), "digest", "left").withColumn("bucket", F.when(F.col("hot"), F.sequence(F.lit(-copies), F.lit(-1))).otherwise(F.array(bucket))).select("digest", "keep_id", "n", F.explode("bucket").alias("bucket"))
    rows = rows.join(F.broadcast(hot), "digest", "left").select("doc_id", "digest", F.when(F.col("hot"), -1 - F.pmod(F.hash("doc_id"), F.lit(copies))).otherwise(bucket).alias("bucket"))
    found = rows.groupBy("bucket").cogroup(index.groupBy("bucket")).applyInArrow(_lookup, "doc_id long, digest binary, keep_id long, n long")
    if history is None:
        return found  # every row is a member of its own history
    found = cut(found, "digest-lookups")
    new = found.filter("n is null").select("doc_id", "digest")
    groups = new.groupBy("digest").agg(F.max("doc_id").alias("keep_id"), F.count("*").alias("n"))
    return found.filter("n is not null").unionByName(new.join(groups, "digest").select("doc_id", "digest", "keep_id", "n"))


def keep_one_of_each(docs: DataFrame, text: str = "text", key: str = "doc_id") -> DataFrame:
    """The documents that stay, with all their columns: of equal texts one row with the largest id.

    Winners are matched by id and digest, so rows of equal id and different text don't stay for one another; of several
    rows with the winner's id and text, one stays."""
    won = cut(exact_duplicates(docs, text=text, key=key).filter("doc_id <=> keep_id").groupBy(F.col("doc_id").alias("__id"), F.col("digest").alias("__digest")).agg(F.count("*").alias("__rows")), "winners")

    def those(winners: DataFrame) -> DataFrame:
        same = F.col(key).cast("long").eqNullSafe(F.col("__id")) & (F.unhex(F.sha2(text_of(text).cast("binary"), 256)) == F.col("__digest"))
        return docs.join(winners, same, "left_semi")

    twins = won.filter("__rows > 1")
    if twins.isEmpty():
        return those(won)
    return those(won.filter("__rows = 1")).unionByName(those(twins).withColumn("__text", text_of(text)).dropDuplicates([key, "__text"]).drop("__text"))


def op5_exact_dedup(spark, sf_dir: str) -> DataFrame:
    d = exact_duplicates(documents(spark, sf_dir))
    return d.select("doc_id", "keep_id", F.col("n").alias("group_size"), F.col("doc_id").eqNullSafe(F.col("keep_id")).alias("kept"), F.lower(F.hex("digest")).alias("text_sha256"))
