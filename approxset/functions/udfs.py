"""Filters in SQL: aggregates that build and merge payloads, table functions that list them, probes over registered filters.

A payload describes itself: a header of four longs (first quotient, ring, r, width), then the packed ring. One payload
holds one contiguous range of quotients; callers group by (group, shard) after `build_fp`, so a payload's rows are
bounded by the shard and repeated keys have collapsed before the shuffle."""

from __future__ import annotations

import struct

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators.quotient import BROADCAST_BYTES, layout, pack_ring, ring_size, unpack_ring
from ..schema import FilterSpec
from . import fingerprint

HEAD, HEAD_BYTES = "<4q", 32
STATS = "n long, ring long, bits long, longest long"


def encode(fps: np.ndarray, first: int, per: int, r: int, width: int) -> bytes:
    """Sorted fingerprints (with repeats) of quotients first .. first + per - 1."""
    ring = ring_size(per, len(fps))
    return struct.pack(HEAD, first, ring, r, width) + pack_ring(fps // width - first, fps % width, ring, r)


def decode(payload: bytes) -> np.ndarray:
    first, ring, r, width = struct.unpack_from(HEAD, payload)
    g, rem = unpack_ring(payload[HEAD_BYTES :], ring, r)
    return (g + first) * width + rem


def build_filter(spec: FilterSpec, shards: int = 1):
    """Aggregate (fp, cnt) -> payload, for groups inside one of `shards` equal ranges of quotients."""
    per, r, width = -(-spec.slots // shards), spec.r, spec.width

    @F.pandas_udf("binary")
    def build(fp: pd.Series, cnt: pd.Series) -> bytes:
        f = np.sort(np.repeat(fp.to_numpy(np.int64), cnt.to_numpy(np.int64)))
        first = int(f[0]) // width // per * per if len(f) else 0
        return encode(f, first, per, r, width)

    return build


def merge_filters(spec: FilterSpec, shards: int = 1):
    """Aggregate payload -> payload: the multisets of one range of quotients add up, without rehashing."""
    per, r, width = -(-spec.slots // shards), spec.r, spec.width

    @F.pandas_udf("binary")
    def merge(payload: pd.Series) -> bytes:
        parts = [decode(bytes(p)) for p in payload.dropna()]
        f = np.sort(np.concatenate(parts)) if parts else np.zeros(0, np.int64)
        first = int(f[0]) // width // per * per if len(f) else 0
        return encode(f, first, per, r, width)

    return merge


class TraverseFilter:
    """Rows of a payload in ascending order of fingerprint."""

    def eval(self, payload: bytes):
        if payload is not None:
            width = struct.unpack_from(HEAD, payload)[3]
            for fp, cnt in zip(*np.unique(decode(bytes(payload)), return_counts=True), strict=True):
                yield int(fp) // width, int(fp) % width, int(fp), int(cnt)


class FilterSlots:
    """Used slots of a payload's ring, numbered inside it."""

    def eval(self, payload: bytes):
        if payload is not None:
            first, ring, _, width = struct.unpack_from(HEAD, payload)
            f = decode(bytes(payload))
            g = f // width - first
            cont = np.append(False, g[1:] == g[:-1])[: len(g)]
            for row in zip(layout(g, ring).tolist(), g.tolist(), (f % width).tolist(), cont.tolist(), strict=True):
                yield row[0], row[1] + first, row[2], row[0] != row[1], row[3]


def filter_stats(payload: pd.Series) -> pd.DataFrame:
    """Items, slots, bits of the packed ring and its longest cluster; nulls for a null payload."""
    out = []
    for p in payload:
        if p is None:
            out.append((None,) * 4)
            continue
        first, ring, r, width = struct.unpack_from(HEAD, p)
        s = np.sort(layout(decode(bytes(p)) // width - first, ring))
        edges = np.flatnonzero(np.diff(s) > 1) + 1
        runs = np.diff(np.concatenate([[0], edges, [len(s)]]))
        if len(runs) > 1 and s[0] == 0 and s[-1] == ring - 1:
            runs[0] += runs[-1]
        out.append((len(s), ring, ring * (r + 3), int(runs.max()) if len(s) else 0))
    return pd.DataFrame(out, columns=["n", "ring", "bits", "longest"]).astype("Int64")


def _sent(spark: SparkSession, payloads: DataFrame):
    """Payloads as a broadcast, behind a check of their size; beyond it the callers' plain join is the way."""
    size = payloads.agg(F.coalesce(F.sum(F.octet_length("payload")), F.lit(0))).first()[0]
    if size > BROADCAST_BYTES:
        raise ValueError(f"{size} bytes of filters: use probe_shard or probe_join")
    return spark.sparkContext.broadcast([(r["filter_id"], bytes(r["payload"])) for r in payloads.collect()])


def register_might_contain(spark: SparkSession, payloads: DataFrame, p: int, name: str = "might_contain") -> None:
    """SQL `name(filter_id, hash60(key))` over payloads (filter_id, payload); null keys and unknown filters are absent."""
    sent, known = _sent(spark, payloads), {}

    @F.pandas_udf("boolean")
    def might_contain(filter_id: pd.Series, h: pd.Series) -> pd.Series:
        if not known:
            parts = {}
            for i, payload in sent.value:
                parts.setdefault(i, []).append(decode(payload))
            known.update({i: np.unique(np.concatenate(x)) for i, x in parts.items()})
        out = np.zeros(len(h), bool)
        fp = h.fillna(-1).to_numpy(np.int64) >> (60 - p)
        for i, at in filter_id.groupby(filter_id).indices.items():
            f = known.get(i)
            if f is not None and len(f):
                out[at] = f[np.minimum(np.searchsorted(f, fp[at]), len(f) - 1)] == fp[at]
        return pd.Series(out)

    fingerprint.register(spark)
    spark.udf.register(name, might_contain)


def _positions(h: np.ndarray, m: int, k: int) -> np.ndarray:
    """k bit positions of 60-bit hashes: one half plus multiples of the other, made odd."""
    return ((h >> 30)[:, None] + np.arange(k) * ((h & ((1 << 30) - 1)) | 1)[:, None]) % m


def build_bloom(m: int, k: int):
    """Aggregate hash60 -> payload of m bits. State is bounded by the distinct keys of a group: deduplicate first."""

    @F.pandas_udf("binary")
    def build(h: pd.Series) -> bytes:
        bits = np.zeros(m, np.uint8)
        bits[_positions(h.dropna().to_numpy(np.int64), m, k).ravel()] = 1
        return np.packbits(bits, bitorder="little").tobytes()

    return build


def register_bloom_might_contain(spark: SparkSession, payloads: DataFrame, m: int, k: int, name: str = "bloom_might_contain") -> None:
    """SQL `name(filter_id, hash60(key))` over Bloom payloads (filter_id, payload)."""
    sent = _sent(spark, payloads)

    @F.pandas_udf("boolean")
    def might_contain(filter_id: pd.Series, h: pd.Series) -> pd.Series:
        known = dict(sent.value)
        out = np.zeros(len(h), bool)
        at = _positions(h.fillna(0).to_numpy(np.int64), m, k)
        for i, rows in filter_id.groupby(filter_id).indices.items():
            if i in known:
                bits = np.frombuffer(known[i], np.uint8)
                out[rows] = ((bits[at[rows] >> 3] >> (at[rows] & 7)) & 1).all(1)
        return pd.Series(out & h.notna().to_numpy())

    fingerprint.register(spark)
    spark.udf.register(name, might_contain)


def register_tables(spark: SparkSession) -> None:
    """SQL `traverse_filter(payload)`, `filter_slots(payload)` (table functions) and `filter_stats(payload)`."""
    spark.udtf.register("traverse_filter", F.udtf(TraverseFilter, returnType="quotient long, remainder long, fp long, cnt long"))
    spark.udtf.register("filter_slots", F.udtf(FilterSlots, returnType="slot long, quotient long, remainder long, shifted boolean, continuation boolean"))
    spark.udf.register("filter_stats", F.pandas_udf(filter_stats, STATS))
