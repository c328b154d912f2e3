"""Lexical retrieval packing: documents that share vocabulary fill the same training windows.

Documents are encoded once and written to the shared folder. Term statistics (document frequencies of the vocabulary's
ids, number and mean length of documents) cover all documents; their size is bounded by the vocabulary. Documents are
dealt by content into shards of about `shard_tokens` ids, each an inverted index with BM25 weights: a document's BM25
weights, projected to `DIM` numbers, walk down a tree of splits along the axes on which a bounded sample differs most, so
that documents with the same vocabulary meet in a shard whatever the number of shards. A group of like documents too
large for a shard is spread over as many as it needs. In a shard the longest
unused document seeds a window; its BM25 neighbours that are unused and fit follow in score order; the best
neighbour left is cut to fill the gap exactly, and its rest stays in the pool. So only a shard's last window is
padded, to a power of two. Full windows inside long documents stand alone.

Defined results: a null text is empty and has only the end id; each id lies in exactly one piece; repeated rows are separate
documents; ties go to the smaller position in id order; an empty table gives no rows.
"""

from __future__ import annotations

import functools
import zlib

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import textkit
from .common import cut, documents, ship

PIECE = pa.schema([("doc_id", pa.int64()), ("start", pa.int64()), ("length", pa.int64()), ("ids_crc32", pa.int64()), ("doc_tokens", pa.int64()), ("sequence_id", pa.int64()), ("offset", pa.int64())])

#: Numbers a document is dealt by, the width of a cut on float32 signatures, and the most documents the splits are drawn from.
DIM, TIE, SAMPLE = 128, 1e-3, 1 << 17


def _encoder(vocabulary: str, end_id: int):
    def run(batches):
        enc = textkit.word_encoder(vocabulary)
        end = np.array([end_id], enc.dtype).tobytes()
        for batch in batches:
            ids = enc.columns(batch.column(1), end)
            n = pc.cast(pc.divide(pc.binary_length(ids), enc.dtype.itemsize), pa.int64())
            yield pa.RecordBatch.from_arrays([batch.column(0), n, ids], names=["doc_id", "n", "ids"])

    return run


def _frequencies(dtype: str, vocab: int):
    def run(batches):
        df = np.zeros(vocab, np.int64)
        for batch in batches:
            docs = batch.column(0).to_pylist()
            for lo in range(0, len(docs), 255):  # as many as a byte counts
                some, seen = np.zeros(vocab, np.uint8), np.zeros(vocab, np.uint8)
                for x in docs[lo : lo + 255]:
                    seen[:] = 0
                    seen[np.frombuffer(x, dtype)] = 1
                    some += seen
                df += some
        at = np.flatnonzero(df)
        yield pa.RecordBatch.from_arrays([pa.array(at), pa.array(df[at])], names=["id", "df"])

    return run


class Shard:
    """BM25 inverted index over a shard's documents."""

    def __init__(self, docs: list[np.ndarray], idf: np.ndarray, mean: float, k1: float = 1.2, b: float = 0.75):
        n = np.array([len(d) for d in docs], np.int64)
        key = np.repeat(np.arange(len(docs)), n) * len(idf) + np.concatenate(docs)
        key, tf = np.unique(key.astype(np.uint32 if len(docs) * len(idf) < 1 << 32 else np.uint64), return_counts=True)
        self.doc, self.term = (key // len(idf)).astype(np.int32), (key % len(idf)).astype(np.int32)
        self.of_doc = np.searchsorted(self.doc, np.arange(len(docs) + 1))
        weight = idf[self.term] * tf * (k1 + 1) / (tf + k1 * (1 - b + b * n[self.doc] / mean))
        order = np.argsort(self.term, kind="stable")
        self.posted, self.weight = self.doc[order].astype(np.intp), weight[order].astype(np.float32).astype(float)  # as bincount takes them
        self.starts = np.searchsorted(self.term[order], np.arange(len(idf) + 1))
        self.size = len(docs)

    def scores(self, seed: int) -> np.ndarray:
        """BM25 of every document of the shard for the seed's distinct terms."""
        t = self.term[self.of_doc[seed] : self.of_doc[seed + 1]]
        lo, n = self.starts[t], self.starts[t + 1] - self.starts[t]
        at = np.arange(n.sum()) + np.repeat(lo - np.cumsum(n) + n, n)
        return np.bincount(self.posted[at], self.weight[at], self.size)

    def keep(self, alive: np.ndarray) -> None:
        """Take the postings of all other documents out."""
        here = alive[self.posted]
        self.starts = np.concatenate([[0], np.cumsum(here)])[self.starts]
        self.posted, self.weight = self.posted[here], self.weight[here]


def pack_shard(docs: list[np.ndarray], index: Shard, window: int) -> list[tuple[int, int, int, int, int]]:
    """(document, start, length, sequence, offset) of all pieces."""
    pieces, seq = [], 0
    n = np.array([len(d) for d in docs], np.int64)
    start = n // window * window
    for d in np.flatnonzero(start):
        for s in range(0, start[d], window):
            pieces.append((d, s, window, seq, 0))
            seq += 1
    rest = n - start
    by_length = np.argsort(-rest, kind="stable")
    at, posted = 0, len(docs)
    while True:
        while at < len(by_length) and not rest[by_length[at]]:
            at += 1
        if at == len(by_length):
            return pieces
        seed = by_length[at]
        room, offset = window, 0

        def put(d, size):
            nonlocal room, offset
            pieces.append((d, start[d], size, seq, offset))
            start[d] += size
            rest[d] -= size
            room, offset = room - size, offset + size

        put(seed, rest[seed])
        if room:
            left = np.flatnonzero(rest)
            if len(left) < 0.8 * posted:  # scores of what is used up aren't needed any more
                index.keep(rest > 0)
                posted = len(left)
            left = left[np.argsort(-index.scores(seed)[left], kind="stable")]
            sizes = rest[left]
            used = np.zeros(len(left), bool)
            pos = 0
            while room:
                fit = np.flatnonzero((sizes[pos:] <= room) & ~used[pos:])
                if not len(fit):
                    break
                pos += int(fit[0])
                used[pos] = True
                put(left[pos], sizes[pos])
            if room and not used.all():
                put(left[np.flatnonzero(~used)[0]], room)
        seq += 1


@functools.cache
def _axes(vocab: int) -> np.ndarray:
    return np.random.default_rng(6).standard_normal((vocab, DIM), np.float32)


def _terms(docs: list[np.ndarray], vocab: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Of all documents in order, each one's distinct ids ascending and how often it has them; and where each document begins, one more at the end."""
    n = np.array([len(d) for d in docs], np.int64)
    key = np.repeat(np.arange(len(docs)) * vocab, n).astype(np.uint32 if len(docs) * vocab < 1 << 32 else np.uint64)  # 32 bits are sorted several times faster
    key += np.concatenate(docs)
    key.sort()
    first = np.concatenate([[0], np.flatnonzero(key[1:] != key[:-1]) + 1]) if len(key) else np.zeros(0, np.int64)
    doc, term = np.divmod(key[first], key.dtype.type(vocab))
    return term, np.diff(first, append=len(key)), np.searchsorted(doc, np.arange(len(docs) + 1))


def signatures(docs: list[np.ndarray], idf: np.ndarray, k1: float = 1.2, run: int = 512) -> np.ndarray:
    """Saturated BM25 weights of each document under a fixed random projection, of unit length."""
    axes = _axes(len(idf))
    out = np.zeros((len(docs), DIM), np.float32)
    for lo in range(0, len(docs), run):
        t, tf, at = _terms(docs[lo : lo + run], len(idf))
        w = (idf[t] * tf * (k1 + 1) / (tf + k1)).astype(np.float32)
        for i in range(len(at) - 1):
            out[lo + i] = w[at[i] : at[i + 1]] @ axes[t[at[i] : at[i + 1]]]
    return out / np.maximum(np.linalg.norm(out, axis=1, keepdims=True), 1e-12)


class Splits:
    """Binary tree over signatures: each node cuts along its sample's first principal axis, in proportion to the leaves
    below. Documents on the cut (copies of one text) go to either side by hash, in the share that the sample shows."""

    def __init__(self, v: np.ndarray, weight: np.ndarray, hashes: np.ndarray, leaves: int):
        self.axis, self.cut, self.share, self.below = [], [], [], []
        v = v.astype(np.float32)
        todo = [(np.arange(len(v)), leaves, None)]
        done = 0
        while todo:
            at, n, parent = todo.pop()
            if parent is not None:
                self.below[parent[0]][parent[1]] = -1 - done if n == 1 else len(self.axis)
            if n == 1:
                done += 1
                continue
            x, w = v[at], weight[at].astype(float)
            axis = np.zeros(DIM, np.float32)
            if len(at) > 1:
                y = (x - np.average(x, axis=0, weights=w)) * np.sqrt(w / w.sum())[:, None]
                value, vector = np.linalg.eigh(y.T @ y)
                if value[-1] > 1e-8:
                    axis = vector[:, -1].astype(np.float32)
            p = np.einsum("ij,j->i", x, axis)
            order = np.argsort(p, kind="stable")
            want = w.sum() * (n // 2) / n
            cut = float(p[order[min(np.searchsorted(np.cumsum(w[order]), want), len(at) - 1)]]) if len(at) else 0.0
            tied = np.abs(p - cut) <= TIE
            share = (want - w[(p < cut) & ~tied].sum()) / w[tied].sum() if tied.any() else 0.5
            node = len(self.axis)
            self.axis.append(axis)
            self.cut.append(cut)
            self.share.append(share)
            self.below.append([0, 0])
            right = self._right(p, np.full(len(at), cut), np.full(len(at), share), hashes[at], np.full(len(at), node))
            todo += [(at[right], n - n // 2, (node, 1)), (at[~right], n // 2, (node, 0))]
        self.axis, self.cut, self.share, self.below = np.array(self.axis, np.float32).reshape(-1, DIM), np.array(self.cut), np.array(self.share), np.array(self.below, np.int64).reshape(-1, 2)

    @staticmethod
    def _right(p, cut, share, hashes, node):
        u = textkit.mix(hashes.astype(np.uint64) + node.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15)) / 2.0**64
        return np.where(np.abs(p - cut) <= TIE, u >= share, p > cut)

    def leaf(self, v: np.ndarray, hashes: np.ndarray) -> np.ndarray:
        node = np.full(len(v), 0 if len(self.axis) else -1)
        while len(at := np.flatnonzero(node >= 0)):
            n = node[at]
            right = self._right(np.einsum("ij,ij->i", v[at], self.axis[n]), self.cut[n], self.share[n], hashes[at], n)
            node[at] = self.below[n, right.astype(int)]
        return -1 - node


def _signer(dtype: str, idf: np.ndarray):
    def run(batches):
        for batch in batches:
            v = signatures([np.frombuffer(x, dtype) for x in batch.column(2).to_pylist()], idf).astype(np.float16)
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array([x.tobytes() for x in v], pa.binary())], names=["n", "h", "v"])

    return run


def _dealer(dtype: str, idf: np.ndarray, splits: Splits, parts: int):
    def run(batches):
        for batch in batches:
            h = batch.column(3).to_numpy().view(np.uint64)
            v = signatures([np.frombuffer(x, dtype) for x in batch.column(2).to_pylist()], idf)
            part = (textkit.mix(h) % np.uint64(parts)).astype(np.int64)
            yield pa.RecordBatch.from_arrays([*batch.columns[:3], pa.array(splits.leaf(v, h) * parts + part)], names=["doc_id", "n", "ids", "shard"])

    return run


def deal(coded: DataFrame, dtype: str, idf: np.ndarray, many: int, shards: int) -> DataFrame:
    """doc_id, n, ids, shard: like documents in one shard, shards of about equal numbers of ids."""
    if shards == 1:
        return coded.withColumn("shard", F.lit(0).cast("long"))
    leaves = min(shards, SAMPLE // 16)
    hashed = coded.select("doc_id", "n", "ids", F.xxhash64("doc_id", "n").alias("h"))
    drawn = F.pmod(F.xxhash64(F.lit(6), "h", "n"), F.lit(1 << 30)) < int(min(1.0, min(64 * leaves, SAMPLE) / many) * (1 << 30))
    some = hashed.filter(drawn).select("n", "h", "ids").mapInArrow(_signer(dtype, idf), "n long, h long, v binary").collect()  # SAMPLE rows at most, but for chance
    some.sort(key=lambda r: (r["h"], r["n"]))
    v = np.array([np.frombuffer(r["v"], np.float16) for r in some]).reshape(-1, DIM)
    splits = Splits(v, np.array([r["n"] for r in some]), np.array([r["h"] for r in some], np.int64).view(np.uint64), leaves)
    return hashed.mapInArrow(_dealer(dtype, idf, splits, -(-shards // leaves)), "doc_id long, n long, ids binary, shard long")


def _packer(dtype: str, idf: np.ndarray, mean: float, window: int):
    def run(key, table):
        table = table.sort_by([("doc_id", "ascending"), ("ids", "ascending")])  # the ids settle rows of equal doc_id
        docs = [np.frombuffer(x, dtype) for x in table["ids"].to_pylist()]
        ids = table["doc_id"].to_pylist()
        index = Shard(docs, idf, mean)
        base = key[0].as_py() << 32
        rows = [(ids[d], int(s), int(n), zlib.crc32(docs[d][s : s + n].astype("<u4")), len(docs[d]), base + q, int(o)) for d, s, n, q, o in pack_shard(docs, index, window)]
        return pa.Table.from_arrays([pa.array(c, f.type) for c, f in zip(zip(*rows, strict=True), PIECE, strict=True)], schema=PIECE)

    return run


def pack(docs: DataFrame, vocabulary: str, end_id: int = 1, window: int = 2048, shard_tokens: int = 1 << 20, text: str = "text", key: str = "doc_id") -> DataFrame:
    """One row per piece: doc_id, start, length, ids_crc32, doc_tokens, sequence_id, offset."""
    spark = docs.sparkSession
    ship(spark)
    enc = textkit.word_encoder(vocabulary)
    dtype, vocab = enc.dtype.str, enc.lib.get_vocab_size()
    coded = cut(docs.select(F.col(key).cast("long").alias("doc_id"), F.col(text).alias("text")).mapInArrow(_encoder(vocabulary, end_id), "doc_id long, n long, ids binary"), "encoded")
    many, total = coded.agg(F.count("*"), F.coalesce(F.sum("n"), F.lit(0))).first()
    df = np.zeros(vocab, np.int64)
    for r in coded.select("ids").mapInArrow(_frequencies(dtype, vocab), "id long, df long").groupBy("id").agg(F.sum("df").alias("df")).collect():  # one row per id of the vocabulary
        df[r["id"]] = r["df"]
    idf = np.log1p((many - df + 0.5) / (df + 0.5)).astype(np.float32)
    shards = max(1, -(-total // shard_tokens))
    return deal(coded, dtype, idf, many, shards).groupBy("shard").applyInArrow(_packer(dtype, idf, max(total / max(many, 1), 1), window), "doc_id long, start long, length long, ids_crc32 long, doc_tokens long, sequence_id long, offset long")


def op6_packing(spark, sf_dir: str) -> DataFrame:
    import public_tokenizers

    return pack(documents(spark, sf_dir), public_tokenizers.path("word_bpe_49k.json"))
