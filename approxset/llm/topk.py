"""Exact top-k by inner product with pivot-table elimination.

Vectors are packed into blocks, in the order of their nearest pivots; each block carries a table of the least and largest
distance to every pivot in each group of `GROUP` vectors. For a query, the largest gap between its own distance to a pivot and
a group's range bounds the distance to all of the group from below, hence (with the norms) their inner products from above.
A group whose bound reaches no query's k-th best score so far (in the sample or the task's blocks) is left out, ties included; what remains is evaluated
by matrix products of a tile of queries, which are exact: in single precision where all products stay below 2^24, else in
double precision. Query blocks are sent to all tasks, `SENT` bytes in a pass at most, and meet the candidate blocks where these
lie: no vector is copied once a meeting. A task keeps each query's k best so far, which raise the bound of its next
blocks, and yields k rows per query at most.

Pivots come from a bounded sample (`sample` vectors, farthest-first); it steers speed only, never the result. Squared
distances are sums of integers below 2^53 and so exact; the slack of the bounds covers their square roots.

Defined results: components are floor(256 * x) with x as double; vectors that are null, or hold a null or a non-finite
component, take no part; shorter vectors count as padded with zeros; equal scores go to the smaller id; rows with equal
ids are separate candidates, but none is a candidate of its own id; fewer than k candidates give fewer rows; an
empty table gives no rows. Squared lengths must stay below 2^51, so that inner products and distances are exact in
doubles; a longer vector raises an error.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..cluster import cleaned
from .common import cut, ship

EXACT = 2.0**51
#: Vectors of a block that share a row of bounds.
GROUP = 64
#: Bytes of the queries' vectors that are sent to all tasks in one pass.
SENT = 32 << 20
OUT = pa.schema([("query_id", pa.int64()), ("vec_id", pa.int64()), ("score", pa.int64())])


def integer_vectors(rows: DataFrame, key: str = "vec_id", vector: str = "embedding", scale: int = 256) -> DataFrame:
    """id, v (array of long): the vectors that take part."""
    d = rows.select(F.col(key).cast("long").alias("id"), F.transform(vector, lambda x: x.cast("double")).alias("d")).filter("id is not null and d is not null")
    fine = F.forall("d", lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < float("inf")))
    norm = F.aggregate("d", F.lit(0.0), lambda s, x: s + F.pow(F.abs(x) * scale + 1, F.lit(2)))
    long = F.concat(F.lit("vector of id "), "id", F.lit(" is too long for exact scores"))
    v = F.when(norm >= EXACT, F.raise_error(long)).otherwise(F.transform("d", lambda x: F.floor(x * scale).cast("long")))
    return d.filter(fine).select("id", v.alias("v"))


def _pack(pivots: np.ndarray, dim: int, more):
    """Blocks as (ids, vectors, table), one row per group; vectors lie by their nearest pivot, `more(ids, vectors)` is the table."""

    def pack(key, table):
        ids = table["id"].to_numpy()
        v, x = np.zeros((len(ids), dim)), table["v"].combine_chunks()
        long = x.value_lengths().to_numpy(zero_copy_only=False)
        v[np.arange(dim) < long[:, None]] = x.flatten().to_numpy()
        o = np.lexsort((ids, _distances(v, pivots).argmin(1)))
        return pa.table({"block": pa.array([key[0].as_py()], pa.int32()), "ids": [ids[o].astype("<i8").tobytes()], "vectors": [v[o].astype("<i4").tobytes()], "table": [more(ids[o], v[o]).astype("<f8").tobytes()]})

    return pack


def group_table(v: np.ndarray, pivots: np.ndarray) -> np.ndarray:
    """Of each group: least and largest distance to each pivot, the largest squared norm."""
    at = np.arange(0, len(v), GROUP)
    d = _distances(v, pivots)
    return np.concatenate([np.minimum.reduceat(d, at), np.maximum.reduceat(d, at), np.maximum.reduceat((v**2).sum(1), at)[:, None]], axis=1)


def _distances(v: np.ndarray, p: np.ndarray) -> np.ndarray:
    return np.sqrt(np.maximum((v**2).sum(1)[:, None] + (p**2).sum(1) - 2 * v @ p.T, 0))


def farthest_first(v: np.ndarray, many: int) -> np.ndarray:
    """Pivots from a sample: each is the one farthest from those before it."""
    chosen, d = [0], None
    while len(chosen) < min(many, len(v)):
        e = ((v - v[chosen[-1]]) ** 2).sum(1)
        d = e if d is None else np.minimum(d, e)
        chosen.append(int(d.argmax()))
    return v[chosen]


def group_bounds(q: np.ndarray, qt: np.ndarray, table: np.ndarray) -> np.ndarray:
    """Upper bounds of the inner products of each query with each group."""
    m = qt.shape[1]
    low = np.zeros((len(q), len(table)))
    for j in range(m):
        np.maximum(low, np.maximum(table[:, j] - qt[:, j, None], qt[:, j, None] - table[:, m + j]), out=low)
    low = np.maximum(low - 1e-6 * (1 + low), 0)
    return ((q**2).sum(1)[:, None] + table[:, 2 * m] - low**2) / 2 + 0.5


def reached(q: np.ndarray, qt: np.ndarray, table: np.ndarray, floor: np.ndarray, first: int = 16) -> np.ndarray:
    """Whether a group's bound reaches the floor of any query. Few queries show it for most groups; the others ask all."""
    live = np.zeros(len(table), bool)
    for part in (slice(first), slice(first, None)):
        if len(at := np.flatnonzero(~live)) and len(q[part]):
            live[at] = (group_bounds(q[part], qt[part], table[at]) >= floor[part]).any(axis=0)
    return live


def block_top(qid: np.ndarray, q: np.ndarray, qt: np.ndarray, ids: np.ndarray, v: np.ndarray, table: np.ndarray, k: int, least: np.ndarray, tile: int = 256) -> tuple[np.ndarray, np.ndarray, np.ndarray, int]:
    """Queries' ids, ids and scores of each query's k best in the block, and how many inner products it took. Scores below
    `least`, one for each query, are known not to be among its k best anywhere."""
    out, done = [(np.zeros(0, np.int64),) * 3], 0
    small = ((q**2).sum(1).max(initial=0) * table[:, -1].max(initial=0)) < 2.0**48
    kind = np.float32 if small else np.float64
    v, q_ = v.astype(kind), q.astype(kind)
    own = np.isin(ids, qid)
    for lo in range(0, len(qid), tile):
        part = slice(lo, lo + tile)
        floor = np.maximum(least[part, None], -2 * EXACT)  # above what marks a query's own row
        at = np.flatnonzero(np.repeat(reached(q[part], qt[part], table, floor), GROUP)[: len(ids)])
        if not len(at):
            continue
        s = q_[part] @ (v if len(at) == len(v) else v[at]).T
        done += s.size
        for j in np.flatnonzero(own[at]):
            s[qid[part] == ids[at[j]], j] = -np.inf
        good = s >= floor.astype(kind)
        i, j = np.divmod(np.flatnonzero(good), len(at))
        many = np.flatnonzero(np.bincount(i, minlength=len(s)) > 16 * k)
        for m in many:  # a low or much tied bound: the k best of the row alone
            kth = np.partition(s[m], len(at) - k)[len(at) - k] if len(at) > k else -np.inf
            tied = np.flatnonzero(good[m] & (s[m] == kth))
            good[m] &= s[m] > kth
            good[m, tied[np.argsort(ids[at[tied]], kind="stable")[:k]]] = True
        if len(many):
            i, j = np.divmod(np.flatnonzero(good), len(at))
        score, found = s[i, j].astype(np.int64), ids[at[j]]
        o = np.lexsort((found, -score, i))
        i, score, found = i[o], score[o], found[o]
        first = np.arange(len(i)) - np.searchsorted(i, i) < k
        out.append((qid[part][i[first]], found[first], score[first]))
    return *(np.concatenate(x) for x in zip(*out, strict=True)), done


def sample_best(qid: np.ndarray, q: np.ndarray, ids: np.ndarray, v: np.ndarray, k: int) -> np.ndarray:
    """Each query's k-th best score in a sample of the candidates: no smaller score is among its k best of all."""
    if len(ids) <= k:
        return np.full(len(qid), -np.inf)
    s = q @ v.T
    s[qid[:, None] == ids] = -np.inf
    return -np.partition(-s, k - 1, axis=1)[:, k - 1]


def best_of(query: np.ndarray, found: np.ndarray, score: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """The k best rows of each query id, ties to the smaller id, by query id and rank."""
    o = np.lexsort((found, -score, query))
    query, found, score = query[o], found[o], score[o]
    first = np.arange(len(query)) - np.searchsorted(query, query) < k
    return query[first], found[first], score[first]


def raised(least: np.ndarray, qid: np.ndarray, best: tuple[np.ndarray, np.ndarray, np.ndarray], k: int) -> np.ndarray:
    """`least`, or the k-th of the best rows found so far (as `best_of` gives them) where that is more."""
    query, _, score = best
    first = np.searchsorted(query, qid)
    full = np.flatnonzero(np.searchsorted(query, qid, "right") - first >= k)
    out = least.copy()
    out[full] = np.maximum(least[full], score[first[full] + k - 1])
    return out


def _meet(k: int, dim: int, pivots: np.ndarray):
    def run(batches):
        held = {}  # by query block: each query's best rows of the task's blocks so far, and the least score that can still be one
        for batch in batches:
            for i in range(batch.num_rows):
                r = {n: batch.column(n)[i].as_py() for n in batch.schema.names}
                q, v = (np.frombuffer(r[n], "<i4").reshape(-1, dim).astype(float) for n in ("qvectors", "vectors"))
                qid = np.frombuffer(r["qids"], "<i8")
                best, least = held.get(r["qblock"]) or (None, np.frombuffer(r["least"], "<f8"))
                got = block_top(qid, q, _distances(q, pivots), np.frombuffer(r["ids"], "<i8"), v, np.frombuffer(r["table"], "<f8").reshape(-1, 2 * len(pivots) + 1), k, least)[:3]
                best = best_of(*(got if best is None else map(np.concatenate, zip(best, got, strict=True))), k)
                held[r["qblock"]] = best, raised(least, qid, best, k)
        for best, _ in held.values():
            yield pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in best], schema=OUT)

    return run


def top_k(candidates: DataFrame, queries: DataFrame, k: int = 5, pivots: int = 32, sample: int = 2048, block: int = 4096) -> DataFrame:
    """query_id, rank (from 1), vec_id, score: exact. Both inputs have columns id, v as `integer_vectors` gives them."""
    spark = candidates.sparkSession
    ship(spark)
    some = candidates.orderBy(F.xxhash64("id"), "id").limit(sample).collect()  # bounded sample for pivots
    n, dim = candidates.agg(F.count("*"), F.coalesce(F.max(F.size("v")), F.lit(1))).first()
    qn, qdim = queries.agg(F.count("*"), F.coalesce(F.max(F.size("v")), F.lit(1))).first()
    dim = max(dim, qdim, 1)
    v = np.zeros((max(len(some), 1), dim))
    for i, r in enumerate(some):
        v[i, : len(r["v"])] = r["v"]
    p = farthest_first(v, pivots)
    some_v = v[: len(some)]
    some_ids = np.array([r["id"] for r in some], np.int64)
    blocks, qblocks = max(1, -(-n // block)), max(1, -(-qn // block))
    dealt = lambda d, m: d.withColumn("block", F.pmod(F.xxhash64("id", "v"), F.lit(m)).cast("int"))
    kind = "block int, ids binary, vectors binary, table binary"
    right = cut(dealt(candidates, blocks).groupBy("block").applyInArrow(_pack(p, dim, lambda _, x: group_table(x, p)), kind), "candidate-blocks")
    left = cut(dealt(queries, qblocks).groupBy("block").applyInArrow(_pack(p, dim, lambda ids, x: sample_best(ids, x, some_ids, some_v, k)), kind), "query-blocks")
    tasks = min(blocks, max(16, 4 * spark.sparkContext.defaultParallelism))
    left = left.select(F.col("block").alias("qblock"), F.col("ids").alias("qids"), F.col("vectors").alias("qvectors"), F.col("table").alias("least"))
    many = max(1, SENT // (block * dim * 4))

    def ranked(rows: DataFrame) -> DataFrame:
        w = Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id")
        return rows.withColumn("rank", F.row_number().over(w)).filter(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")

    def met(asked: DataFrame) -> DataFrame:
        return ranked(right.repartition(tasks, "block").crossJoin(F.broadcast(asked)).mapInArrow(_meet(k, dim, p), "query_id long, vec_id long, score long"))

    if qblocks <= many:
        return met(left)
    out = None
    for lo in range(0, qblocks, many):
        with cleaned(spark):
            one = cut(met(left.filter(F.col("qblock").between(lo, lo + many - 1))), "best")
        out = one if out is None else out.unionByName(one)
    return ranked(out.drop("rank"))  # rows of one query id may have come in several passes


def op7_exact_topk(spark, sf_dir: str) -> DataFrame:
    rows = integer_vectors(spark.read.parquet(f"{sf_dir}/embeddings.parquet"))
    return top_k(rows, rows.filter(F.col("id") % 50 == 0), 5)
