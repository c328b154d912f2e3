"""Quality by ordinal cumulative-link regression over hashed text.

Graded ratings 0 < 1 < ... < G share one weight vector over hashed features; ordered thresholds cut its score:
P(grade >= g) = logistic(score - threshold_g). Features: byte trigrams as shares of the text, presence of hashed words,
and a few shape statistics (share of distinct words, of capitals, of punctuation, of digits, mean word length, length) in
reserved bins. The fit is full-batch Adam on a bounded sample of rated rows (`sample`); word bins whose rates don't differ
between grades beyond chance get no weight. Every document is scored whole.

Ratings from the table `labels`: quality 0 is grade 0, quality 1 with toxic 1 is grade 1, quality 1 alone is grade 2. A
document is kept where P(grade >= 2) >= `least`.

Defined results: a null text counts as empty; rows with null ratings are not used; without rated rows every grade is
equally likely and all documents are kept; repeated rows get equal results; an empty table gives no rows.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import textkit
from .common import documents, ship

TRI, WORD, BINS = 1 << 13, 1 << 20, 16
STATS = 6
SIZE = TRI + WORD + STATS * BINS
#: Rated documents of which a step of the fit makes arrays at once.
BLOCK_ROWS = 256
_UPPER, _PUNCT, _DIGIT = np.zeros(256, np.float32), np.zeros(256, np.float32), np.zeros(256, np.float32)
_UPPER[65:91] = _DIGIT[48:58] = 1
_PUNCT[[*range(33, 48), *range(58, 65), *range(91, 97), *range(123, 127)]] = 1


def _parts(texts: list[bytes]):
    """Of a group of texts: (row, bin) of distinct words, the trigram bins of the joined bytes with each text's run, and
    the bins of the shape statistics."""
    sizes = np.array([len(t) for t in texts])
    data = np.frombuffer(b"".join(texts) + b"\0\0", np.uint8)
    at = np.cumsum(sizes) - sizes
    d = data.astype(np.uint32)
    tri = ((d[:-2] * np.uint32(0x9E3779B1) ^ d[1:-1] * np.uint32(0x85EBCA77) ^ d[2:] * np.uint32(0xC2B2AE3D)) * np.uint32(0x27D4EB2F) >> np.uint32(32 - 13)).astype(np.int32)
    row, _, n, h = textkit.words(texts)
    key = np.unique(row * WORD + (h >> np.uint64(44)).astype(np.int64))
    words = np.bincount(row, minlength=len(texts))
    seen = np.unique(row.astype(np.uint64) << np.uint64(40) | h >> np.uint64(24))
    distinct = np.bincount((seen >> np.uint64(40)).astype(np.int64), minlength=len(texts))
    total = np.maximum(sizes, 1)

    def share(table):
        c = np.concatenate([[0], np.cumsum(table[data[:-2]], dtype=np.float64)])
        return (c[at + sizes] - c[at]) / total

    scaled = [distinct / np.maximum(words, 1) * 15, np.minimum(share(_UPPER) * 40, 15), np.minimum(share(_PUNCT) * 30, 15), np.minimum(share(_DIGIT) * 60, 15), np.minimum(np.bincount(row, n, len(texts)) / np.maximum(words, 1) * 1.2, 15), np.minimum(np.log2(words + 1), 15)]
    stats = np.stack([TRI + WORD + k * BINS + x.astype(np.int64) for k, x in enumerate(scaled)], 1)
    return sizes, at, tri, key // WORD, TRI + key % WORD, stats


def features(texts: list[bytes]) -> list[tuple[np.ndarray, np.ndarray]]:
    """(bins, values) of each text."""
    sizes, at, tri, wrow, wbin, stats = _parts(texts)
    w = np.searchsorted(wrow, np.arange(len(texts) + 1))
    out = []
    for i, n in enumerate(sizes):
        b, c = np.unique(tri[at[i] : at[i] + max(n - 2, 0)], return_counts=True)
        bins = np.concatenate([b, wbin[w[i] : w[i + 1]], stats[i]])
        out.append((bins.astype("<i4"), np.concatenate([c * (100 / max(n, 1)), np.ones(len(bins) - len(b))]).astype("<f4")))
    return out


def scores(texts: list[bytes], weights: np.ndarray) -> np.ndarray:
    sizes, at, tri, wrow, wbin, stats = _parts(texts)
    c = np.concatenate([[0], np.cumsum(weights[tri], dtype=np.float64)])
    dense = (c[at + np.maximum(sizes - 2, 0)] - c[at]) * (100 / np.maximum(sizes, 1))
    return dense + np.bincount(wrow, weights[wbin], len(texts)) + weights[stats].sum(1)


def _sigmoid(x):
    return 1 / (1 + np.exp(-np.clip(x, -40, 40)))


def _telling(idx: np.ndarray, grade: np.ndarray, share: np.ndarray, least: int = 5, z: float = 4.0) -> np.ndarray:
    """Which bins lie over or under in some grade, against chance, by `z` standard deviations: the rest carry no word weight."""
    seen = np.bincount(idx, minlength=SIZE)
    out = np.zeros(SIZE, bool)
    for g, p in enumerate(share):
        out |= np.abs(np.bincount(idx[grade == g], minlength=SIZE) - seen * p) > z * np.sqrt(seen * p * (1 - p) + 1e-9)
    return out & (seen >= least)


def fit(rows: list[tuple[np.ndarray, np.ndarray]], grades: np.ndarray, top: int, steps: int = 160, l2: float = 1e-4) -> tuple[np.ndarray, np.ndarray]:
    """(weights, thresholds): thresholds[g-1] parts the grades below g from g and above. Uses up `rows`."""
    whole, t = np.zeros(SIZE), np.array([-1.0] + [0.0] * (top - 1))  # first threshold, then logs of the gaps
    if not len(rows):
        return whole, np.zeros(top)
    # the arrays of all features keep four bytes an entry; what a step computes is made for one block of rows after the other
    idx, val = np.concatenate([r[0] for r in rows]), np.concatenate([r[1] for r in rows])
    row = np.repeat(np.arange(len(rows), dtype=np.int32), [len(r[0]) for r in rows])
    many = len(rows)
    rows.clear()
    fine = (idx < TRI) | (idx >= TRI + WORD) | _telling(idx, grades.astype(np.int8)[row], np.bincount(grades, minlength=top + 1) / many)[idx]
    idx, val, row = idx[fine], val[fine], row[fine]
    used = np.zeros(SIZE, bool)
    used[idx] = True
    bins = np.flatnonzero(used)
    idx = (np.cumsum(used, dtype=np.int32) - 1)[idx]
    first, size = np.searchsorted(row, np.arange(many + 1)), len(bins)
    blocks = [(a, min(a + BLOCK_ROWS, many)) for a in range(0, many, BLOCK_ROWS)]
    w, m, v = np.zeros(size), np.zeros(size + top), np.zeros(size + top)
    for k in range(1, steps + 1):
        cuts = np.concatenate([[-np.inf], t[0] + np.concatenate([[0], np.cumsum(np.exp(t[1:]))]), [np.inf]])
        s = np.concatenate([np.add.reduceat(val[first[a] : first[b]] * w[idx[first[a] : first[b]]], first[a:b] - first[a]) for a, b in blocks])
        hi, lo = _sigmoid(cuts[grades + 1] - s), _sigmoid(cuts[grades] - s)
        p = np.maximum(hi - lo, 1e-12)
        dhi, dlo = hi * (1 - hi) / p, lo * (1 - lo) / p
        ds = (dhi - dlo) / many
        dc = np.bincount(grades, dlo, top + 1)[1:] - np.bincount(grades, dhi, top + 1)[:-1]
        dt = np.concatenate([[dc.sum()], np.cumsum(dc[::-1])[::-1][1:] * np.exp(t[1:])]) / many
        dw = l2 * w
        for a, b in blocks:
            x, y = first[a], first[b]
            dw += np.bincount(idx[x:y], val[x:y] * ds[row[x:y]], size)
        g = np.concatenate([dw, dt])
        m, v = 0.9 * m + 0.1 * g, 0.99 * v + 0.01 * g * g
        rate = 0.05 * min(1, 2 * (1 - k / (steps + 1)))
        step = rate * (m / (1 - 0.9**k)) / (np.sqrt(v / (1 - 0.99**k)) + 1e-6)
        w, t = w - step[:size], t - step[size:]
    whole[bins] = w
    return whole, t[0] + np.concatenate([[0], np.cumsum(np.exp(t[1:]))])


def _featurise(batches):
    for batch in batches:
        for lo, hi, texts in textkit.groups_of_rows(batch, "text"):
            got = features(texts)
            yield pa.RecordBatch.from_arrays([batch.column(0).slice(lo, hi - lo), pa.array([b.tobytes() for b, _ in got], pa.binary()), pa.array([v.tobytes() for _, v in got], pa.binary())], names=["grade", "bins", "vals"])


def train(docs: DataFrame, ratings: DataFrame, top: int = 2, sample: int = 6000) -> tuple[np.ndarray, np.ndarray]:
    """Fit on at most `sample` rated documents, drawn by hash of the id. `ratings`: doc_id, grade in 0..top."""
    ship(docs.sparkSession)
    drawn = ratings.filter("doc_id is not null and grade is not null").orderBy(F.xxhash64("doc_id"), "doc_id").limit(sample).select(F.col("doc_id").alias("__id"), F.col("grade").cast("int").alias("__grade"))
    rated = docs.select("doc_id", "text").join(F.broadcast(drawn), F.col("doc_id") == F.col("__id")).select(F.col("__grade").alias("grade"), "text")
    got = rated.mapInArrow(_featurise, "grade int, bins binary, vals binary").collect()
    got.sort(key=lambda r: (r["grade"], bytes(r["bins"])))
    rows, grades = [(np.frombuffer(r["bins"], "<i4"), np.frombuffer(r["vals"], "<f4")) for r in got], np.array([r["grade"] for r in got], int)
    del got
    return fit(rows, grades, top)


def _sparse(w: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    at = np.flatnonzero(w).astype(np.int32)
    return at, w[at].astype(np.float32)


def _dense(sparse: tuple[np.ndarray, np.ndarray]) -> np.ndarray:
    w = np.zeros(SIZE, np.float32)
    w[sparse[0]] = sparse[1]
    return w


def _scorer(sparse, cuts: np.ndarray):
    def run(batches):
        textkit.release()
        w = _dense(sparse)
        for batch in batches:
            for lo, hi, texts in textkit.groups_of_rows(batch, "text"):
                tails = _sigmoid(scores(texts, w)[:, None] - cuts)
                yield pa.RecordBatch.from_arrays([*(c.slice(lo, hi - lo) for c in batch.columns[:-1]), pa.array(np.round(tails.sum(1), 6)), pa.array(np.round(tails[:, -1], 6))], names=[*batch.schema.names[:-1], "expected_grade", "tail_probability"])

    return run


def score(docs: DataFrame, model: tuple[np.ndarray, np.ndarray], key: str = "doc_id") -> DataFrame:
    """doc_id, expected_grade, tail_probability (of the top grade) of every document."""
    ship(docs.sparkSession)
    w, cuts = model
    return docs.select(F.col(key).cast("long").alias("doc_id"), "text").mapInArrow(_scorer(_sparse(w), cuts), "doc_id long, expected_grade double, tail_probability double")


def ratings_of(labels: DataFrame) -> DataFrame:
    grade = F.when(F.col("quality") == 0, 0).when(F.col("toxic") == 1, 1).when(F.col("quality") == 1, 2)
    return labels.groupBy("doc_id").agg(F.min(grade).alias("grade"))


def keep_good(docs: DataFrame, labels: DataFrame, least: float = 0.5) -> DataFrame:
    """The documents with P(top grade) >= `least`, with all their columns."""
    w, cuts = train(docs, ratings_of(labels))
    sparse = _sparse(w)

    def run(batches):
        textkit.release()
        w = _dense(sparse)
        for batch in batches:
            for lo, hi, texts in textkit.groups_of_rows(batch, "text"):
                ok = _sigmoid(scores(texts, w) - cuts[-1]) >= least
                yield batch.slice(lo, hi - lo).filter(pa.array(ok))

    return docs.mapInArrow(run, docs.schema)


def op2_quality(spark, sf_dir: str) -> DataFrame:
    docs = documents(spark, sf_dir)
    model = train(docs, ratings_of(spark.read.parquet(f"{sf_dir}/labels.parquet")))
    return score(docs, model).withColumn("kept", F.col("tail_probability") >= 0.5)
