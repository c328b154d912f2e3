"""Byte-level BPE without regular expressions: class arrays, transition-function scans, cached pair merging.

Each code point has a class (letter, number, space, other white space, other); with one to two code points of lookahead
it becomes a symbol, and a symbol is a function from the automaton's state before it to the state after it. Functions
compose associatively, and the functions that the symbols generate are a small finite monoid; so states at all
positions come from a blocked prefix scan over a composition table, vectorised over the blocks. A slice begins where
(symbol, state) says so. Slices are merged by rank with a cache. Their byte offsets are kept beside the ids:
decoding finds the slices that cover any range of bytes, and puts each back into its place.

Defined results: a null text is empty, with no ids; special tokens' strings are ordinary text; an empty table gives no rows.
"""

from __future__ import annotations

import base64
import hashlib
import heapq
import unicodedata
from bisect import bisect_left, bisect_right
from itertools import accumulate, chain

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import documents, ship

LETTER, NUMBER, OTHER, INNER_WS, LAST_SPACE, LAST_WS, APOS2, APOS3 = range(8)
CLOSED, IN_LETTERS, IN_NUMBERS, IN_OTHER, IN_WS, AFTER_SPACE, LEFT1, LEFT2 = range(8)
#: The code points that are white space.
WHITE = [9, 10, 11, 12, 13, 32, 0x85, 0xA0, 0x1680, *range(0x2000, 0x200B), 0x2028, 0x2029, 0x202F, 0x205F, 0x3000]


def _step(symbol: int, state: int) -> tuple[int, bool]:
    """State after the symbol, and whether a slice begins at it."""
    if state in (LEFT1, LEFT2):  # the rest of a contraction
        return (CLOSED if state == LEFT1 else LEFT1), False
    if symbol in (LETTER, NUMBER, OTHER):
        to = (IN_LETTERS, IN_NUMBERS, IN_OTHER)[symbol]
        return to, state not in (to, AFTER_SPACE)
    if symbol == INNER_WS:
        return IN_WS, state != IN_WS
    if symbol in (LAST_SPACE, LAST_WS):
        return (AFTER_SPACE if symbol == LAST_SPACE else CLOSED), True
    if state in (IN_OTHER, AFTER_SPACE):
        return IN_OTHER, False
    return (LEFT1 if symbol == APOS2 else LEFT2), True


def _monoid():
    """Functions of the symbols (of first symbols of a text: from 8 on) closed under composition: tables of the
    functions' values, of composition, and of where slices begin."""
    gens = [tuple(_step(s, q)[0] for q in range(8)) for s in range(8)]
    gens += [(g[CLOSED],) * 8 for g in gens]
    funcs: dict[tuple, int] = {}
    for g in gens:
        funcs.setdefault(g, len(funcs))
    todo = list(funcs)
    while todo:
        f = todo.pop()
        for g in gens:
            c = tuple(g[x] for x in f)
            if c not in funcs:
                funcs[c] = len(funcs)
                todo.append(c)
    values = np.array(list(funcs), np.uint8)
    compose = np.zeros((len(funcs), len(funcs)), np.int16)
    for f, i in funcs.items():
        for g, j in funcs.items():
            compose[i, j] = funcs[tuple(g[x] for x in f)]
    begins = np.array([[_step(s % 8, CLOSED if s >= 8 else q)[1] for q in range(8)] for s in range(16)])
    return np.array([funcs[g] for g in gens], np.int16), values, compose, begins


OF_SYMBOL, VALUES, COMPOSE, BEGINS = _monoid()
_classes: np.ndarray | None = None


def classes() -> np.ndarray:
    """The class of each code point: LETTER, NUMBER, OTHER, LAST_SPACE for the space, LAST_WS for other white space."""
    global _classes
    if _classes is None:
        t = np.full(0x110000, OTHER, np.uint8)
        for c in range(0x110000):
            k = unicodedata.category(chr(c))[0]
            if k in "LN":
                t[c] = LETTER if k == "L" else NUMBER
        t[WHITE] = LAST_WS
        t[32] = LAST_SPACE
        _classes = t
    return _classes


def symbols(cp: np.ndarray, first: np.ndarray) -> np.ndarray:
    """Symbols of code points; `first` marks the first code point of each text."""
    c = classes()[cp]
    end = np.append(first[1:], True)
    c1, c2 = np.append(cp[1:], 0), np.append(cp[2:], [0, 0])[: len(cp)]
    end1 = end | np.append(end[1:], True)
    ws = c >= LAST_SPACE
    s = c.copy()
    s[ws & (end | np.append(ws[1:], False))] = INNER_WS
    apos = (cp == 39) & ~end
    s[apos & np.isin(c1, [115, 116, 109, 100])] = APOS2
    three = ((c1 == 114) & (c2 == 101)) | ((c1 == 118) & (c2 == 101)) | ((c1 == 108) & (c2 == 108))
    s[apos & ~end1 & three] = APOS3
    return s + np.uint8(8) * first


def scan(f: np.ndarray, block: int = 256) -> np.ndarray:
    """Inclusive prefix compositions of an array of function numbers."""
    n = len(f)
    if n <= block:
        out = f.copy()
        for i in range(1, n):
            out[i] = COMPOSE[out[i - 1], f[i]]
        return out
    k = -(-n // block)
    p = np.ascontiguousarray(np.append(f, np.zeros(k * block - n, f.dtype)).reshape(k, block).T)
    flat, m = COMPOSE.ravel(), np.int32(len(COMPOSE))
    for j in range(1, block):
        p[j] = flat[p[j - 1] * m + p[j]]
    if k > 1:
        before = scan(p[-1].copy(), block)[:-1]
        p[:, 1:] = flat[before * m + p[:, 1:]]
    return p.T.ravel()[:n]


def slices(texts: list[str]) -> tuple[bytes, np.ndarray, np.ndarray]:
    """The texts' UTF-8 bytes, the byte offsets at which slices begin, and each text's byte offset (one more at the end)."""
    whole = "".join(texts)
    cp = np.frombuffer(whole.encode("utf-32-le"), np.uint32)
    sizes = np.array([len(t) for t in texts])
    first = np.zeros(len(cp), bool)
    at = np.cumsum(sizes) - sizes
    first[at[sizes > 0]] = True
    width = np.uint8(1) + (cp > 0x7F) + (cp > 0x7FF) + (cp > 0xFFFF)
    byte = np.concatenate([[0], np.cumsum(width, dtype=np.int64)])
    text_at = byte[np.append(at, len(cp))]
    if not len(cp):
        return b"", np.zeros(0, np.int64), text_at
    s = symbols(cp, first)
    after = VALUES[scan(OF_SYMBOL[s].astype(np.int32)), CLOSED]
    before = np.concatenate([[np.uint8(CLOSED)], after[:-1]])
    return whole.encode(), byte[np.flatnonzero(BEGINS[s, before])], text_at


class ByteBPE:
    """Encoder and decoder of a rank file. The cache stops growing at `most` slices."""

    def __init__(self, path: str, most: int = 500_000):
        with open(path, "rb") as f:
            self.ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, f)}
        self.tokens = {i: t for t, i in self.ranks.items()}
        self.most, self.cache = most, {}

    def merge(self, piece: bytes) -> tuple[int, ...]:
        """Ids of one slice: the adjacent pair of least rank, leftmost first, is joined until none is known."""
        ranks = self.ranks
        if piece in ranks:
            return (ranks[piece],)
        if len(piece) > 96:
            return self._merge_long(piece)
        parts = [piece[i : i + 1] for i in range(len(piece))]
        get = ranks.get
        pair = [get(parts[i] + parts[i + 1], 1 << 40) for i in range(len(parts) - 1)]
        while pair:
            low = min(pair)
            if low == 1 << 40:
                break
            i = pair.index(low)
            parts[i] += parts.pop(i + 1)
            pair.pop(i)
            if i < len(pair):
                pair[i] = get(parts[i] + parts[i + 1], 1 << 40)
            if i:
                pair[i - 1] = get(parts[i - 1] + parts[i], 1 << 40)
        return tuple([ranks[p] for p in parts])

    def _merge_long(self, piece: bytes) -> tuple[int, ...]:
        """The same with a heap over linked parts: n log n for slices of any length."""
        n, ranks = len(piece), self.ranks
        end, nxt, prev = list(range(1, n + 1)), list(range(1, n + 1)), list(range(-1, n - 1))
        alive = [True] * n

        def look(i):
            j = nxt[i]
            if j < n and (r := ranks.get(piece[i : end[j]])) is not None:
                heapq.heappush(heap, (r, i, end[j]))

        heap: list[tuple[int, int, int]] = []
        for i in range(n - 1):
            look(i)
        while heap:
            _, i, stop = heapq.heappop(heap)
            if not alive[i] or nxt[i] >= n or end[nxt[i]] != stop:
                continue
            j = nxt[i]
            alive[j], end[i], nxt[i] = False, end[j], nxt[j]
            if nxt[i] < n:
                prev[nxt[i]] = i
            look(i)
            if prev[i] >= 0:
                look(prev[i])
        return tuple([ranks[piece[i : end[i]]] for i in range(n) if alive[i]])

    def encode_slices(self, texts: list[str]) -> list[tuple[list[int], list[int], list[int]]]:
        """Of each text: its ids, the byte offset at which each slice begins (and the text's length), and the number of ids
        before each slice (and of all)."""
        data, begin, text_at = slices(texts)
        get, out = self.cache.get, []
        cuts = np.searchsorted(begin, text_at)
        b = begin.tolist()
        b.append(len(data))
        for i in range(len(texts)):
            lo, hi = cuts[i], cuts[i + 1]
            pieces = [data[x:y] for x, y in zip(b[lo:hi], b[lo + 1 : hi + 1])]
            got = list(map(get, pieces))
            if None in got:
                for k, x in enumerate(got):
                    if x is None:
                        got[k] = ids = self.merge(pieces[k])
                        if len(self.cache) < self.most:
                            self.cache[pieces[k]] = ids
            first = int(text_at[i])
            out.append((list(chain.from_iterable(got)), [x - first for x in b[lo:hi]] + [int(text_at[i + 1]) - first], [0, *accumulate(map(len, got))]))
        return out

    def encode(self, texts: list[str]) -> list[list[int]]:
        return [ids for ids, _, _ in self.encode_slices(texts)]

    def decode(self, ids: list[int], begins: list[int] | None = None, firsts: list[int] | None = None, lo: int = 0, hi: int | None = None) -> bytes:
        """Bytes lo to hi of a text: the slices that cover them are found by their offsets, and only their ids are decoded.
        Ids without offsets are decoded whole."""
        if begins is None:
            return b"".join(map(self.tokens.__getitem__, ids))[lo:hi]
        end = begins[-1]
        hi = end if hi is None else min(hi, end)
        if lo >= hi:
            return b""
        i, j = bisect_right(begins, lo) - 1, bisect_left(begins, hi)
        part = b"".join(map(self.tokens.__getitem__, ids[firsts[i] : firsts[j]]))
        if len(part) != begins[j] - begins[i]:
            raise ValueError("ids and offsets are of different texts")
        return part[lo - begins[i] : hi - begins[i]]


_coders: dict[str, ByteBPE] = {}


def coder(path: str) -> ByteBPE:
    """One per Python worker."""
    if path not in _coders:
        _coders.clear()
        _coders[path] = ByteBPE(path)
    return _coders[path]


def _round_trip(path: str):
    schema = pa.schema([("doc_id", pa.int64()), ("n_tokens", pa.int64()), ("ids_sha256", pa.string()), ("decoded_sha256", pa.string())])

    def run(batches):
        bpe = coder(path)
        word = {i: str(i) for i in bpe.tokens}
        for batch in batches:
            ids, texts = batch.column(0), batch.column(1)
            lo = 0
            while lo < len(texts):
                group, size = [], 0
                while lo + len(group) < len(texts) and (not group or size < 1 << 20):
                    group.append(texts[lo + len(group)].as_py() or "")
                    size += len(group[-1])
                enc = bpe.encode_slices(group)
                a = [hashlib.sha256(" ".join(map(word.__getitem__, e)).encode()).hexdigest() for e, _, _ in enc]
                b = [hashlib.sha256(bpe.decode(*e)).hexdigest() for e in enc]
                yield pa.RecordBatch.from_arrays([ids.slice(lo, len(group)), pa.array([len(e) for e, _, _ in enc], pa.int64()), pa.array(a, pa.string()), pa.array(b, pa.string())], schema=schema)
                lo += len(group)

    return run


ROW = pa.schema([("doc_id", pa.int64()), ("ids", pa.list_(pa.int32())), ("begins", pa.list_(pa.int64())), ("firsts", pa.list_(pa.int64()))])


def _encode_rows(path: str):
    def run(batches):
        bpe = coder(path)
        for batch in batches:
            for i, t in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                got = bpe.encode_slices([t or ""])[0]
                yield pa.RecordBatch.from_arrays([pa.array([x], f.type) for x, f in zip((i, *got), ROW, strict=True)], schema=ROW)

    return run


def _decode_rows(path: str):
    def run(batches):
        bpe = coder(path)
        for batch in batches:
            for r in batch.to_pylist():
                got = bpe.decode(r["ids"], r["begins"], r["firsts"], r["lo"], r["hi"])
                yield pa.RecordBatch.from_arrays([pa.array([r["doc_id"]], pa.int64()), pa.array([got], pa.binary())], names=["doc_id", "bytes"])

    return run


def encode_documents(docs: DataFrame, path: str, text: str = "text", key: str = "doc_id") -> DataFrame:
    """doc_id, ids, begins (byte offset of each slice, and the text's length), firsts (ids before each slice, and of all)."""
    ship(docs.sparkSession)
    return docs.select(F.col(key).cast("long").alias("doc_id"), F.col(text).alias("text")).mapInArrow(_encode_rows(path), "doc_id long, ids array<int>, begins array<long>, firsts array<long>")


def decode_documents(coded: DataFrame, path: str, lo: int = 0, hi: int | None = None) -> DataFrame:
    """doc_id, bytes (lo to hi of each text) from the columns of `encode_documents`."""
    ship(coded.sparkSession)
    return coded.select("doc_id", "ids", "begins", "firsts", F.lit(lo).cast("long").alias("lo"), F.lit(hi).cast("long").alias("hi")).mapInArrow(_decode_rows(path), "doc_id long, bytes binary")


def round_trip(docs: DataFrame, path: str, text: str = "text", key: str = "doc_id") -> DataFrame:
    """doc_id, n_tokens, ids_sha256, decoded_sha256: encoded whole, then decoded from the ids by the slices' offsets."""
    ship(docs.sparkSession)
    return docs.select(F.col(key).cast("long").alias("doc_id"), F.col(text).alias("text")).mapInArrow(_round_trip(path), "doc_id long, n_tokens long, ids_sha256 string, decoded_sha256 string")


def op4_byte_bpe(spark, sf_dir: str) -> DataFrame:
    import public_tokenizers

    return round_trip(documents(spark, sf_dir), public_tokenizers.path("byte_bpe_50k.tiktoken"))
