"""Vectorised text primitives on NumPy: word boundaries and word hashes of a whole Arrow batch at once."""

from __future__ import annotations

import json
import re
from array import array
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

_SEP = np.zeros(256, bool)
_SEP[[9, 10, 11, 12, 13, 32]] = True
_LOWER = np.arange(256, dtype=np.uint8)
_LOWER[65:91] += 32
_BASE = 0x9E3779B97F4A7C15 | 1
_pw = np.ones(1, np.uint64)


def _powers(n: int) -> np.ndarray:
    """Powers of the hash base modulo 2^64, kept and grown by need."""
    global _pw
    if len(_pw) < n:
        x = np.full(max(n, 2 * len(_pw)), _BASE, np.uint64)
        x[0] = 1
        _pw = np.multiply.accumulate(x)
    return _pw[:n]


def mix(h: np.ndarray) -> np.ndarray:
    """A 64-bit finaliser: spreads every input bit over the word."""
    h = h.astype(np.uint64, copy=True)
    h ^= h >> np.uint64(30)
    h *= np.uint64(0xBF58476D1CE4E5B9)
    h ^= h >> np.uint64(27)
    h *= np.uint64(0x94D049BB133111EB)
    h ^= h >> np.uint64(31)
    return h


def groups_of_rows(batch: pa.RecordBatch, column: str, most: int = 1 << 19) -> Iterator[tuple[int, int, list[bytes]]]:
    """Rows of a batch in runs of about `most` text bytes, at least one row each: (first, last, texts); null is empty."""
    col = batch.column(batch.schema.get_field_index(column))
    values = [x or b"" for x in col.cast(pa.binary()).to_pylist()]
    lo = size = 0
    for i, v in enumerate(values):
        if size and size + len(v) > most:
            yield lo, i, values[lo:i]
            lo, size = i, 0
        size += len(v)
    if lo < len(values):
        yield lo, len(values), values[lo:]


def words(texts: list[bytes], lower: bool = True, block: int = 1 << 20, separators: np.ndarray = _SEP) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """All words of the texts (between `separators`, by default ASCII white space, and the line feeds that join texts): row, start byte in its text, length, 64-bit hash.

    Works through blocks cut after a separator, so memory follows the block (or the longest word), not the text."""
    ends = np.cumsum([len(t) + 1 for t in texts])
    begins = np.concatenate([[0], ends[:-1]]).astype(np.int64)
    data = np.frombuffer(b"\n".join(texts) + b"\n", np.uint8)
    out: list[tuple[np.ndarray, np.ndarray, np.ndarray]] = []
    lo = 0
    while lo < len(data):
        hi = min(len(data), lo + block)
        while hi < len(data) and not separators[data[hi - 1]]:
            stop = np.flatnonzero(separators[data[hi : hi + block]])
            hi = hi + int(stop[0]) + 1 if len(stop) else min(len(data), hi + block)
        part = data[lo:hi]
        sep = separators[part]
        edge = np.flatnonzero(np.diff(np.concatenate([[True], sep, [True]]).view(np.int8)))
        s, e = edge[::2], edge[1::2]
        if len(s):
            n = e - s
            at = np.flatnonzero(~sep)
            rel = np.arange(len(at)) - np.repeat(np.cumsum(n) - n, n)
            b = (_LOWER[part[at]] if lower else part[at]).astype(np.uint64) + np.uint64(1)
            h = np.add.reduceat(b * _powers(int(n.max()))[rel], np.cumsum(n) - n)
            out.append((s + lo, n, mix(h + n.astype(np.uint64))))
        lo = hi
    if not out:
        z = np.zeros(0, np.int64)
        return z, z, z, np.zeros(0, np.uint64)
    start, n, h = (np.concatenate(x) for x in zip(*out, strict=True))
    row = np.searchsorted(ends, start, side="right")
    return row, start - begins[row], n, h


def bounds(row: np.ndarray, rows: int) -> np.ndarray:
    """Of each row, where its words begin in arrays ordered by row; one more at the end."""
    return np.searchsorted(row, np.arange(rows + 1))


def _parts(strings: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """The bytes of a string or binary column without nulls, and where each value begins in them; one more at the end."""
    offset = np.frombuffer(strings.buffers()[1], np.int32)[strings.offset : strings.offset + len(strings) + 1]
    data = np.frombuffer(strings.buffers()[2] or b"", np.uint8)[offset[0] : offset[-1]]
    return data, offset - offset[0]


def _joined(values: pa.Array, ends: np.ndarray) -> pa.Array:
    """The values up to each of `ends`, joined to one binary each."""
    data, offset = _parts(values)
    return pa.Array.from_buffers(pa.binary(), len(ends), [None, pa.py_buffer(offset[np.concatenate([[0], ends])].astype(np.int32).tobytes()), pa.py_buffer(data)])


class Merges:
    """Byte-pair merges of many short words at once: in each, the pair of lowest rank, the leftmost of equal ones, until none is left.

    Words with equally many symbols are the columns of one matrix; a merge moves a word to the matrix with one symbol less."""

    LONGEST, NONE, BITS = 64, 1 << 30, 18  # ranks are kept times LONGEST, so that a position can be added

    def __init__(self, vocab: dict[str, int], merges: list, suffix: str, bytes_as: dict[int, str]):
        pairs = [m.split(" ") if isinstance(m, str) else m for m in merges]
        self.result = np.array([vocab[a + b] for a, b in pairs], np.uint16)
        self.slots, self.ranks = np.full(1 << self.BITS, 0xFFFFFFFF, np.uint32), np.full(1 << self.BITS, self.NONE, np.int32)
        keys = [vocab[a] << 16 | vocab[b] for a, b in pairs]
        for rank, (key, slot) in enumerate(zip(keys, self._slot(np.array(keys, np.uint32)).tolist(), strict=True)):
            while self.slots[slot] not in (key, 0xFFFFFFFF):
                slot = (slot + 1) % len(self.slots)
            self.slots[slot], self.ranks[slot] = key, rank * self.LONGEST
        # bytes without a character in `bytes_as` occur in no word given to `ids`
        self.inner, self.last = (np.array([vocab[bytes_as[i] + end] if i in bytes_as else 0 for i in range(256)], np.uint16) for end in ("", suffix))
        a = np.repeat(self.inner, 256)
        self.inner_pairs, self.last_pairs = self._rank(a, np.tile(self.inner, 256)), self._rank(a, np.tile(self.last, 256))

    @classmethod
    def _slot(cls, key: np.ndarray) -> np.ndarray:
        return (key * np.uint32(0x9E3779B1)) >> np.uint32(32 - cls.BITS)

    def _rank(self, left: np.ndarray, right: np.ndarray) -> np.ndarray:
        key = left.astype(np.uint32) << np.uint32(16) | right
        slot = self._slot(key)
        found = self.slots[slot]
        out = np.where(found == key, self.ranks[slot], self.NONE)
        open_ = np.flatnonzero((found != key) & (found != 0xFFFFFFFF))
        while len(open_):
            slot[open_] = (slot[open_] + 1) % len(self.slots)
            found = self.slots[slot[open_]]
            hit = found == key[open_]
            out[open_[hit]] = self.ranks[slot[open_[hit]]]
            open_ = open_[~hit & (found != 0xFFFFFFFF)]
        return out

    def ids(self, data: np.ndarray, start: np.ndarray, size: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Ids of the words data[start : start + size], each of 1 to LONGEST bytes: all ids in order, and how many a word has."""
        done = []
        by_size = np.argsort(size, kind="stable")
        edge = np.searchsorted(size[by_size], np.arange(self.LONGEST + 2))
        word, sym, rank = np.zeros(0, np.int64), np.zeros((0, 0), np.uint16), np.zeros((0, 0), np.int32)
        for n in range(int(size.max(initial=0)), 0, -1):
            new = by_size[edge[n] : edge[n + 1]]
            if len(new):
                text = data[start[new] + np.arange(n)[:, None]]
                new_sym = self.inner[text]
                new_sym[-1] = self.last[text[-1]]
                pair = text[:-1].astype(np.int32) << 8 | text[1:]
                new_rank = self.inner_pairs[pair]
                if n > 1:
                    new_rank[-1] = self.last_pairs[pair[-1]]
                if len(word):
                    word, sym, rank = np.concatenate([word, new]), np.concatenate([sym, new_sym], axis=1), np.concatenate([rank, new_rank], axis=1)
                else:
                    word, sym, rank = new, new_sym, new_rank
            if n == 1:
                done.append((word, sym))
                break
            best = (rank + np.arange(n - 1, dtype=np.int32)[:, None]).min(axis=0)
            more = best < self.NONE
            if not more.all():
                left, more = np.flatnonzero(~more), np.flatnonzero(more)
                done.append((word[left], sym.take(left, axis=1)))
                word, sym, rank, best = word[more], sym.take(more, axis=1), rank.take(more, axis=1), best[more]
            at, merged = best % self.LONGEST, self.result[best // self.LONGEST]
            row = np.arange(n - 1, dtype=np.int32)[:, None]
            sym = np.where(row <= at, sym[:-1], sym[1:])
            rank = np.where(row[:-1] < at, rank[:-1], rank[1:])
            flat, flat_rank, many = sym.reshape(-1), rank.reshape(-1), len(word)
            col = at * np.int64(many) + np.arange(many)
            flat[col] = merged
            left, right = np.flatnonzero(at > 0), np.flatnonzero(at < n - 2)
            flat_rank[col[left] - many] = self._rank(flat[col[left] - many], merged[left])
            flat_rank[col[right]] = self._rank(merged[right], flat[col[right] + many])
        many = np.zeros(len(size), np.int64)
        for word, sym in done:
            many[word] = len(sym)
        first = np.cumsum(many) - many
        out = np.zeros(int(many.sum()), np.uint16)
        for word, sym in done:
            out[first[word] + np.arange(len(sym))[:, None]] = sym
        return out, many


class WordEncoder:
    """Ids of a `tokenizers` vocabulary whose pre-tokeniser drops white space: text between spaces is encoded apart and cached.

    A text that holds a special token's opening, or anything the cached path can't split the same way, goes to the library whole.
    The caches stop growing at `most` entries: memory is bounded, rarer words are encoded again. `columns` encodes many texts
    at once and caches only what goes to the library: each different word of them is split and merged once, in arrays."""

    def __init__(self, path: str, most: int = 400_000):
        import regex
        from tokenizers import Tokenizer
        from tokenizers.pre_tokenizers import ByteLevel

        self.lib = Tokenizer.from_file(path)
        self.lib.no_truncation()
        self.lib.no_padding()
        self.wide = self.lib.get_vocab_size() > 65_536
        self.dtype = np.dtype("<u4" if self.wide else "<u2")
        self.special = [t.content for t in self.lib.get_added_tokens_decoder().values()]
        self.most, self.chunks, self.pieces = most, {}, {}
        self.chunks[""] = b""
        self.code = "I" if self.wide else "H"
        self.pre = self.lib.pre_tokenizer
        self.norm = self.lib.normalizer
        self.model = self.lib.model
        with open(path) as f:
            file = json.load(f)
        self.fast = self._known(file)
        #: The vocabulary file's own split pattern.
        self.split = regex.compile(r"'s|'t|'re|'ve|'m|'ll|'d|[\p{L}]+|[\p{N}]|[^\s\p{L}\p{N}]+").findall
        self.split_ascii = re.compile(r"'s|'t|'re|'ve|'m|'ll|'d|[a-z]+|[0-9]|[^\t-\r a-z0-9]+").findall  # `re` takes U+001C to U+001F for white space, the library doesn't
        #: The same classes below U+0250, where `re` is faster; and the letters that stand for bytes.
        latin = [chr(i) for i in range(128, 0x250)]
        letters, numbers = ("".join(c for c in latin if regex.match(x, c)) for x in (r"\p{L}", r"\p{N}"))
        latin_pattern = rf"'s|'t|'re|'ve|'m|'ll|'d|[a-zA-Z{letters}]+|[0-9{numbers}]|[^\t-\r \x85\xa0a-zA-Z0-9{letters}{numbers}]+"
        self.split_latin = re.compile(latin_pattern).findall
        self.split_lines = re.compile(latin_pattern + r"|\n").findall
        byte_level = ByteLevel(add_prefix_space=False, use_regex=False).pre_tokenize_str
        # characters below 128 are one byte each; the first characters of 64 two-byte leads give the rest
        self.bytes_as = {i: byte_level(chr(i))[0][0] for i in range(128)}
        for i in range(0x80, 0x800):
            for byte, c in zip(chr(i).encode(), byte_level(chr(i))[0][0], strict=True):
                self.bytes_as[byte] = c
        self.merges = self._merges(file["model"]) if self.fast and not self.wide else None

    def _merges(self, model: dict) -> Merges | None:
        """The file's merges, where they are plain and each byte has its own symbols."""
        odd = ("dropout", "unk_token", "continuing_subword_prefix", "fuse_unk", "byte_fallback", "ignore_merges")
        vocab, suffix = model["vocab"], model.get("end_of_word_suffix") or ""
        if model["type"] != "BPE" or any(model.get(k) for k in odd) or not all(c + end in vocab for c in self.bytes_as.values() for end in ("", suffix)):
            return None
        return Merges(vocab, model["merges"], suffix, self.bytes_as)

    @staticmethod
    def _known(x: dict) -> bool:
        """Whether the file normalises and splits in the one way that the fast path repeats."""
        kinds = [n["type"] for n in (x["normalizer"] or {}).get("normalizers", [])]
        pres = (x["pre_tokenizer"] or {}).get("pretokenizers", [])
        return kinds == ["NFC", "Replace", "Lowercase"] and [p["type"] for p in pres] == ["Split", "ByteLevel"] and pres[0]["pattern"] == {"Regex": r"'s|'t|'re|'ve|'m|'ll|'d|[\p{L}]+|[\p{N}]|[^\s\p{L}\p{N}]+"}

    def _piece(self, p: str) -> bytes:
        got = self.pieces.get(p)
        if got is None:
            # a printable ASCII character stands for its own byte
            mapped = p if p.isascii() and p.isprintable() else p.encode().decode("latin-1").translate(self.bytes_as)
            got = array(self.code, [t.id for t in self.model.tokenize(mapped)]).tobytes()
            if len(self.pieces) < self.most:
                self.pieces[p] = got
        return got

    def _chunk(self, c: str) -> bytes:
        if not self.fast:
            got = array(self.code, self.lib.encode(c, add_special_tokens=False).ids).tobytes()
        elif c.isascii():
            c_ = c.lower()
            got = self._piece(c_) if c_.isalpha() else b"".join([self._piece(p) for p in self.split_ascii(c_)])
        elif max(c) < "\u0250":  # no combining marks: already in composed form
            c_ = c.lower()
            got = b"".join([self._piece(p) for p in (self.split_latin if max(c_) < "\u0250" else self.split)(c_)])
        else:
            got = array(self.code, self.lib.encode(c, add_special_tokens=False).ids).tobytes()
        if len(self.chunks) < self.most:
            self.chunks[c] = got
        return got

    def ids(self, text: str) -> bytes:
        """Little-endian ids of the whole text, without special tokens."""
        for s in self.special:
            if s in text:
                return array(self.code, self.lib.encode(text, add_special_tokens=False).ids).tobytes()
        chunks = text.replace("\n", " ").split(" ")
        out = list(map(self.chunks.get, chunks))
        if None in out:
            out = [self._chunk(c) if x is None else x for c, x in zip(chunks, out)]
        return b"".join(out)

    def columns(self, texts: pa.Array, end: bytes, most: int = 1 << 25) -> pa.Array:
        """`ids` of each text and `end` behind them, as one binary column; null is empty. Works through runs of about `most` text bytes."""
        texts = pc.fill_null(texts.cast(pa.string()), "")
        if self.merges is None:
            return pa.array([self.ids(t) + end for t in texts.to_pylist()], pa.binary())
        if not len(texts):
            return pa.array([], pa.binary())
        run = np.cumsum(pc.binary_length(texts).to_numpy(zero_copy_only=False).astype(np.int64)) // most
        edge = np.concatenate([[0], np.flatnonzero(np.diff(run)) + 1, [len(texts)]])
        return pa.concat_arrays([self._run(texts.slice(lo, hi - lo), end) for lo, hi in zip(edge[:-1], edge[1:], strict=True)])

    def _run(self, texts: pa.Array, end: bytes) -> pa.Array:
        whole = np.zeros(len(texts), bool)  # those that hold a special token's name
        data = _parts(texts)[0].tobytes()
        for s in self.special:
            if s.encode() in data:
                whole |= pc.match_substring(texts, s).to_numpy(zero_copy_only=False)
        named = np.flatnonzero(whole)
        ends = [array(self.code, self.lib.encode(texts[int(i)].as_py(), add_special_tokens=False).ids).tobytes() + end for i in named]
        if len(named):
            texts = pc.if_else(pa.array(whole), "", texts)
        # a space more: each text's last word is empty and stands for what ends it
        chunks = pc.split_pattern(pc.binary_join_element_wise(pc.replace_substring(texts, "\n", " "), "", " "), " ")
        words = chunks.flatten().dictionary_encode()
        at = np.cumsum(pc.list_value_length(chunks).to_numpy(zero_copy_only=False).astype(np.int64))
        code = words.indices.to_numpy(zero_copy_only=False).copy()
        code[at - 1] = len(words.dictionary)
        code[at[named] - 1] = len(words.dictionary) + 1 + np.arange(len(named))
        known = pa.concat_arrays([self._different(words.dictionary), pa.array([end, *ends], pa.binary())])
        return _joined(known.take(pa.array(code)), at)

    def _different(self, words: pa.Array) -> pa.Array:
        """Ids of each of these words."""
        lines = pc.binary_join_element_wise(words, "", "\n")
        data, offset = _parts(lines)
        # leads of U+0180 and above, and U+0130: below, small letters stay below
        high = np.flatnonzero(data >= 0xC4)
        high = high[(data[high] >= 0xC6) | (data[high] == 0xC4) & (data[high + 1] == 0xB0)]
        apart = np.unique(np.searchsorted(offset, high, side="right") - 1)
        if len(apart):
            plain = np.ones(len(words), bool)
            plain[apart] = False
            data = _parts(pc.if_else(pa.array(plain), lines, "\n"))[0]
        pieces = pa.array(self.split_lines(data.tobytes().decode().lower()), pa.string()).dictionary_encode()
        data, offset = _parts(pieces.dictionary)
        start, size = offset[:-1].astype(np.int64), np.diff(offset)
        line = pc.index(pieces.dictionary, "\n").as_py()
        rest = size > Merges.LONGEST
        rest[line] = True
        own = np.flatnonzero(~rest)
        done = [self.merges.ids(data, start[some], size[some]) for some in np.split(own, range(1 << 16, len(own), 1 << 16))]
        ends = np.concatenate([[0], np.cumsum(np.concatenate([many for _, many in done]) * 2)]).astype(np.int32)
        by_merges = pa.Array.from_buffers(pa.binary(), len(own), [None, pa.py_buffer(ends.tobytes()), pa.py_buffer(b"".join(ids.astype(self.dtype).tobytes() for ids, _ in done))])
        rest = np.flatnonzero(rest)
        by_library = pa.array([b"" if i == line else self._piece(pieces.dictionary[int(i)].as_py()) for i in rest], pa.binary())
        code = np.zeros(len(size), np.int64)
        code[own], code[rest] = np.arange(len(own)), len(own) + np.arange(len(rest))
        of_word = pieces.indices.to_numpy(zero_copy_only=False)
        out = _joined(pa.concat_arrays([by_merges, by_library]).take(pa.array(code[of_word])), np.flatnonzero(of_word == line) + 1)
        if len(apart):
            code = np.arange(len(words))
            code[apart] = len(words) + np.arange(len(apart))
            out = pa.concat_arrays([out, pa.array([self.chunks.get(w) or self._chunk(w) for w in words.take(pa.array(apart)).to_pylist()], pa.binary())]).take(pa.array(code))
        return out


_encoders: dict[str, WordEncoder] = {}


def release() -> None:
    """Free the caches that earlier operators left in this Python worker, which Spark reuses."""
    import gc

    if _encoders:
        _encoders.clear()
        gc.collect()


def word_encoder(path: str) -> WordEncoder:
    """One encoder per Python worker, kept between tasks."""
    if path not in _encoders:
        _encoders.clear()
        _encoders[path] = WordEncoder(path)
    return _encoders[path]
