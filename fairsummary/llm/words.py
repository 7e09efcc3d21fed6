"""Vectorised word finding and hashing over UTF-8 bytes.

A word is a maximal run of bytes other than space and 0x09-0x0D; in UTF-8 no
multi-byte character contains those bytes, so byte positions are safe cuts.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa

_SEP = np.zeros(256, bool)
_SEP[[0x20, 0x09, 0x0A, 0x0B, 0x0C, 0x0D]] = True

_BASES = (0x9E3779B97F4A7C15, 0xD1342543DE82EF95)
_powers: dict[int, tuple[np.ndarray, np.ndarray]] = {}


def mix(x: np.ndarray, salt: int = 0) -> np.ndarray:
    """Full-avalanche mixing of 64-bit words (the splitmix finaliser)."""
    x = x + np.uint64((0x9E3779B97F4A7C15 * (salt + 1)) & (2**64 - 1))
    x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


_BYTE = mix(np.arange(256, dtype=np.uint64), 7)


def _power(base: int, n: int) -> tuple[np.ndarray, np.ndarray]:
    """Powers of an odd base and of its inverse modulo 2**64, grown on demand."""
    have = _powers.get(base)
    if have is None or len(have[0]) < n:
        size = max(1 << 20, 1 << (n - 1).bit_length())
        fwd = np.full(size, base, np.uint64)
        fwd[0] = 1
        back = np.full(size, pow(base, -1, 2**64), np.uint64)
        back[0] = 1
        with np.errstate(over="ignore"):
            have = _powers[base] = (np.cumprod(fwd), np.cumprod(back))
    return have


def range_hash(values: np.ndarray, starts: np.ndarray, ends: np.ndarray, which: int = 0) -> np.ndarray:
    """Polynomial hash of values[start:end] for every range, independent of the position, then mixed."""
    fwd, back = _power(_BASES[which], len(values) + 1)
    total = np.zeros(len(values) + 1, np.uint64)
    np.cumsum(values * fwd[: len(values)], out=total[1:])
    return mix((total[ends] - total[starts]) * back[starts], which)


@dataclass
class Words:
    """Words of a batch of documents, in order; ``first`` and ``count`` are per document."""

    data: np.ndarray
    start: np.ndarray
    end: np.ndarray
    first: np.ndarray
    count: np.ndarray

    @property
    def doc(self) -> np.ndarray:
        return np.repeat(np.arange(len(self.count)), self.count)

    @property
    def index(self) -> np.ndarray:
        return np.arange(len(self.start)) - np.repeat(self.first, self.count)

    def hashes(self, which: int = 0) -> np.ndarray:
        return range_hash(_BYTE[self.data], self.start, self.end, which)


def raw_bytes(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """Value bytes of a string column and the n+1 offsets into them; nulls are empty."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    column = column.cast(pa.large_string()) if column.type != pa.large_string() else column
    if column.null_count:
        column = column.fill_null("")
    _, offs, data = column.buffers()
    offsets = np.frombuffer(offs, np.int64, len(column) + 1, column.offset * 8)
    body = np.frombuffer(data, np.uint8) if data is not None and data.size else np.zeros(0, np.uint8)
    return body[offsets[0] : offsets[-1]], offsets - offsets[0]


def find_words(column: pa.Array) -> Words:
    data, offsets = raw_bytes(column)
    n = len(offsets) - 1
    if not len(data):
        zero = np.zeros(0, np.int64)
        return Words(data, zero, zero, np.zeros(n, np.int64), np.zeros(n, np.int64))
    word = ~_SEP[data]
    cut = np.zeros(len(data) + 1, bool)  # a document starts here
    cut[offsets] = True
    begin = word.copy()
    begin[1:] &= ~word[:-1] | cut[1:-1]
    stop = word.copy()
    stop[:-1] &= ~word[1:] | cut[1:-1]
    start, end = np.flatnonzero(begin), np.flatnonzero(stop) + 1
    bounds = np.searchsorted(start, offsets)
    return Words(data, start, end, bounds[:-1], np.diff(bounds))


class WordTable:
    """Id lists of words, looked up for whole batches at once.

    Words are found by 64 bits of hash and checked by another 32 and their
    length in an open-addressing table; the lists lie end to end in one array.
    Once ``limit`` words are held, further ones are worked out batch by batch.
    """

    def __init__(self, work, limit: int):
        self.work, self.limit = work, limit
        size = 1 << (4 * limit - 1).bit_length()
        self.mask = np.uint64(size - 1)
        self.key, self.check, self.at = np.zeros(size, np.uint64), np.zeros(size, np.uint64), np.full(size, -1, np.int32)
        self.flat, self.first, self.size = np.zeros(0, np.uint32), np.zeros(0, np.int64), np.zeros(0, np.int64)

    def _find(self, key: np.ndarray, check: np.ndarray) -> np.ndarray:
        """Number of each word, or -1."""
        out = np.full(len(key), -1, np.int64)
        left, slot = np.arange(len(key)), (key & self.mask).astype(np.int64)
        while len(left):
            at = self.at[slot]
            hit = (at >= 0) & (self.key[slot] == key[left]) & (self.check[slot] == check[left])
            out[left[hit]] = at[hit]
            go = (at >= 0) & ~hit
            left, slot = left[go], (slot[go] + 1) & int(self.mask)
        return out

    def _insert(self, key: np.ndarray, check: np.ndarray, number: np.ndarray) -> None:
        left, slot = np.arange(len(key)), (key & self.mask).astype(np.int64)
        while len(left):
            free = self.at[slot] < 0
            self.at[slot[free]] = number[left[free]]  # of several on one slot the last stays
            won = free & (self.at[slot] == number[left])
            self.key[slot[won]], self.check[slot[won]] = key[left[won]], check[left[won]]
            left, slot = left[~won], (slot[~won] + 1) & int(self.mask)

    def __call__(self, words: Words) -> tuple[np.ndarray, np.ndarray]:
        """Ids of all words in order, and the number of ids of each word."""
        key = words.hashes()
        check = (words.hashes(1) & np.uint64(0xFFFFFFFF00000000)) | (words.end - words.start).astype(np.uint64) & np.uint64(0xFFFFFFFF)
        at = self._find(key, check)
        miss = np.flatnonzero(at < 0)
        flat, first, size = self.flat, self.first, self.size
        if len(miss):
            _, one, which = np.unique(key[miss], return_index=True, return_inverse=True)
            new = miss[one]
            body = words.data.tobytes()
            lists = self.work([body[s:e].decode("utf-8", "surrogatepass") for s, e in zip(words.start[new].tolist(), words.end[new].tolist())])
            own = np.array([len(x) // 4 for x in lists], np.int64)
            held = len(size)
            flat = np.concatenate([flat, np.frombuffer(b"".join(lists), np.uint32)])
            size = np.concatenate([size, own])
            first = np.concatenate([first, len(self.flat) + np.cumsum(own) - own])
            at[miss] = held + which
            if held + len(new) <= self.limit:
                self._insert(key[new], check[new], np.arange(held, held + len(new), dtype=np.int32))
                self.flat, self.first, self.size = flat, first, size
        n = size[at]
        return flat[np.repeat(first[at] - (np.cumsum(n) - n), n) + np.arange(int(n.sum()))], n
