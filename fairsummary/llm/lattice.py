"""Sentence-piece encoding by a Viterbi search over whole batches of equal-length words, and decoding.

The search is the one of unigram vocabularies: among all ways to cut a word
into pieces, the one with the largest sum of scores; of equal sums the one
whose last piece starts first.  Characters outside the vocabulary fall back to
their UTF-8 bytes.
"""

from __future__ import annotations

import hashlib
import re
import zlib
from collections import defaultdict
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from .common import MEMORY, WORD_BYTES, Memory, extended, text_slices, texts_of
from .token_table import vocabulary
from .words import mix

MARK = "▁"
_SEGMENT = re.compile(f"{MARK}+[^{MARK}]*|[^{MARK}]+")
_BASE = np.uint64(0x9E3779B97F4A7C15)
_loaded: dict[str, "Lattice"] = {}
_encoders: dict[str, "Encoder"] = {}


class Lattice:
    """A vocabulary with scores, its sorted hash keys, and the batched search."""

    def __init__(self, pieces: list[str], scores: list[float], byte_ids: list[int], ids: list[int]):
        """``pieces`` are the ordinary ones, ``ids`` their ids; ``byte_ids`` has the id of each byte value."""
        order = np.argsort(keys := self._hash_all(pieces), kind="stable")
        self.keys, self.slot = keys[order], order
        if len(self.keys) and (self.keys[1:] == self.keys[:-1]).any():
            raise ValueError("two pieces share a hash key")
        self.pieces, self.ids = pieces, np.asarray(ids, np.int64)
        self.scores = np.asarray(scores, np.float64)[order] if pieces else np.zeros(0)
        self.longest = max(map(len, pieces), default=1)
        self.unknown = (min(scores) if scores else 0.0) - 10.0
        self.byte_ids = byte_ids
        self.flags = np.zeros(1 << 21, bool)  # of a hash's top bits: whether any key has them
        self.flags[(self.keys >> np.uint64(43)).astype(np.int64)] = True
        self.lengths = np.array(sorted({len(p) for p in pieces} | {1}, reverse=True))
        self.table = None
        self.bytes_of: dict[int, bytes] = {i: p.encode() for i, p in zip(ids, pieces)} | {i: bytes([v]) for v, i in enumerate(byte_ids)}

    @staticmethod
    def from_model(path: str) -> "Lattice":
        if path not in _loaded:
            import sentencepiece

            sp = sentencepiece.SentencePieceProcessor(model_file=path)
            n = sp.get_piece_size()
            ids = [i for i in range(n) if not (sp.is_control(i) or sp.is_unknown(i) or sp.is_byte(i) or sp.is_unused(i))]
            _loaded[path] = Lattice([sp.id_to_piece(i) for i in ids], [sp.get_score(i) for i in ids], [sp.piece_to_id(f"<0x{v:02X}>") for v in range(256)], ids)
        return _loaded[path]

    @staticmethod
    def _hash_all(pieces: list[str]) -> np.ndarray:
        out = np.zeros(len(pieces), np.uint64)
        by_length = defaultdict(list)
        for i, p in enumerate(pieces):
            by_length[len(p)].append(i)
        for n, at in by_length.items():
            codes = np.frombuffer("".join(pieces[i] for i in at).encode("utf-32-le"), "<u4").reshape(len(at), n)
            out[at] = _row_hash(codes)
        return out

    def encode_words(self, words: list[str]) -> list[bytes]:
        """Ids of each word as little-endian 32-bit integers; words of one length are searched side by side."""
        out = [b""] * len(words)
        by_length = defaultdict(list)
        for i, w in enumerate(words):
            if w:
                by_length[len(w)].append(i)
        for n, at in by_length.items():
            step = max(1, (1 << 17) // n)
            for lo in range(0, len(at), step):
                some = at[lo : lo + step]
                for i, ids in zip(some, self._search([words[i] for i in some], n)):
                    out[i] = ids
        return out

    def _search(self, words: list[str], n: int) -> list[bytes]:
        rows = len(words)
        codes = np.frombuffer("".join(words).encode("utf-32-le", "surrogatepass"), "<u4").reshape(rows, n)
        prefix, power = _prefixes(codes)
        best = np.full((n + 1, rows), -np.inf)
        best[0] = 0
        back = np.zeros((n + 1, rows), np.int32)
        piece = np.full((n + 1, rows), -1, np.int32)
        for end in range(1, n + 1):
            score, origin, used = best[end], back[end], piece[end]
            for size in self.lengths[self.lengths <= end].tolist():
                start = end - size
                h = _finish(prefix[end] - prefix[start] * power[size], size)
                at = np.flatnonzero(self.flags[(h >> np.uint64(43)).astype(np.int64)])
                slot = np.searchsorted(self.keys, h[at]) if len(at) else at
                found = self.keys[np.minimum(slot, len(self.keys) - 1)] == h[at] if len(at) else np.zeros(0, bool)
                at, slot = at[found], slot[found]
                if size == 1 and len(at) < rows:
                    rest = np.setdiff1d(np.arange(rows), at, assume_unique=True)
                    rest = rest[best[start][rest] + self.unknown > score[rest]]
                    score[rest], origin[rest], used[rest] = best[start][rest] + self.unknown, start, -1
                total = best[start][at] + self.scores[slot]
                better = total > score[at]
                at = at[better]
                score[at], origin[at], used[at] = total[better], start, slot[better]
        return self._trace(words, n, back, piece)

    def _trace(self, words: list[str], n: int, back: np.ndarray, piece: np.ndarray) -> list[bytes]:
        """Follow the backpointers of all words together; words with byte fallback are spelled one by one."""
        rows = len(words)
        every, end = np.arange(rows), np.full(rows, n)
        ids, size, plain = np.zeros((rows, n), "<u4"), np.zeros(rows, np.int64), np.ones(rows, bool)
        column = n
        while end.any():
            column -= 1
            on, slot = end > 0, piece[end, every]
            plain &= ~on | (slot >= 0)
            ids[:, column] = self.ids[self.slot[np.maximum(slot, 0)]] if len(self.ids) else 0
            size += on
            end = np.where(on, back[end, every], 0)
        # words of fewer pieces ended early: their ids fill the last columns
        body, width = ids.tobytes(), 4 * n
        out = [body[width * (r + 1) - 4 * k : width * (r + 1)] for r, k in enumerate(size.tolist())]
        for r in np.flatnonzero(~plain).tolist():
            spelled: list[int] = []
            end_r = n
            while end_r:
                start = int(back[end_r, r])
                if piece[end_r, r] >= 0:
                    spelled.append(int(self.ids[self.slot[piece[end_r, r]]]))
                else:
                    spelled.extend(self.byte_ids[v] for v in reversed(words[r][start:end_r].encode("utf-8", "surrogatepass")))
                end_r = start
            out[r] = np.array(spelled[::-1], "<u4").tobytes()
        if "".join(words) != self.spell(b"".join(out)).decode("utf-8", "surrogatepass"):
            raise ValueError("a substring shares a hash key with another piece")
        return out

    def spell(self, ids: bytes) -> bytes:
        """Bytes of ids, gathered from one table; ids without a spelling (control pieces) add nothing."""
        if self.table is None:
            top = max(self.bytes_of, default=0) + 1
            each = [self.bytes_of.get(i, b"") for i in range(top)]
            size = np.array([len(x) for x in each])
            self.table = np.frombuffer(b"".join(each) or b"\0", np.uint8), np.cumsum(size) - size, size
        flat, first, size = self.table
        at = np.frombuffer(ids, "<u4").astype(np.int64)
        at = at[at < len(size)]
        n = size[at]
        skip = np.cumsum(n) - n
        return flat[np.repeat(first[at] - skip, n) + np.arange(int(n.sum()))].tobytes()

    def decode(self, ids: bytes) -> str:
        """Text of ids.  The mark that encoding put in front goes."""
        text = self.spell(ids).decode("utf-8", "replace")
        return text.replace(MARK, " ")[1:] if text.startswith(MARK) else text.replace(MARK, " ")


def _prefixes(codes: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    n = codes.shape[1]
    prefix = np.zeros((n + 1, len(codes)), np.uint64)
    power = np.concatenate([np.ones(1, np.uint64), np.cumprod(np.full(n, _BASE, np.uint64))])
    values = mix(codes.astype(np.uint64).T.copy(), 1)
    for k in range(n):
        prefix[k + 1] = prefix[k] * _BASE + values[k]
    return prefix, power


def _finish(h: np.ndarray, size: int) -> np.ndarray:
    return mix(h, size)


def _row_hash(codes: np.ndarray) -> np.ndarray:
    return _finish(_prefixes(codes)[0][-1], codes.shape[1])


def segments(text: str) -> list[str]:
    """The marked text cut before each run of marks; no piece has a mark after another character."""
    return _SEGMENT.findall(MARK + text.replace(" ", MARK)) if text else []


class Encoder:
    """Texts to ids (as little-endian unsigned 32-bit bytes) with a memory of segments."""

    def __init__(self, lattice: Lattice):
        self.memory = Memory(lattice.encode_words, MEMORY // 3)

    @staticmethod
    def at(path: str) -> "Encoder":
        if path not in _encoders:
            _encoders[path] = Encoder(Lattice.from_model(path))
        return _encoders[path]

    def __call__(self, texts: list[str]) -> list[bytes]:
        split = [segments(t) for t in texts]
        known = self.memory(set().union(*split))
        return [b"".join(map(known.__getitem__, s)) for s in split]


def encode_pieces(docs: DataFrame, *, text_col: str = "text", model: str | None = None) -> DataFrame:
    """Adds the list ``ids`` of each whole text; null and empty texts have none.  A column of that name is replaced."""
    model = model or vocabulary("piece_bpe_32k.model")
    base = docs.drop("ids")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encoder = Encoder.at(model)
        for batch in batches:
            for b in text_slices(batch, text_col, WORD_BYTES // 2):
                ids = encoder(texts_of(b, text_col))
                ends = np.concatenate([[0], np.cumsum([len(x) // 4 for x in ids])]).astype(np.int32)
                lists = pa.ListArray.from_arrays(pa.array(ends), pa.array(np.frombuffer(b"".join(ids), np.int32)))
                yield pa.RecordBatch.from_arrays([*b.columns, lists], [*b.schema.names, "ids"])

    return base.mapInArrow(run, extended(base.schema, "ids array<int>"))


def decode_pieces(rows: DataFrame, *, ids_col: str = "ids", model: str | None = None) -> DataFrame:
    """Adds ``decoded``, the text of each id list; null lists give null.

    Decoding inverts encoding for every text without U+2581, which the model
    uses for a space and so decodes as one.
    """
    model = model or vocabulary("piece_bpe_32k.model")
    base = rows.drop("decoded")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        lattice = Lattice.from_model(model)
        for batch in batches:
            for lo in range(0, batch.num_rows, 64):
                b = batch.slice(lo, 64)
                lists = b.column(b.schema.get_field_index(ids_col))
                texts = [lattice.decode(x.values.to_numpy(zero_copy_only=False).astype("<u4").tobytes()) if x.is_valid else None for x in lists]
                yield pa.RecordBatch.from_arrays([*b.columns, pa.array(texts, pa.string())], [*b.schema.names, "decoded"])

    return base.mapInArrow(run, extended(base.schema, "decoded string"))


def digest(docs: DataFrame) -> DataFrame:
    """doc_id, n_ids, ids_crc32, decoded_sha256 and whether decoding gave the text back, for every document."""
    model = vocabulary("piece_bpe_32k.model")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encoder, lattice = Encoder.at(model), Lattice.from_model(model)
        for batch in batches:
            for b in text_slices(batch, "text", WORD_BYTES // 2):
                texts = texts_of(b, "text")
                ids = encoder(texts)
                back = [lattice.decode(x) for x in ids]
                cols = [pa.array([len(x) // 4 for x in ids], pa.int64()), pa.array([zlib.crc32(x) for x in ids], pa.int64()), pa.array([hashlib.sha256(t.encode()).hexdigest() for t in back]), pa.array([t == d for t, d in zip(texts, back)])]
                yield pa.RecordBatch.from_arrays([b.column(0), *cols], ["doc_id", "n_ids", "ids_crc32", "decoded_sha256", "round_trip"])

    # encoding and decoding share one pass: a worker process less for each task than the two operators in a row
    return docs.select("doc_id", "text").mapInArrow(run, "doc_id long, n_ids long, ids_crc32 long, decoded_sha256 string, round_trip boolean")
