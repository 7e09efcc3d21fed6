"""Exact removal of repeated passages by difference-cover anchors.

Every pair of equal windows, wherever each lies in its document, has a common
shift at which both positions fall on the difference cover modulo the period,
so it is enough to hash short anchors at cover positions.  Windows around an
anchor that occurs twice are extended to the whole window length, hashed with
96 bits and counted; windows that occur at least twice are removed.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import extended, materialize, sized, text_slices
from .words import Words, find_words, mix, range_hash

#: Perfect difference sets; all differences modulo the period occur.
COVERS = {1: (0,), 3: (0, 1), 7: (0, 1, 3), 13: (0, 1, 3, 9), 21: (3, 6, 7, 12, 14)}
#: The filter of repeated anchors is broadcast up to this many bits (32 MB); beyond it anchors are joined.
FILTER_BITS = 1 << 28


def is_cover(period: int, cover: tuple[int, ...]) -> bool:
    return {(a - b) % period for a in cover for b in cover} == set(range(period))


def period_for(window: int) -> int:
    """The longest tabulated period that leaves anchors of at least two fifths of the window."""
    return max(p for p in COVERS if window - p + 1 >= max(1, 2 * window // 5))


def _anchors(words: Words, hashes: np.ndarray, window: int, period: int) -> tuple[np.ndarray, np.ndarray]:
    """Word numbers of the anchors in the batch and their hashes."""
    on = np.zeros(period, bool)
    on[list(COVERS[period])] = True
    length, index = window - period + 1, words.index
    room = np.repeat(words.count, words.count)
    at = np.flatnonzero(on[index % period] & (index + length <= room) & (room >= window))
    return at, range_hash(hashes, at, at + length)


def _candidates(words: Words, at: np.ndarray, window: int, period: int) -> np.ndarray:
    """Word numbers at which a window starts that contains one of the anchors ``at``."""
    n = len(words.start)
    edge = np.zeros(n + 1, np.int32)
    first = np.repeat(words.first, words.count)[at] if len(at) else at
    np.add.at(edge, np.maximum(at - period + 1, first), 1)
    np.add.at(edge, at + 1, -1)
    inside = np.cumsum(edge[:-1]) > 0
    return np.flatnonzero(inside & (words.index + window <= np.repeat(words.count, words.count)))


class _Filter:
    """A Bloom filter: a miss is certain, a hit is not."""

    def __init__(self, bits: np.ndarray):
        self.bits = bits

    def __call__(self, h: np.ndarray) -> np.ndarray:
        out = np.ones(len(h), bool)
        for slot in _slots(h, len(self.bits) * 8):
            out &= (self.bits[slot >> np.uint64(3)] >> (slot & np.uint64(7)).astype(np.uint8)) & 1 > 0
        return out


def _slots(h: np.ndarray, size: int) -> list[np.ndarray]:
    """Three bit numbers for each hash; ``size`` is a power of two."""
    return [mix(h, salt) & np.uint64(size - 1) for salt in (3, 4, 6)]


def _filter_bits(repeated: DataFrame, n: int, limit: int) -> np.ndarray | None:
    """Filter of the repeated anchors with 16 or more bits for each, or None where the bound does not hold."""
    size = 1 << max(16, (16 * n - 1).bit_length())
    if size > limit:
        return None

    def part(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            slot = np.concatenate(_slots(b.column(0).to_numpy().view(np.uint64), size))
            word, bit = (slot >> np.uint64(6)).astype(np.int64), (np.uint64(1) << (slot & np.uint64(63))).view(np.int64)
            yield pa.RecordBatch.from_arrays([pa.array(word), pa.array(bit)], ["word", "bit"])

    got = repeated.mapInArrow(part, "word long, bit long").groupBy("word").agg(F.bit_or("bit").alias("bit")).toArrow()
    words = np.zeros(size // 64, np.int64)
    words[got["word"].to_numpy()] = got["bit"].to_numpy()
    return words.view(np.uint8)


TEXT = ("text_key", "text_sum")


def _identity(column: str) -> dict[str, Column]:
    """96 bits that stand for a text; equal texts have equal spans, so rows need no other key."""
    return {"text_key": F.xxhash64(column), "text_sum": F.hash(column)}


def _column(b: pa.RecordBatch, name: str) -> pa.Array:
    return b.column(b.schema.get_field_index(name))


def repeated_spans(docs: DataFrame, *, id_col: str = "doc_id", text_col: str = "text", window: int = 35, period: int | None = None, filter_bits: int = FILTER_BITS) -> DataFrame:
    """Word spans that lie in a repeated window: (text_key, text_sum, copies, span_from[], span_to[]), one row per text that has any.

    Texts of several rows have ``copies`` set instead of spans: all their
    windows repeat.  Null, empty and short texts have no windows.
    """
    if window < 1:
        raise ValueError("window must be positive")
    period = period or period_for(window)
    if period not in COVERS or not is_cover(period, COVERS[period]) or period > window:
        raise ValueError("the period must have a cover and not exceed the window")
    spark = docs.sparkSession
    keyed = docs.where(F.col(text_col).isNotNull()).select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("text")).withColumns(_identity("text"))
    copied = materialize(keyed.groupBy(*TEXT).agg(F.min("doc_id").alias("least"), F.count("*").alias("n")).where("n > 1").select(*TEXT, "least"), "copied")
    # of copies one row (or the few that share its id) speaks for the text; its windows repeat in any case
    marked = keyed.join(sized(copied.withColumn("copied", F.lit(True))), list(TEXT), "left")
    once = marked.where(F.col("copied").isNull() | F.col("doc_id").eqNullSafe(F.col("least"))).select("text")
    own = marked.where(F.col("copied").isNull()).select(*TEXT, "text")

    def anchors(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for b in text_slices(batch, "text"):
                w = find_words(b.column(0))
                _, h = _anchors(w, w.hashes(), window, period)
                kept, n = np.unique(h, return_counts=True)  # of what repeats in the slice, two rows say enough
                h = np.concatenate([kept, kept[n > 1]]).view(np.int64)
                if len(h):
                    yield pa.RecordBatch.from_arrays([pa.array(h)], ["anchor"])

    repeated = materialize(once.mapInArrow(anchors, "anchor long").groupBy("anchor").count().where("count > 1").select("anchor"), "anchors")
    bits = _filter_bits(repeated, repeated.count(), filter_bits)
    shared = None if bits is None else spark.sparkContext.broadcast(bits)
    if bits is None:
        spots = _located(once.withColumns(_identity("text")), repeated, window, period)
        once = once.withColumns(_identity("text")).join(sized(spots), list(TEXT)).select("text", "spots")
        own = own.join(sized(spots), list(TEXT)).select(*TEXT, "text", "spots")

    def windows(batches: Iterator[pa.RecordBatch], places: bool) -> Iterator[pa.RecordBatch]:
        test = None if shared is None else _Filter(shared.value)
        for batch in batches:
            for b in text_slices(batch, "text"):
                w = find_words(_column(b, "text"))
                h = w.hashes()
                if test is not None:
                    at, key = _anchors(w, h, window, period)
                    at = at[test(key)]
                else:
                    at = np.concatenate([np.asarray(s, np.int64) + f for s, f in zip(_column(b, "spots").to_pylist(), w.first)])
                p = _candidates(w, np.unique(at), window, period)
                if not len(p):
                    continue
                cols = {"h1": range_hash(h, p, p + window).view(np.int64), "h2": (range_hash(mix(h, 5), p, p + window, 1) >> np.uint64(32)).astype(np.uint32).view(np.int32)}
                if places:
                    d = w.doc[p]
                    cols |= {c: _column(b, c).take(pa.array(d)) for c in TEXT} | {"at": (p - w.first[d]).astype(np.int32)}
                yield pa.RecordBatch.from_arrays([pa.array(c) for c in cols.values()], list(cols))

    twice = once.mapInArrow(lambda it: windows(it, False), "h1 long, h2 int").groupBy("h1", "h2").count().where("count > 1").select("h1", "h2")
    twice = materialize(twice, "windows")
    places = own.mapInArrow(lambda it: windows(it, True), "h1 long, h2 int, text_key long, text_sum int, at int")
    hit = places.join(twice.hint("shuffle_hash"), ["h1", "h2"]).groupBy(*TEXT).agg(F.collect_list("at").alias("at"))

    def spans(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            lo, hi = [], []
            for starts in b.column(2):
                s = np.unique(starts.values.to_numpy())
                new = np.flatnonzero(np.diff(s, prepend=s[0] - window - 1) > window)
                lo.append(s[new])
                hi.append(s[np.append(new[1:], len(s)) - 1] + window)
            yield pa.RecordBatch.from_arrays([*b.columns[:2], pa.array(lo, pa.list_(pa.int32())), pa.array(hi, pa.list_(pa.int32()))], [*TEXT, "span_from", "span_to"])

    found = hit.mapInArrow(spans, "text_key long, text_sum int, span_from array<int>, span_to array<int>").withColumn("copies", F.lit(False))
    none = F.lit(None).cast("array<int>")
    return materialize(found.unionByName(copied.select(*TEXT, F.lit(True).alias("copies"), none.alias("span_from"), none.alias("span_to"))), "spans")


def _located(once: DataFrame, repeated: DataFrame, window: int, period: int) -> DataFrame:
    """Where a filter would outgrow its bound: repeated anchors joined back to their places, per text."""

    def places(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for b in text_slices(batch, "text"):
                w = find_words(_column(b, "text"))
                at, h = _anchors(w, w.hashes(), window, period)
                d = w.doc[at]
                yield pa.RecordBatch.from_arrays([pa.array(h.view(np.int64)), *(_column(b, k).take(pa.array(d)) for k in TEXT), pa.array((at - w.first[d]).astype(np.int32))], ["anchor", *TEXT, "at"])

    rows = once.mapInArrow(places, "anchor long, text_key long, text_sum int, at int").join(repeated.hint("shuffle_hash"), "anchor")
    return materialize(rows.groupBy(*TEXT).agg(F.collect_set("at").alias("spots")), "spots")


def remove_repeats(docs: DataFrame, *, id_col: str = "doc_id", text_col: str = "text", window: int = 35, period: int | None = None, filter_bits: int = FILTER_BITS) -> DataFrame:
    """Documents with every word of a repeated window cut out.

    All columns stay; added are ``kept_text`` (the kept words joined by one
    space; null texts give an empty one), ``n_words``, ``n_removed``,
    ``removed_from`` and ``removed_to`` (word spans).  Documents of which no
    window repeats keep all words.  Repeated rows and equal texts repeat each
    other.  Added names replace columns of the same name.
    """
    added = ["kept_text", "n_words", "n_removed", "removed_from", "removed_to"]
    keys = ["__key", "__sum"]
    found = repeated_spans(docs, id_col=id_col, text_col=text_col, window=window, period=period, filter_bits=filter_bits)
    found = sized(found.select(*(F.col(c).alias(k) for c, k in zip(TEXT, keys)), "copies", "span_from", "span_to"))
    bare = docs.drop(*added)
    base = bare.withColumns(dict(zip(keys, _identity(text_col).values())))
    joined = base.join(found, keys, "left").select(*bare.columns, F.col("copies").alias("__copies"), F.col("span_from").alias("__from"), F.col("span_to").alias("__to"))

    def cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for b in text_slices(batch, text_col):
                w = find_words(_column(b, text_col))
                body, start, end = w.data.tobytes(), w.start.tolist(), w.end.tolist()
                texts, gone, lows, highs = [], [], [], []
                for f, n, copies, lo, hi in zip(w.first.tolist(), w.count.tolist(), *(_column(b, c).to_pylist() for c in ("__copies", "__from", "__to"))):
                    lo, hi = ([0], [n]) if copies and n >= window else (lo or [], hi or [])
                    parts = [range(f + x, f + y) for x, y in zip([0, *hi], [*lo, n])]
                    texts.append(b" ".join([body[start[i] : end[i]] for r in parts for i in r]).decode("utf-8", "surrogatepass"))
                    gone.append(sum(hi) - sum(lo))
                    lows.append(lo)
                    highs.append(hi)
                cols = {c: b.column(i) for i, c in enumerate(b.schema.names) if c not in ("__copies", "__from", "__to")}
                cols |= {"kept_text": pa.array(texts, pa.string()), "n_words": pa.array(w.count.astype(np.int64)), "n_removed": pa.array(gone, pa.int64()), "removed_from": pa.array(lows, pa.list_(pa.int32())), "removed_to": pa.array(highs, pa.list_(pa.int32()))}
                yield pa.RecordBatch.from_arrays(list(cols.values()), list(cols))

    return joined.mapInArrow(cut, extended(bare.schema, "kept_text string, n_words long, n_removed long, removed_from array<int>, removed_to array<int>"))


def digest(docs: DataFrame) -> DataFrame:
    """The query's columns: doc_id, n_words, n_removed, kept_sha256."""
    slim = docs.select("doc_id", "text")
    return remove_repeats(slim).select("doc_id", "n_words", "n_removed", F.sha2(F.col("kept_text").cast("binary"), 256).alias("kept_sha256"))


def brute_force(texts: list[str | None], window: int = 35) -> list[tuple[int, int, str]]:
    """The definition, row by row in plain Python: (n_words, n_removed, kept_sha256)."""
    import re
    from collections import Counter

    split = [re.findall(r"[^\x20\x09-\x0D]+", t or "") for t in texts]
    seen = Counter(tuple(w[i : i + window]) for w in split for i in range(len(w) - window + 1))
    out = []
    for w in split:
        gone = [False] * len(w)
        for i in range(len(w) - window + 1):
            if seen[tuple(w[i : i + window])] > 1:
                gone[i : i + window] = [True] * window
        kept = " ".join(x for x, g in zip(w, gone) if not g)
        out.append((len(w), sum(gone), hashlib.sha256(kept.encode()).hexdigest()))
    return out
