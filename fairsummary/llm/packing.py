"""Best-fit packing of documents into bins of a token capacity, under conflicts.

A bin never holds two pieces of one source or of one duplicate cluster.  Open
bins are kept in the order of their residual capacity and carry bitmaps of
their sources and clusters; a piece goes to the tightest bin that fits it and
shares no bit with it, found by walking up from the first residual that fits.
"""

from __future__ import annotations

from bisect import bisect_left, insort
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import materialize, text_slices
from .simhash import fingerprint, label_fingerprints
from .words import find_words, raw_bytes

CAPACITY = 2048
#: Words of a shingle and differing bits of linked fingerprints, for clusters of near duplicates.
SHINGLE, LINK_BITS = 5, 2
#: Pieces packed together in one task; shards are packed apart from each other.
SHARD = 4096


def best_fit(sizes: list[int], sources: list, clusters: list, capacity: int) -> list[int]:
    """Bin number of each piece; pieces are placed in the order given.  A null source or cluster conflicts with nothing."""
    source_bit = {s: 1 << k for k, s in enumerate(dict.fromkeys(x for x in sources if x is not None))}
    cluster_bit = {c: 1 << k for k, c in enumerate(dict.fromkeys(x for x in clusters if x is not None))}
    open_bins: list[tuple[int, int]] = []
    held: list[list[int]] = []
    out = []
    for size, source, cluster in zip(sizes, sources, clusters):
        s, c = source_bit.get(source, 0), cluster_bit.get(cluster, 0)
        at = bisect_left(open_bins, (size, -1)) if size < capacity else len(open_bins)
        while at < len(open_bins) and (held[open_bins[at][1]][0] & s or held[open_bins[at][1]][1] & c):
            at += 1
        if at < len(open_bins):
            residual, number = open_bins.pop(at)
            held[number][0] |= s
            held[number][1] |= c
        else:
            residual, number = capacity, len(held)
            held.append([s, c])
        if residual > size:
            insort(open_bins, (residual - size, number))
        out.append(number)
    return out


def brute_force(sizes: list[int], sources: list, clusters: list, capacity: int) -> list[int]:
    """The same placement by looking at every bin."""
    bins: list[dict] = []
    out = []
    for size, source, cluster in zip(sizes, sources, clusters):
        fits = [(b["left"], k) for k, b in enumerate(bins) if b["left"] >= size and b["left"] > 0 and not (source is not None and source in b["s"]) and not (cluster is not None and cluster in b["c"])] if size < capacity else []
        if fits:
            k = min(fits)[1]
        else:
            bins.append({"left": capacity, "s": set(), "c": set()})
            k = len(bins) - 1
        bins[k]["left"] -= size
        bins[k]["s"].add(source)
        bins[k]["c"].add(cluster)
        out.append(k)
    return out


def measure(docs: DataFrame, *, near: bool = False, text_col: str = "text", id_col: str = "doc_id", source_col: str = "source") -> DataFrame:
    """(doc_id, source, cluster, n_tokens) of every document: words of the whole text, and its duplicate cluster.

    A cluster is the exact copies of a text, or with ``near`` the documents
    whose fingerprints of five-word shingles are linked by at most 2 differing
    bits, copies included.
    """
    rows = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(source_col).cast("string").alias("source"), F.xxhash64(text_col).alias("cluster"), F.col(text_col).alias("text"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for b in text_slices(batch, "text"):
                cluster = b.column(2)
                if near:
                    data, offs = raw_bytes(b.column(3))
                    body, offs = data.tobytes(), offs.tolist()
                    cluster = pa.array([fingerprint(body[s:e], SHINGLE)[0] for s, e in zip(offs[:-1], offs[1:])], pa.int64())
                yield pa.RecordBatch.from_arrays([*b.columns[:2], cluster, pa.array(find_words(b.column(3)).count.astype(np.int64))], ["doc_id", "source", "cluster", "n_tokens"])

    found = rows.mapInArrow(run, "doc_id long, source string, cluster long, n_tokens long")
    if not near:
        return found
    found = materialize(found, "measured")
    return found.withColumnRenamed("cluster", "fp").transform(lambda x: label_fingerprints(x, LINK_BITS)).withColumnRenamed("root", "cluster").select("doc_id", "source", "cluster", "n_tokens")


def token_items(table: DataFrame, docs: DataFrame, *, id_col: str = "doc_id", source_col: str = "source", text_col: str = "text") -> DataFrame:
    """(doc_id, source, cluster, n_tokens) with the counts of a token table, whose ids are unique."""
    known = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(source_col).cast("string").alias("source"), F.xxhash64(text_col).alias("cluster"))
    return table.select("doc_id", "n_tokens").join(known, "doc_id").select("doc_id", "source", "cluster", "n_tokens")


def build_sequences(placed: DataFrame, table: DataFrame) -> DataFrame:
    """(shard, bin, n_tokens, doc_ids, ids) of every bin: the ids of its pieces one after the other, the longest first, ties by document and piece.

    ``placed`` is what :func:`pack` makes of the counts of ``table`` (doc_id,
    ids).  A bin holds at most the capacity, so no group grows with the input.
    """
    own = placed.where("n_tokens > 0").join(table.select("doc_id", "ids"), "doc_id")
    cut = F.slice("ids", (F.col("start") + 1).cast("int"), F.col("n_tokens").cast("int"))
    rows = own.select("shard", "bin", F.struct((-F.col("n_tokens")).alias("size"), "doc_id", "piece", cut.alias("ids")).alias("x"))
    bins = rows.groupBy("shard", "bin").agg(F.sort_array(F.collect_list("x")).alias("x"))
    ids = F.flatten(F.transform("x", lambda x: x["ids"]))
    return bins.select("shard", "bin", F.size(ids).cast("long").alias("n_tokens"), F.transform("x", lambda x: x["doc_id"]).alias("doc_ids"), ids.alias("ids"))


def pack(items: DataFrame, *, capacity: int = CAPACITY, shard_size: int = SHARD) -> DataFrame:
    """Place (doc_id, source, cluster, n_tokens) rows: (doc_id, piece, start, n_tokens, shard, bin, bin_tokens).

    A document longer than the capacity is cut into full pieces and a rest.
    Pieces are dealt evenly to shards by row, so a hot source, cluster or id is
    spread; in a shard they are placed from the longest to the shortest, ties by
    id and row.  Documents without tokens have one row without a shard or bin.
    Nulls in source or cluster conflict with nothing; null or negative counts are zero.
    """
    if capacity < 1:
        raise ValueError("capacity must be positive")
    n = F.greatest(F.coalesce(F.col("n_tokens"), F.lit(0)), F.lit(0)).cast("long")
    rows = items.select("doc_id", "source", "cluster", n.alias("total"), F.monotonically_increasing_id().alias("row"))
    rows = materialize(rows, "items")
    pieces = rows.where("total > 0").select("*", F.explode(F.sequence(F.lit(0), F.floor((F.col("total") - 1) / capacity).cast("int"))).alias("piece"))
    pieces = pieces.select("doc_id", "source", "cluster", "row", "piece", (F.col("piece").cast("long") * capacity).alias("start"), F.least(F.lit(capacity).cast("long"), F.col("total") - F.col("piece").cast("long") * capacity).alias("size"))
    shards = max(1, -(-int(rows.where("total > 0").agg(F.sum(F.ceil(F.col("total") / capacity))).first()[0] or 0) // shard_size))
    pieces = pieces.withColumn("shard", F.pmod(F.xxhash64("row", "piece"), F.lit(shards)).cast("int"))

    def place(table):
        t = table.to_pandas().sort_values(["size", "doc_id", "row", "piece"], ascending=[False, True, True, True], kind="stable")
        none = lambda column: [None if pd.isna(x) else x for x in t[column].tolist()]
        t["bin"] = best_fit(t["size"].tolist(), none("source"), none("cluster"), capacity)
        t["bin_tokens"] = t.groupby("bin")["size"].transform("sum")
        ids = pa.array(none("doc_id"), pa.int64()) if t["doc_id"].isna().any() else pa.array(t["doc_id"].astype("int64"))
        return pa.table({"doc_id": ids, "piece": pa.array(t["piece"], pa.int32()), "start": pa.array(t["start"], pa.int64()), "n_tokens": pa.array(t["size"], pa.int64()), "shard": pa.array(t["shard"], pa.int32()), "bin": pa.array(t["bin"], pa.int32()), "bin_tokens": pa.array(t["bin_tokens"], pa.int64())})

    schema = "doc_id long, piece int, start long, n_tokens long, shard int, bin int, bin_tokens long"
    placed = pieces.groupBy("shard").applyInArrow(place, schema)
    empty = rows.where("total = 0").selectExpr("doc_id", "0 AS piece", "0L AS start", "0L AS n_tokens", "CAST(NULL AS int) AS shard", "CAST(NULL AS int) AS bin", "CAST(NULL AS bigint) AS bin_tokens")
    return placed.unionByName(empty)


def digest(docs: DataFrame) -> DataFrame:
    """Where every piece of every document goes, at the default capacity; near duplicates share a cluster."""
    return pack(measure(docs, near=True))
