"""SimHash near-duplicates by the generalised pigeonhole principle.

Bits that go together are grouped into partitions.  If two fingerprints differ
in at most t bits, then for any thresholds t_i with sum(t_i + 1) = t + 1 some
partition differs in at most t_i bits, so partitions get unequal thresholds,
some of them none at all, by dynamic programming on estimated probe and
candidate counts.  Probes enumerate the flips within a threshold; candidates
are verified on the whole fingerprint.  Buckets with many members are not
expanded into pairs: an exact linear way links their members.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass
from itertools import combinations
from math import ceil, comb

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import label_rows, map_batches, materialize, null_safe, scratch, sized, small_batches, text_slices
from .graph import components
from .words import find_words, range_hash, raw_bytes

BITS, SEED = 64, 42
#: Differing bits of near duplicates' fingerprints; pairs beyond are found by their shingles.
NEAR = 3
#: Buckets with more members take the linear way.
CROWD = 48
#: Members of a crowded bucket that all others are compared with before any pairs are made.
LEADERS = 8
#: Texts, at most about twice as many, that show which shingles are common, and common shingles that are told apart; they set an order, not the result.
SAMPLE, COMMON = 4000, 100_000
#: Shingles that each of some rounds of prefixes may add to them.
SHARED, ROUNDS = 500_000, 1


def _bits_of(hashes: list[int]) -> int:
    h = np.array(hashes, np.uint64)
    ones = np.zeros(BITS, np.int64)
    for lo in range(0, len(h), 8192):
        ones += np.unpackbits(h[lo : lo + 8192].view(np.uint8).reshape(-1, 8), axis=1).sum(axis=0, dtype=np.int32)
    return int(np.packbits(2 * ones > len(h)).view(np.int64)[0])


def fingerprint(text: bytes, shingle: int = 3) -> tuple[int, int]:
    """Signed 64-bit fingerprint of a UTF-8 text and its number of distinct shingles (0 without words)."""
    words = text.lower().split()  # ASCII letters and exactly the six separators
    if not words:
        return 0, 0
    body = b" ".join(words)
    size = np.fromiter(map(len, words), np.int64, len(words)) + 1
    end = np.cumsum(size)
    start, n = end - size, max(1, len(words) - shingle + 1)
    stop = end[min(shingle, len(words)) - 1 :] - 1
    digest = xxhash.xxh64_intdigest
    hashes = [digest(body[s:e], SEED) for s, e in zip(start[:n].tolist(), stop.tolist())]
    return _bits_of(hashes), len(set(hashes))


def fingerprints(docs: DataFrame, *, id_col: str = "doc_id", text_col: str = "text", shingle: int = 3) -> DataFrame:
    """(doc_id, text_key, fp, size) of every whole text; null texts are empty and have fingerprint zero."""
    rows = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.xxhash64(text_col).alias("text_key"), F.col(text_col).alias("text"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for b in text_slices(batch, "text"):
                data, offs = raw_bytes(b.column(2))
                body, offs = data.tobytes(), offs.tolist()
                fp, n = zip(*(fingerprint(body[s:e], shingle) for s, e in zip(offs[:-1], offs[1:])))
                yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array(fp, pa.int64()), pa.array(n, pa.int64())], ["doc_id", "text_key", "fp", "size"])

    return map_batches(rows, run, "doc_id long, text_key long, fp long, size long")


def bit_statistics(fps: DataFrame) -> tuple[int, np.ndarray]:
    """Number of fingerprints and the 64 x 64 counts of bits set together, over all rows."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total, n = np.zeros((BITS, BITS)), 0
        for b in batches:
            h = b.column(0).to_numpy()
            for lo in range(0, len(h), 65536):
                bits = (h[lo : lo + 65536].view(np.uint64)[:, None] >> np.arange(BITS, dtype=np.uint64) & np.uint64(1)).astype(np.float32)
                total += bits.T @ bits
                n += len(bits)
        if n:
            i, j = np.triu_indices(BITS)
            at = np.append(i * BITS + j, -1)
            yield pa.RecordBatch.from_arrays([pa.array(at), pa.array(np.append(total[i, j], n).astype(np.int64))], ["at", "n"])

    got = map_batches(fps.select("fp"), run, "at long, n long").groupBy("at").agg(F.sum("n").alias("n")).toArrow()
    flat = dict(zip(got["at"].to_pylist(), got["n"].to_pylist()))
    both = np.zeros((BITS, BITS))
    for at, n in flat.items():
        if at >= 0:
            both[at // BITS, at % BITS] = both[at % BITS, at // BITS] = n
    return flat.get(-1, 0), both


@dataclass(frozen=True)
class Plan:
    """Partitions as bit masks, and the threshold of each; only those with a threshold of 0 or more are probed."""

    masks: tuple[int, ...]
    thresholds: tuple[int, ...]
    cost: float

    def probes(self) -> list[tuple[int, int, int]]:
        """(partition, mask, flip) of every key that a fingerprint asks for."""
        out = []
        for i, (mask, t) in enumerate(zip(self.masks, self.thresholds)):
            bits = [1 << b for b in range(BITS) if mask >> b & 1]
            for k in range(t + 1):
                out += [(i, mask, sum(c)) for c in combinations(bits, k)]
        return out


def group_bits(both: np.ndarray, n: int, parts: int) -> list[list[int]]:
    """Partitions of nearly equal size that keep correlated bits together."""
    p = np.diag(both) / max(n, 1)
    spread = np.sqrt(np.maximum(p * (1 - p), 1e-12))
    corr = np.abs((both / max(n, 1) - np.outer(p, p)) / np.outer(spread, spread))
    np.fill_diagonal(corr, 0)
    left, out = list(range(BITS)), []
    for i in range(parts):
        size = (BITS * (i + 1)) // parts - (BITS * i) // parts
        own = [max(left, key=lambda b: corr[b, left].sum())]
        left.remove(own[0])
        while len(own) < size:
            best = max(left, key=lambda b: corr[b, own].sum())
            own.append(best)
            left.remove(best)
        out.append(sorted(own))
    return out


def plan(n: int, both: np.ndarray, max_bits: int, *, share: float = 1.0, copies: int = 1, probe_cost: float = 1.0, pair_cost: float = 0.3, most_parts: int = 6) -> Plan:
    """The cheapest partitions and thresholds by dynamic programming.

    A threshold's cost is its probe keys plus its expected candidates, from
    the measured share of ones of each bit.  ``share`` scales candidates and
    ``copies`` probes where a further key column cuts buckets.
    """
    p = np.diag(both) / max(n, 1)
    best = None
    for parts in range(1, most_parts + 1):
        groups = group_bits(both, n, parts)
        costs = []
        for g in groups:
            law = np.ones(1)
            for q in 2 * p[g] * (1 - p[g]):  # chance that two fingerprints differ in a bit
                law = np.convolve(law, [1 - q, q])
            at_most, keys, row = np.cumsum(law), 0, [0.0]
            for t in range(max_bits + 1):
                keys += comb(len(g), t)
                row.append(n * keys * copies * probe_cost + n * n * share * at_most[min(t, len(at_most) - 1)] * pair_cost)
            costs.append(row)
        state = {0: (0.0, ())}
        for row in costs:
            nxt: dict[int, tuple[float, tuple[int, ...]]] = {}
            for used, (cost, chosen) in state.items():
                for t, c in enumerate(row):  # t stands for threshold t - 1
                    if used + t <= max_bits + 1 and (used + t not in nxt or cost + c < nxt[used + t][0]):
                        nxt[used + t] = cost + c, (*chosen, t - 1)
            state = nxt
        if max_bits + 1 in state:
            cost, chosen = state[max_bits + 1]
            if best is None or cost < best.cost:
                best = Plan(tuple(sum(1 << b for b in g) for g in groups), chosen, cost)
    return best


def _signed(x: int) -> int:
    return x - (1 << 64) if x >> 63 else x


def _keys(nodes: DataFrame, probes: list[tuple[int, int, int]], by_size: bool, probing: bool) -> DataFrame:
    """Bucket keys of every node: its own as ``probing`` is false, those it asks for otherwise."""
    table = F.array(*[F.struct(F.lit(i).alias("part"), F.lit(_signed(m)).alias("mask"), F.lit(_signed(f)).alias("flip")) for i, m, f in probes])
    rows = nodes.select("node", "fp", "size", F.explode(table).alias("k"))
    rows = rows.select("node", "fp", "size", F.col("k.part").alias("part"), F.col("fp").bitwiseAND(F.col("k.mask")).bitwiseXOR(F.col("k.flip")).alias("val"))
    if not by_size:
        return rows.withColumn("rank", F.lit(0))
    rank = F.floor(F.log(F.greatest(F.col("size"), F.lit(1)).cast("double")) / F.log(F.lit(1.25))).cast("int")
    if probing:  # a size ratio of 0.8 or more crosses one rank bound at most
        return rows.withColumn("rank", F.explode(F.array(rank - 1, rank, rank + 1)))
    return rows.withColumn("rank", rank)


def _once(chosen: Plan, part: Column, differ: Column) -> Column:
    """Whether this is the first probed partition that brings the pair together, so that a pair is made once."""
    out, before = None, F.lit(True)
    for i, (mask, t) in enumerate(zip(chosen.masks, chosen.thresholds)):
        if t >= 0:
            out = F.when(part == i, before) if out is None else out.when(part == i, before)
            before = before & (F.bit_count(differ.bitwiseAND(F.lit(_signed(mask)))) > t)
    return out


def _pairs(home: DataFrame, asking: DataFrame, on: list[str], chosen: Plan, max_bits: int, *more: str) -> DataFrame:
    """Pairs (a, b), a < b, of a node in its own bucket and one that asks for the bucket; the other order comes from b's bucket."""
    l = home.select(*on, F.col("node").alias("a"), F.col("fp").alias("fa"), *(F.col(c).alias(f"{c}_a") for c in more))
    r = asking.select(*on, F.col("node").alias("b"), F.col("fp").alias("fb"), *(F.col(c).alias(f"{c}_b") for c in more))
    differ = F.col("fa").bitwiseXOR(F.col("fb"))
    near = (F.col("a") < F.col("b")) & (F.bit_count(differ) <= max_bits) & _once(chosen, F.col("part"), differ)
    for c in more:  # nodes with equal values are connected already
        near = near & (F.col(f"{c}_a") != F.col(f"{c}_b"))
    return l.join(r, on).where(near).select("a", "b")


def links(nodes: DataFrame, max_bits: int, *, check=None, by_size: bool = False, crowd: int = CROWD) -> DataFrame:
    """Edges (a, b) that connect exactly the nodes which chains of links connect.

    ``nodes`` is a materialized (node, fp, size).  A link is a pair within
    ``max_bits`` that ``check`` (pairs to pairs, such as a similarity of texts)
    accepts.  ``by_size`` also needs sizes within a ratio of 0.8.  Nodes in
    crowded buckets are linked without all their pairs: through shared one-bit
    neighbours where ``max_bits`` is 2 or less and there is no check, else by some
    leaders for each bucket and pairs of only those that leaders don't connect.
    """
    n, both = bit_statistics(nodes)
    if n < 2:
        return nodes.select(F.col("node").alias("a"), F.col("node").alias("b")).where("false")
    chosen = plan(n, both, max_bits, share=0.2 if by_size else 1.0, copies=3 if by_size else 1)
    probes = chosen.probes()
    on = ["part", "val", "rank"]
    own = _keys(nodes, [(i, m, 0) for i, (m, t) in enumerate(zip(chosen.masks, chosen.thresholds)) if t >= 0], by_size, False)
    asked = _keys(nodes, probes, by_size, True)
    crowded = materialize(own.groupBy(*on).count().where(F.col("count") > crowd).select(*on), "crowded")
    if crowded.isEmpty():
        found = materialize(_pairs(own, asked, on, chosen, max_bits), "pairs")
        return check(found) if check else found
    crowded = sized(crowded)
    found = materialize(_pairs(own.join(crowded, on, "left_anti"), asked, on, chosen, max_bits), "pairs")
    inside = asked.join(crowded, on, "left_semi")
    if check is None and max_bits <= 2:
        return found.union(_shared_neighbours(inside.select("node", "fp").distinct(), max_bits))
    members = materialize(own.join(crowded, on, "left_semi").withColumn("home", F.lit(True)).unionByName(inside.withColumn("home", F.lit(False))).groupBy(*on, "node", "fp").agg(F.max("home").alias("home")), "members")
    turn = F.row_number().over(Window.partitionBy(*on).orderBy(F.xxhash64("node")))
    leaders = members.where("home").withColumn("turn", turn).where(F.col("turn") <= LEADERS).select(*on, F.col("node").alias("lead"), F.col("fp").alias("lead_fp"))
    star = members.join(leaders, on).where((F.col("node") != F.col("lead")) & (F.bit_count(F.col("fp").bitwiseXOR(F.col("lead_fp"))) <= max_bits))
    first = materialize(star.select(F.least("node", "lead").alias("a"), F.greatest("node", "lead").alias("b")).distinct(), "stars")
    sure = check(first) if check else first
    joined = members.join(sized(materialize(components(sure), "roots")), "node", "left").withColumn("group", F.coalesce("root", "node"))
    joined = materialize(joined.select(*on, "node", "fp", "home", "group"), "joined")
    # pairs that leaders have connected need no look; every other pair of the bucket gets one
    rest = materialize(_pairs(joined.where("home"), joined, on, chosen, max_bits, "group").union(found), "pairs")
    return (check(rest) if check else rest).union(sure)


def _shared_neighbours(nodes: DataFrame, max_bits: int) -> DataFrame:
    """Links within 2 bits (or 1) in linear time: two fingerprints share a one-bit neighbour just when they differ in at most 2."""
    one = [1 << b for b in range(BITS)]
    if max_bits == 2:
        hubs = F.array(*[F.col("fp").bitwiseXOR(F.lit(_signed(m))) for m in [0, *one]])
        rows = nodes.select("node", F.explode(hubs).alias("hub"))
    else:
        hubs = F.array(*[F.struct(F.lit(b).alias("bit"), F.col("fp").bitwiseAND(F.lit(_signed(~m & (2**64 - 1)))).alias("rest")) for b, m in enumerate(one)]) if max_bits else F.array(F.struct(F.lit(0).alias("bit"), F.col("fp").alias("rest")))
        rows = nodes.select("node", F.explode(hubs).alias("hub"))
    least = rows.groupBy("hub").agg(F.min("node").alias("a"), F.count("*").alias("n")).where("n > 1").select("hub", "a")
    return rows.join(least, "hub").where("node != a").select("a", F.col("node").alias("b")).distinct()


def label_fingerprints(rows: DataFrame, max_bits: int) -> DataFrame:
    """Adds ``root`` to materialized rows with a fingerprint ``fp``: the smallest fingerprint that links within ``max_bits`` reach."""
    counts = materialize(rows.groupBy("fp").agg(F.count("*").alias("n")), "nodes")
    nodes = counts.select(F.col("fp").alias("node"), "fp", F.lit(1).alias("size"))
    roots = components(links(nodes, max_bits))
    label = materialize(counts.join(roots, F.col("fp") == F.col("node"), "left").select("fp", F.coalesce("root", "fp").alias("root"), "n"), "labels")
    return label_rows(rows, label, "fp")


def near_components(docs: DataFrame, *, shingle: int = 3, max_bits: int = 2, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, fp, component_id) for every row; rows of one fingerprint are linked at distance zero.

    Texts without words have fingerprint zero and link like any other.  A
    component without any id has a null ``component_id``.
    """
    rows = materialize(fingerprints(docs, id_col=id_col, text_col=text_col, shingle=shingle).select("doc_id", "fp"), "fingerprints")
    nodes = materialize(rows.groupBy("fp").agg(F.min("doc_id").alias("least"), F.count("*").alias("n")).select(F.col("fp").alias("node"), "fp", F.lit(1).alias("size"), "least", "n"), "nodes")
    edges = links(nodes.drop("least", "n"), max_bits)
    roots = components(edges)
    labelled = nodes.join(roots, "node", "left").select("fp", "least", "n", F.coalesce("root", "node").alias("root"))
    least = labelled.groupBy("root").agg(F.min("least").alias("component_id"))
    label = materialize(labelled.join(least, "root").select("fp", "component_id", "n"), "labels")
    return label_rows(rows, label, "fp").select("doc_id", "fp", "component_id")


def digest(docs: DataFrame) -> DataFrame:
    """doc_id, fingerprint (16 hexadecimal digits) and component_id of every document."""
    found = near_components(docs.select("doc_id", "text"))
    return found.select("doc_id", F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id")


def _sets(batch: pa.RecordBatch, shingle: int) -> Iterator[tuple[pa.Array, list[np.ndarray]]]:
    """Slices of the first column of (key, text), with the sorted distinct 64-bit shingle hashes of each whole text (fewer words: the whole sequence)."""
    for b in text_slices(batch, "text"):
        data, offs = raw_bytes(b.column(1))
        low = pa.array([data[s:e].tobytes().lower() for s, e in zip(offs[:-1].tolist(), offs[1:].tolist())], pa.binary()).cast(pa.large_binary()).view(pa.large_string())
        w = find_words(low)
        h = w.hashes()
        out = []
        for f, n in zip(w.first.tolist(), w.count.tolist()):
            at = np.arange(f, f + max(1, n - shingle + 1)) if n else np.zeros(0, np.int64)
            out.append(np.unique(range_hash(h, at, np.minimum(at + shingle, f + n))) if n else np.zeros(0, np.uint64))
        yield b.column(0), out


def shingle_sets(texts: DataFrame, key: str, shingle: int) -> DataFrame:
    """(key, shingles): sorted distinct 32-bit hashes of the word shingles of each whole text, as bytes."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for keys, sets in _sets(batch, shingle):
                yield pa.RecordBatch.from_arrays([keys, pa.array([np.unique((x >> np.uint64(32)).astype("<u4")).tobytes() for x in sets], pa.binary())], [key, "shingles"])

    return map_batches(texts.select(key, "text"), run, f"{key} long, shingles binary")


def common_shingles(texts: DataFrame, n: int, shingle: int) -> tuple[np.ndarray, np.ndarray]:
    """Sorted hashes of shingles that are common in a sample of the ``n`` texts, and their counts there."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for _, sets in _sets(batch, shingle):
                yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(sets).view(np.int64))], ["h"])

    some = texts.where(F.pmod(F.xxhash64("node"), F.lit(max(1, n // SAMPLE))) == 0)
    got = map_batches(some.select("node", "text"), run, "h long").groupBy("h").count().where("count > 2").orderBy(F.desc("count"), "h").limit(COMMON).toArrow()
    h, count = got["h"].to_numpy().view(np.uint64), got["count"].to_numpy()
    order = np.argsort(h)
    return h[order], count[order]


def known_shared(keys: DataFrame, common: tuple[np.ndarray, np.ndarray], most: int = SHARED) -> tuple[np.ndarray, np.ndarray]:
    """The common shingles and, of ``keys``, the ``most`` that occur most often beyond once: hashes in order, and counts.

    They only order prefixes, so a bound on them costs candidates, not pairs.
    """
    got = keys.groupBy("key").count().where("count > 1").orderBy(F.desc("count"), "key").limit(most).toArrow()
    h = np.concatenate([got["key"].to_numpy().view(np.uint64), common[0]])
    count = np.concatenate([got["count"].to_numpy(), common[1]])
    order = np.lexsort((-count, h))
    h, count = h[order], count[order]
    kept = np.append(True, h[1:] != h[:-1])[: len(h)]
    return h[kept], count[kept]


def prefixes(texts: DataFrame, common: tuple[np.ndarray, np.ndarray], *, shingle: int, similarity: float) -> DataFrame:
    """(node, size, parity, keys) of (node, text): number of distinct shingles, parities of 256 hash buckets, prefix.

    Shingles have one order for all texts, rare ones first.  Two sets whose
    Jaccard similarity reaches ``similarity`` share a shingle among the first
    size - ceil(similarity * size) + 1 of each; any order would do.
    """
    known, counts = common

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for nodes, sets in _sets(batch, shingle):
                parity, keys = np.zeros((len(sets), 32), np.uint8), []
                for i, x in enumerate(sets):
                    odd = np.bincount((x & np.uint64(255)).astype(np.int64), minlength=256) & 1
                    parity[i] = np.packbits(odd.astype(np.uint8))
                    if not len(x):
                        keys.append(np.zeros(1, np.int64))  # texts without words have one key of their own
                        continue
                    if len(known):
                        at = np.minimum(np.searchsorted(known, x), len(known) - 1)
                        x = x[np.argsort(np.where(known[at] == x, counts[at], 0), kind="stable")]
                    keys.append(x[: len(x) - ceil(similarity * len(x) - 1e-9) + 1].view(np.int64))
                words = [pa.array(np.ascontiguousarray(parity.view(np.int64)[:, j])) for j in range(4)]
                lists = pa.ListArray.from_arrays(pa.array(np.cumsum([0, *map(len, keys)]), pa.int32()), pa.array(np.concatenate(keys)))
                yield pa.RecordBatch.from_arrays([nodes, pa.array([len(x) for x in sets], pa.int32()), *words, lists], ["node", "size", "p0", "p1", "p2", "p3", "keys"])

    return map_batches(texts.select("node", "text"), run, "node long, size int, p0 long, p1 long, p2 long, p3 long, keys array<long>")


def _may_reach(a: str, b: str, similarity: float) -> Column:
    """What no pair of sets of that similarity fails: sizes in the ratio, and no more odd buckets than differences allow."""
    sa, sb = F.col(f"{a}.size"), F.col(f"{b}.size")
    odd = sum((F.bit_count(F.col(f"{a}.p{j}").bitwiseXOR(F.col(f"{b}.p{j}"))) for j in range(4)), F.lit(0))
    return (F.least(sa, sb) >= similarity * F.greatest(sa, sb) - 1e-9) & (odd <= (sa + sb) * ((1 - similarity) / (1 + similarity)) + 1e-6)


def _one_bucket_each(members: DataFrame) -> DataFrame:
    """Of buckets with the same members one stays: any shared shingle of a pair brings it up, and bounds it, as well as another.

    Equal sets are told by count, ends and the sum of hashes of their members.
    """
    same = F.count("*").alias("n"), F.min("node").alias("first"), F.max("node").alias("last"), F.sum(F.xxhash64("node").cast("decimal(38,0)")).alias("sum")
    kept = members.groupBy("key").agg(*same).groupBy("n", "first", "last", "sum").agg(F.min("key").alias("key")).select("key")
    return materialize(members.join(sized(materialize(kept, "buckets")), "key", "left_semi"), "members")


def fingerprint_links(texts: DataFrame, *, shingle: int = 5, similarity: float = 0.8, max_bits: int = NEAR) -> DataFrame:
    """Edges (a, b) of texts (node, text) whose fingerprints differ in at most ``max_bits`` bits and whose shingles have that Jaccard similarity."""
    found = fingerprints(texts, id_col="node", shingle=shingle)
    nodes = materialize(found.select(F.col("doc_id").alias("node"), "fp", "size"), "fingerprints")
    return links(nodes, max_bits, check=lambda pairs: similar(pairs, texts, shingle=shingle, similarity=similarity))


def similar_links(texts: DataFrame, n: int, *, shingle: int = 5, similarity: float = 0.8) -> DataFrame:
    """Edges (a, b) that connect exactly the texts (node, text) which chains of pairs of that Jaccard similarity connect.

    Pairs near by fingerprint come first.  What fingerprints miss is found among
    texts of different groups that share a shingle of their prefixes, which no
    such pair fails to do.  There every text meets one other at first: of those it shares such a
    shingle with, the one with the smallest share of shingles of its own, as an
    unchanged text has among its copies.  That connects most copies for one look each.  Buckets
    that are not one group by then, of whatever size, are left to :func:`open_links`.
    """
    near = materialize(fingerprint_links(texts, shingle=shingle, similarity=similarity), "near")
    common = common_shingles(texts, n, shingle)
    for _ in range(ROUNDS):  # what a round of prefixes finds in several texts goes behind what it does not
        common = known_shared(prefixes(texts, common, shingle=shingle, similarity=similarity).select(F.explode("keys").alias("key")), common)
    sets = materialize(prefixes(texts, common, shingle=shingle, similarity=similarity), "prefixes")
    keys = sets.select("node", F.explode("keys").alias("key"))
    shared = materialize(keys.groupBy("key").count().where("count > 1").select("key"), "shared")
    members = materialize(keys.join(sized(shared), "key"), "members")
    counts = sized(materialize(members.groupBy("node").agg(F.count("*").alias("n")), "sharing"))
    info = sized(materialize(sets.join(counts, "node").withColumn("own", 1 - F.col("n") / F.size("keys")).drop("keys", "n"), "info"))
    members = _one_bucket_each(members).join(info.select("node", "size", "own"), "node")

    def look(pairs: DataFrame, tag: str) -> DataFrame:
        a, b = info.alias("x"), info.alias("y")
        able = pairs.join(a, F.col("a") == F.col("x.node")).join(b, F.col("b") == F.col("y.node")).where(_may_reach("x", "y", similarity)).select("a", "b")
        return similar(materialize(able, tag), texts, shingle=shingle, similarity=similarity)

    leads = sized(materialize(members.groupBy("key").agg(F.min(F.struct("own", "node")).alias("lead")), "leads"))
    one = members.join(leads, "key").where("node != lead.node").groupBy("node").agg(F.min("lead").alias("lead")).select(F.col("lead.node").alias("a"), F.col("node").alias("b"))
    sure = near.union(look(one, "ones"))
    roots = sized(materialize(components(sure), "roots"))
    rows = members.select("key", "node", "size", "own").join(roots, "node", "left").withColumn("group", F.coalesce("root", "node")).drop("root")
    rows = materialize(rows, "grouped")
    return open_links(rows, texts, shingle=shingle, similarity=similarity).union(sure)


def open_links(rows: DataFrame, texts: DataFrame, *, shingle: int, similarity: float) -> DataFrame:
    """Edges that connect the similar texts of a bucket which are in different groups; ``rows`` is a materialized (key, node, size, own, group).

    Near copies of one text share most of it, so their buckets are large though
    few pairs are similar.  Members of a bucket and of similar sizes are told
    by what sets them apart from one of them, the leader: the text with the
    smallest share ``own`` of shingles that no other has.  With d the number of
    such shingles and q = (1 - similarity) / (1 + similarity), a text is similar
    to the leader if e = d - q * size is at most q * the leader's size, and two
    are similar to each other just when they have (e + e') / 2 of those
    shingles in common.  Two that are not both connected to the leader have
    e + e' > 0, so prefixes of what sets them apart bring them together:
    there shingles that nobody else has, which copies get by their own edits,
    are left out, and what copies have in common does not occur at all.
    """
    q = (1 - similarity) / (1 + similarity)
    rank = F.floor(F.log(F.greatest("size", F.lit(1)).cast("double")) / F.log(F.lit(1.01 / similarity))).cast("int")
    slots = rows.withColumn("slot", F.explode(F.array(rank - 1, rank)))  # similar sizes are one rank apart at most
    leads = slots.groupBy("key", "slot").agg(F.min(F.struct("own", "node", "group")).alias("lead"), F.min("group").alias("lo"), F.max("group").alias("hi"))
    leads = sized(materialize(leads.where("lo < hi").select("key", "slot", F.col("lead.node").alias("lead"), F.col("lead.group").alias("lead_group")), "leads"))
    led = materialize(slots.join(leads, ["key", "slot"]).where("node != lead").select("lead", "node", "group", (F.col("group") == F.col("lead_group")).alias("core")).distinct(), "led")
    asked = sized(materialize(led.select("node").union(led.select("lead")).distinct(), "asked"))
    sets = materialize(shingle_sets(texts.join(asked, "node", "left_semi"), "node", shingle), "shingles")
    pairs = led.join(sets.toDF("node", "sa"), "node").join(sets.toDF("lead", "sb"), "lead").select("lead", "node", "group", "core", "sa", "sb")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for at in range(0, batch.num_rows, 256):
                b = batch.slice(at, 256)
                size, e, linked, apart = [], [], [], []
                for x, y in zip(b.column(4), b.column(5)):
                    x, y = np.frombuffer(x.as_buffer(), "<u4"), np.frombuffer(y.as_buffer(), "<u4")
                    apart.append(np.setxor1d(x, y, assume_unique=True).view("<i4"))
                    size.append(len(x))
                    e.append(len(apart[-1]) - q * len(x))
                    linked.append(e[-1] <= q * len(y) + 1e-6)
                core = np.array(linked, bool) | b.column(3).to_numpy(zero_copy_only=False)
                least = [(v + (1 if c else -1) * q * (len(y.as_buffer()) // 4)) / 2 for v, c, y in zip(e, core, b.column(5))]
                lists = pa.ListArray.from_arrays(pa.array(np.cumsum([0, *map(len, apart)]), pa.int32()), pa.array(np.concatenate(apart)))
                yield pa.RecordBatch.from_arrays([*b.columns[:3], pa.array(core), pa.array(linked, pa.bool_()), pa.array(size, pa.int32()), pa.array(e, pa.float64()), pa.array(least, pa.float64()), lists], ["lead", "node", "group", "core", "linked", "size", "e", "least", "apart"])

    told = materialize(map_batches(pairs, run, "lead long, node long, group long, core boolean, linked boolean, size int, e double, least double, apart array<int>"), "apart")
    each = told.select("lead", "node", F.explode("apart").alias("h"))
    common = materialize(each.groupBy("lead", "h").agg(F.count("*").alias("n")).where("n > 1"), "common")
    own = Window.partitionBy("lead", "node")
    held = each.join(common, ["lead", "h"]).withColumns({"pos": F.row_number().over(own.orderBy("n", "h")), "held": F.count("*").over(own)})
    held = held.join(told.drop("apart", "linked"), ["lead", "node"]).where(F.col("pos") <= F.col("held") - F.greatest(F.lit(1), F.ceil(F.col("least") - 1e-6)) + 1)
    held = materialize(held, "held")
    x, y = held.alias("x"), held.alias("y")
    sa, sb, i, j = F.col("x.size"), F.col("y.size"), F.col("x.pos"), F.col("y.pos")
    most = F.least(i, j) + F.least(F.col("x.held") - i, F.col("y.held") - j)  # shared shingles before, at and after this one
    able = (F.least(sa, sb) >= similarity * F.greatest(sa, sb) - 1e-9) & (most >= (F.col("x.e") + F.col("y.e")) / 2 - 1e-6)
    able = able & (F.col("x.node") < F.col("y.node")) & (F.col("x.group") != F.col("y.group")) & ~(F.col("x.core") & F.col("y.core"))
    rest = x.join(y, (F.col("x.lead") == F.col("y.lead")) & (F.col("x.h") == F.col("y.h")) & able)
    rest = materialize(rest.select(F.col("x.node").alias("a"), F.col("y.node").alias("b")).distinct(), "pairs")
    return similar(rest, texts, shingle=shingle, similarity=similarity).union(told.where("linked").select(F.col("lead").alias("a"), F.col("node").alias("b")))


def similar(pairs: DataFrame, texts: DataFrame, *, shingle: int = 5, similarity: float = 0.8) -> DataFrame:
    """Of pairs (a, b), those whose texts (node, text) have a Jaccard similarity of word shingles of at least ``similarity``."""
    asked = sized(materialize(pairs.select(F.col("a").alias("node")).union(pairs.select(F.col("b").alias("node"))).distinct(), "asked"))
    hashes = materialize(shingle_sets(texts.join(asked, "node", "left_semi"), "node", shingle), "shingles")
    rows = pairs.join(hashes.toDF("a", "sa"), "a").join(hashes.toDF("b", "sb"), "b")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            keep = []
            for x, y in zip(b.column(2), b.column(3)):
                x, y = np.frombuffer(x.as_buffer(), "<u4"), np.frombuffer(y.as_buffer(), "<u4")
                both = np.intersect1d(x, y, assume_unique=True).size
                keep.append(both >= similarity * (len(x) + len(y) - both) - 1e-9)
            b = b.filter(pa.array(keep, pa.bool_()))
            yield pa.RecordBatch.from_arrays(b.columns[:2], ["a", "b"])

    return materialize(map_batches(rows.select("a", "b", "sa", "sb"), run, "a long, b long"), "similar")


def keep_one(docs: DataFrame, *, id_col: str = "doc_id", text_col: str = "text", shingle: int = 5, similarity: float = 0.8) -> DataFrame:
    """One document of each near-duplicate group: the one with the smallest id (nulls last).

    A link is a Jaccard similarity of ``shingle``-word shingles of at least
    ``similarity``; no such pair is missed (``similar_links``).  Equal texts
    are one node from the start, repeated rows leave one, and texts without
    words are copies of each other.  All columns stay.
    """
    base = docs.withColumns({"__id": F.col(id_col).cast("long"), "__key": F.xxhash64(text_col)})
    with scratch(), small_batches(docs.sparkSession):
        rows = materialize(base.select(F.col("__id").alias("doc_id"), F.col("__key").alias("text_key")), "keys")
        nodes = materialize(rows.groupBy(F.col("text_key").alias("node")).agg(F.min("doc_id").alias("least")), "nodes")
        texts = base.join(sized(nodes.toDF("__node", "__least")), (F.col("__key") == F.col("__node")) & F.col("__id").eqNullSafe(F.col("__least")), "left_semi").select(F.col("__key").alias("node"), F.col(text_col).alias("text"))
        edges = similar_links(texts, nodes.count(), shingle=shingle, similarity=similarity)
        labelled = nodes.join(components(edges), "node", "left").select("node", "least", F.coalesce("root", "node").alias("root"))
        chosen = labelled.groupBy("root").agg(F.min(F.struct(F.col("least").isNull(), "least", "node")).alias("c")).select(F.col("c.least").alias("__id"), F.col("c.node").alias("__key"))
        chosen = materialize(chosen, "chosen", keep=True)
        again = rows.groupBy("doc_id", "text_key").count().where("count > 1").isEmpty()
    kept = base.join(sized(chosen), null_safe(base, chosen, ["__id", "__key"]), "left_semi")
    kept = kept if again else kept.dropDuplicates(["__id", "__key"])
    return kept.drop("__id", "__key")
