"""Approximate nearest neighbours with a hierarchical k-means tree and best-bin-first search.

The top of the tree is fitted on a bounded sample; every row is put into a
leaf, and leaves of many rows are split again where they are, on a sample of
each, until they are small, so leaves do not grow with the table.  A query
walks the top through a priority queue, nearest centre first, opens the best
bins below level by level, and visits as many leaves as calibration found to
reach the wanted recall.  Leaves are scanned in blocks, distances are exact on
the original vectors.
"""

from __future__ import annotations

import heapq
from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import materialize, sized


@dataclass(frozen=True)
class Settings:
    """``sample`` bounds the rows the top is fitted on, ``fit`` those for a split below it, ``probes`` the queries for calibration.

    Leaves of more than ``full`` rows are split; only one position cannot be.
    ``beam`` bins stay open for a query between levels; it is doubled until
    calibration reaches ``recall``.
    """

    sample: int = 8192
    branch: int = 12
    leaf: int = 40
    full: int = 256
    fit: int = 1024
    beam: int = 64
    probes: int = 96
    recall: float = 0.97
    block: int = 2048
    asks: int = 4096
    seed: int = 11


@dataclass
class Tree:
    centres: list[np.ndarray] = field(default_factory=list)  # of the children of each inner node
    children: list[list[int]] = field(default_factory=list)  # an inner node, or -1 - leaf
    leaves: int = 0

    def assign(self, X: np.ndarray) -> np.ndarray:
        """Leaf of every row by the nearest centre at each level."""
        out = np.zeros(len(X), np.int64)
        if not self.centres:
            return out
        todo = [(0, np.arange(len(X)))]
        while todo:
            node, rows = todo.pop()
            near = squares(X[rows], self.centres[node]).argmin(1)
            for k, child in enumerate(self.children[node]):
                own = rows[near == k]
                if not len(own):
                    continue
                if child < 0:
                    out[own] = -1 - child
                else:
                    todo.append((child, own))
        return out

    def order(self, q: np.ndarray) -> Iterator[tuple[float, int]]:
        """(squared distance of its centre, leaf), best bin first: the nearest centre in the queue is opened next."""
        if not self.centres:
            yield 0.0, 0
            return
        queue: list[tuple[float, int, int]] = [(0.0, 0, 0)]
        tie = 0
        while queue:
            far, _, node = heapq.heappop(queue)
            if node < 0:
                yield far, -1 - node
                continue
            for d, child in zip(squares(q[None], self.centres[node])[0].tolist(), self.children[node]):
                tie += 1
                heapq.heappush(queue, (d, tie, child))


def squares(X: np.ndarray, Y: np.ndarray) -> np.ndarray:
    return np.maximum((X * X).sum(1)[:, None] + (Y * Y).sum(1)[None] - 2 * X @ Y.T, 0)


def grow(X: np.ndarray, s: Settings) -> Tree:
    """k-means at every level until a node has few rows or only one position."""
    tree, rng = Tree(), np.random.default_rng(s.seed)

    def build(rows: np.ndarray) -> int:
        own = X[rows]
        spots = np.unique(own, axis=0)
        if len(rows) <= s.leaf or len(spots) < 2:
            tree.leaves += 1
            return -tree.leaves
        C = clusters(own, spots, s, rng)
        if len(C) < 2:
            tree.leaves += 1
            return -tree.leaves
        near = squares(own, C).argmin(1)
        node = len(tree.centres)
        tree.centres.append(C)
        tree.children.append([])
        kids = [build(rows[near == k]) for k in range(len(C))]
        tree.children[node] = kids
        return node

    if len(X):
        build(np.arange(len(X)))
    tree.leaves = max(tree.leaves, 1)
    return tree


def nearest(X: np.ndarray, ids: np.ndarray, Q: np.ndarray, qids: np.ndarray, k: int) -> list[tuple[np.ndarray, np.ndarray]]:
    """For each query the k nearest rows other than its own: (ids, distances), ties to the smaller id.

    A matrix product picks what may be among the nearest; those are measured by differences.
    """
    out = []
    norms = (X * X).sum(1)
    for lo in range(0, len(Q), 256):
        q = Q[lo : lo + 256]
        rough = norms[None] + (q * q).sum(1)[:, None] - 2 * q @ X.T
        slack = 1e-9 * (norms.max(initial=0) + (q * q).sum(1) + 1e-300)
        for r, (row, own) in enumerate(zip(rough, qids[lo : lo + 256])):
            row[ids == own] = np.inf
            kth = np.partition(row, k - 1)[k - 1] if len(row) > k else np.inf
            at = np.flatnonzero((row <= kth + slack[r]) & (ids != own))
            d = np.sqrt(((X[at] - q[r]) ** 2).sum(1))
            best = np.lexsort((ids[at], d))[:k]
            out.append((ids[at][best], d[best]))
    return out


def valid_vectors(table: DataFrame, id_col: str, vector_col: str) -> DataFrame:
    """(vec_id, v) of rows whose vector takes part: not null, not zero, no null or non-finite component, of the usual length."""
    v = F.col(vector_col).cast("array<double>")
    rows = table.select(F.col(id_col).cast("long").alias("vec_id"), v.alias("v"))
    good = F.col("v").isNotNull() & F.forall("v", lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) != float("inf"))) & F.exists("v", lambda x: x != 0) & F.col("vec_id").isNotNull()
    rows = rows.where(good)
    usual = rows.groupBy(F.size("v").alias("n")).count().orderBy(F.desc("count"), "n").first()
    return rows.where(F.size("v") == (usual.n if usual else 0))


def matrix(column: pa.Array) -> np.ndarray:
    flat = column.flatten().to_numpy(zero_copy_only=False)
    return flat.reshape(len(column), -1) if len(column) else np.zeros((0, 1))


def _exact(rows: DataFrame, Q: np.ndarray, qids: np.ndarray, k: int) -> list[list[int]]:
    """Ids of the true nearest of a bounded set of queries, from one scan of all rows."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            ids, X = b.column(0).to_numpy(), matrix(b.column(1))
            found = nearest(X, ids, Q, qids, k)
            q = np.repeat(np.arange(len(Q)), [len(i) for i, _ in found])
            at = np.concatenate([i for i, _ in found]) if found else np.zeros(0, np.int64)
            yield pa.RecordBatch.from_arrays([pa.array(q), pa.array(at), pa.array(np.concatenate([d for _, d in found]) if found else np.zeros(0))], ["q", "vec_id", "d"])

    w = Window.partitionBy("q").orderBy("d", "vec_id")
    best = rows.mapInArrow(run, "q long, vec_id long, d double").withColumn("rank", F.row_number().over(w)).where(F.col("rank") <= k).collect()
    out: list[list[int]] = [[] for _ in Q]
    for r in best:
        out[r.q].append(r.vec_id)
    return out


def _dealt(rows: DataFrame, counts: DataFrame, size: int, *by: str) -> DataFrame:
    """Adds ``block`` to rows of a path, so that a block has about ``size`` of them."""
    number = F.pmod(F.xxhash64(*by), F.ceil(F.col("n") / size).cast("long")).cast("int")
    return rows.join(sized(counts), "path").withColumn("block", number).drop("n")


def _copied(rows: DataFrame, counts: DataFrame, size: int) -> DataFrame:
    """A few rows of a path, once for each block of the other side."""
    return rows.join(sized(counts), "path").withColumn("block", F.explode(F.sequence(F.lit(0), (F.ceil(F.col("n") / size) - 1).cast("int")))).drop("n")


def _sizes(rows: DataFrame, tag: str) -> DataFrame:
    return materialize(rows.groupBy("path").agg(F.count("*").alias("n")), tag)


def split_leaves(held: DataFrame, s: Settings, level: int) -> tuple[DataFrame, DataFrame] | None:
    """Split every full leaf of materialized (path, vec_id, v) once: the rows with their new paths, and (path, child, centre); None when no leaf can be."""
    counts = _sizes(held, "leaf-sizes").where(F.col("n") > s.full)
    if counts.isEmpty():
        return None
    share = F.pmod(F.xxhash64("vec_id", F.lit(level)), F.col("n")) < s.fit
    some = held.join(sized(counts), "path").where(share).select("path", "vec_id", "v")

    def fit(table: pa.Table) -> pa.Table:
        order = np.argsort(table["vec_id"].to_numpy(), kind="stable")
        X = matrix(table["v"].combine_chunks())[order]
        spots = np.unique(X, axis=0)
        C = spots[:0] if len(spots) < 2 else clusters(X, spots, s, np.random.default_rng(s.seed + level))
        C = C if len(C) > 1 else C[:0]
        return pa.table({"path": pa.array([table["path"][0].as_py()] * len(C), pa.int64()), "child": pa.array(range(len(C)), pa.int32()), "centre": pa.array(list(C), pa.list_(pa.float64()))})

    nodes = materialize(some.groupBy("path").applyInArrow(fit, "path long, child int, centre array<double>"), "nodes")
    if nodes.isEmpty():
        return None
    counts = materialize(counts.join(sized(nodes.select("path").distinct()), "path", "left_semi"), "split")

    def put(rows: pa.Table, own: pa.Table) -> pa.Table:
        C = matrix(own.sort_by("child")["centre"].combine_chunks())
        return pa.table({"path": rows["path"], "child": pa.array(squares(matrix(rows["v"].combine_chunks()), C).argmin(1), pa.int32()), "vec_id": rows["vec_id"], "v": rows["v"]}) if rows.num_rows else empty

    empty = pa.table({"path": pa.array([], pa.int64()), "child": pa.array([], pa.int32()), "vec_id": pa.array([], pa.int64()), "v": pa.array([], pa.list_(pa.float64()))})
    keys = ["path", "block"]
    left, right = _dealt(held, counts, 8 * s.block, "vec_id").groupBy(*keys), _copied(nodes, counts, 8 * s.block).groupBy(*keys)
    moved = left.cogroup(right).applyInArrow(put, "path long, child int, vec_id long, v array<double>")
    stay = held.join(sized(counts.select("path")), "path", "left_anti")
    return materialize(moved.select(F.xxhash64("path", "child").alias("path"), "vec_id", "v").unionByName(stay), "leaves"), nodes


def clusters(X: np.ndarray, spots: np.ndarray, s: Settings, rng: np.random.Generator) -> np.ndarray:
    """Centres of the non-empty clusters of k-means from random distinct rows."""
    C = spots[rng.choice(len(spots), min(s.branch, len(spots)), replace=False)]
    for _ in range(12):
        near = squares(X, C).argmin(1)
        C = np.stack([X[near == k].mean(0) if (near == k).any() else C[k] for k in range(len(C))])
    return C[np.unique(squares(X, C).argmin(1))]


def frontier(asked: DataFrame, top: Tree, levels: list[DataFrame], beam: int, s: Settings) -> DataFrame:
    """(query_id, q, path, d): for every query its ``beam`` best leaves, nearest centre first, from the top's priority queue down the levels."""
    shared = asked.sparkSession.sparkContext.broadcast(top)

    def walk(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            which, leaf, far = [], [], []
            for r, q in enumerate(matrix(b.column(1))):
                for (d, x), _ in zip(shared.value.order(q), range(beam)):
                    which.append(r)
                    leaf.append(x)
                    far.append(d)
            yield pa.RecordBatch.from_arrays([*(c.take(pa.array(which, pa.int64())) for c in b.columns), pa.array(leaf, pa.int64()), pa.array(far, pa.float64())], ["query_id", "q", "path", "d"])

    shape = "query_id long, q array<double>, path long, d double"
    now = asked.select("vec_id", "v").mapInArrow(walk, shape)

    def step(rows: pa.Table, own: pa.Table) -> pa.Table:
        if not rows.num_rows:
            return pa.table({"query_id": pa.array([], pa.int64()), "q": pa.array([], pa.list_(pa.float64())), "path": pa.array([], pa.int64()), "child": pa.array([], pa.int32()), "d": pa.array([], pa.float64())})
        own = own.sort_by("child")
        d = squares(matrix(rows["q"].combine_chunks()), matrix(own["centre"].combine_chunks()))
        at = pa.array(np.repeat(np.arange(d.shape[0]), d.shape[1]))
        return pa.table({"query_id": rows["query_id"].take(at), "q": rows["q"].take(at), "path": rows["path"].take(at), "child": pa.array(np.tile(own["child"].to_numpy(), d.shape[0]), pa.int32()), "d": pa.array(d.ravel())})

    best = F.row_number().over(Window.partitionBy("query_id").orderBy("d", "path"))
    for nodes in levels:
        now = materialize(now, "frontier")
        opened = sized(materialize(nodes.select("path").distinct(), "opened"))
        counts = _sizes(now.join(opened, "path", "left_semi"), "askers")
        keys = ["path", "block"]
        left, right = _dealt(now, counts, s.asks, "query_id").groupBy(*keys), _copied(nodes, counts, s.asks).groupBy(*keys)
        below = left.cogroup(right).applyInArrow(step, "query_id long, q array<double>, path long, child int, d double")
        now = now.join(opened, "path", "left_anti").select("query_id", "q", "path", "d").unionByName(below.select("query_id", "q", F.xxhash64("path", "child").alias("path"), "d"))
        now = now.withColumn("place", best).where(F.col("place") <= beam).drop("place")
    return now


def search(table: DataFrame, queries: DataFrame | None = None, *, k: int = 10, id_col: str = "vec_id", vector_col: str = "embedding", every: int = 100, s: Settings = Settings()) -> DataFrame:
    """(query_id, rank, vec_id, score) of the k nearest found for each query, nearest first, ties to the smaller id.

    Queries are the rows of ``queries`` or those whose id ``every`` divides;
    rows with a query's id are not its candidates.  Vectors that are null, zero
    or of another length, or hold a null or a non-finite component, take no
    part.  Of rows that repeat an id and vector one counts.  An empty table gives no rows.
    """
    spark = table.sparkSession
    rows = materialize(valid_vectors(table, id_col, vector_col), "vectors")
    asked = rows.where(F.col("vec_id") % every == 0) if queries is None else valid_vectors(queries, id_col, vector_col)
    n = rows.count()
    share = F.pmod(F.xxhash64("vec_id"), F.lit(1 << 30)) < F.lit(int(min(1.0, s.sample / max(n, 1)) * (1 << 30)))
    got = rows.where(share).orderBy(F.xxhash64("vec_id"), "vec_id").toArrow()
    X = matrix(got["v"].combine_chunks()) if got.num_rows else np.zeros((0, 1))
    top = grow(X, s)
    shared = spark.sparkContext.broadcast(top)

    def put(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            yield pa.RecordBatch.from_arrays([pa.array(shared.value.assign(matrix(b.column(1)))), *b.columns], ["path", "vec_id", "v"])

    held, levels = materialize(rows.mapInArrow(put, "path long, vec_id long, v array<double>"), "leaves"), []
    while (more := split_leaves(held, s, len(levels) + 1)) is not None:
        held = more[0]
        levels.append(more[1])
    beam, visits = _calibrate(rows, held, top, levels, X, got["vec_id"].to_pylist() if got.num_rows else [], k, s, None if queries is not None else every)
    counts = _sizes(held, "leaf-sizes")
    near = frontier(asked, top, levels, beam, s).join(sized(counts), "path")
    order = Window.partitionBy("query_id").orderBy("d", "path")
    near = near.withColumns({"place": F.row_number().over(order), "before": F.sum("n").over(order.rowsBetween(Window.unboundedPreceding, Window.currentRow)) - F.col("n")})
    visitors = materialize(near.where((F.col("place") <= visits) | (F.col("before") <= 4 * k)).select("path", "query_id", "q"), "visits")
    groups = _sizes(visitors, "visitors").withColumn("groups", F.ceil(F.col("n") / s.asks).cast("int")).drop("n")
    bounds = materialize(counts.join(sized(groups), "path").select("path", F.ceil(F.col("n") / s.block).cast("int").alias("blocks"), "groups"), "bounds")
    left = held.join(sized(bounds), "path").select("path", "vec_id", "v", F.pmod(F.xxhash64("vec_id"), F.col("blocks").cast("long")).cast("int").alias("block"), F.explode(F.sequence(F.lit(0), F.col("groups") - 1)).alias("group"))
    right = visitors.join(sized(bounds), "path").select("path", "query_id", "q", F.pmod(F.xxhash64("query_id"), F.col("groups").cast("long")).cast("int").alias("group"), F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)).alias("block"))

    def scan(rows_in, asks):
        empty = pa.table({"query_id": pa.array([], pa.int64()), "vec_id": pa.array([], pa.int64()), "score": pa.array([], pa.float64())})
        if not rows_in.num_rows or not asks.num_rows:
            return empty
        qids = asks["query_id"].to_numpy()
        best = nearest(matrix(rows_in["v"].combine_chunks()), rows_in["vec_id"].to_numpy(), matrix(asks["q"].combine_chunks()), qids, k)
        return pa.table({"query_id": np.repeat(qids, [len(i) for i, _ in best]), "vec_id": np.concatenate([i for i, _ in best]), "score": np.concatenate([d for _, d in best])})

    keys = ["path", "block", "group"]
    found = left.groupBy(*keys).cogroup(right.groupBy(*keys)).applyInArrow(scan, "query_id long, vec_id long, score double").distinct()
    w = Window.partitionBy("query_id").orderBy("score", "vec_id")
    return found.withColumn("rank", F.row_number().over(w)).where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")


def _calibrate(rows: DataFrame, held: DataFrame, top: Tree, levels: list[DataFrame], X: np.ndarray, ids: list[int], k: int, s: Settings, every: int | None) -> tuple[int, int]:
    """(beam, visits): open bins between levels and leaves to visit so that the wanted share of the probes' true neighbours is met."""
    probe = [i for i, v in enumerate(ids) if every is None or v % every][: s.probes]
    if not probe:
        return s.beam, 1
    spark = rows.sparkSession
    true = _exact(rows, X[probe], np.array([ids[i] for i in probe], np.int64), k)
    wanted = spark.createDataFrame([(q, int(v)) for q, found in enumerate(true) for v in found], "query_id long, vec_id long")
    if wanted.isEmpty():
        return s.beam, 1
    asked = spark.createDataFrame([(q, X[i].tolist()) for q, i in enumerate(probe)], "vec_id long, v array<double>")
    homes = held.select("path", "vec_id").join(F.broadcast(wanted), "vec_id").select("query_id", "vec_id", "path").distinct().collect()
    beam = s.beam
    while True:
        order: dict[int, list[int]] = {}
        for r in frontier(asked, top, levels, beam, s).select("query_id", "path", "d").orderBy("query_id", "d", "path").collect():
            order.setdefault(r.query_id, []).append(r.path)
        place = {(q, p): i for q, paths in order.items() for i, p in enumerate(paths, 1)}
        need = np.sort([place.get((r.query_id, r.path), np.inf) for r in homes])
        visits = need[min(len(need) - 1, int(np.ceil(s.recall * len(need))) - 1)]
        if np.isfinite(visits) or max(map(len, order.values()), default=0) < beam:
            return beam, int(visits) if np.isfinite(visits) else beam
        beam *= 2


def digest(embeddings: DataFrame) -> DataFrame:
    """The ten nearest found for every vector whose id is divisible by 100."""
    return search(embeddings.select("vec_id", "embedding"))
