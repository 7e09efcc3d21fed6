"""Graph metrics: random graphs, co-purchase graphs, and shortest-path rows."""

from __future__ import annotations

import heapq
import math

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def shortest_paths(edges: DataFrame, nodes: list[int], most_edges: int = 5_000_000) -> DataFrame:
    """(ord, coords): coords is [own position, distance to the node at position 0, 1, ...]; unreachable nodes get a distance above all others.

    Edges (src, dst, w) are undirected.  The adjacency goes to every task, so its
    size is checked; sources are spread over tasks, one search each.
    """
    if edges.limit(most_edges + 1).count() > most_edges:
        raise ValueError(f"more than {most_edges} edges")
    spark = edges.sparkSession
    number = {v: i for i, v in enumerate(nodes)}
    near: list[list[tuple[int, int]]] = [[] for _ in nodes]
    far = 1
    for r in edges.select("src", "dst", F.col("w").cast("bigint").alias("w")).toLocalIterator():
        if r.src in number and r.dst in number:
            near[number[r.src]].append((number[r.dst], r.w))
            near[number[r.dst]].append((number[r.src], r.w))
            far += r.w
    shared = spark.sparkContext.broadcast(near)

    def run(batches):
        adjacency = shared.value
        for b in batches:
            out = []
            for s in b.column(1).to_pylist():
                dist, queue = [far] * len(adjacency), [(0, s)]
                dist[s] = 0
                while queue:
                    d, u = heapq.heappop(queue)
                    if d > dist[u]:
                        continue
                    for v, w in adjacency[u]:
                        if d + w < dist[v]:
                            dist[v] = d + w
                            heapq.heappush(queue, (d + w, v))
                out.append([s, *dist])
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(out, pa.list_(pa.int64()))], ["ord", "coords"])

    sources = spark.createDataFrame(list(zip(nodes, range(len(nodes)))), "ord bigint, at bigint").repartition(16)
    return sources.mapInArrow(run, "ord bigint, coords array<bigint>")


def random_edges(n: int, seed: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(src, dst, w): every pair an edge with chance 2 ln n / n, weights whole thousandths of (0, 1000)."""
    rng = np.random.default_rng([seed, n])
    i, j = np.triu_indices(n, 1)
    on = rng.random(len(i)) < 2 * math.log(max(n, 2)) / n
    return i[on], j[on], rng.integers(1, 1_000_000, len(i))[on]


def random_graph(spark: SparkSession, n: int, seed: int) -> DataFrame:
    """The edges as a table."""
    return spark.createDataFrame(list(zip(*(x.tolist() for x in random_edges(n, seed)))), "src bigint, dst bigint, w bigint")


def path_matrix(n: int, src: np.ndarray, dst: np.ndarray, w: np.ndarray) -> np.ndarray:
    """All shortest paths of a small graph; unreachable pairs are farther than all weights together."""
    D = np.full((n, n), 1 + int(w.sum()), np.int64)
    np.fill_diagonal(D, 0)
    D[src, dst] = D[dst, src] = w
    for k in range(n):
        D = np.minimum(D, D[:, k : k + 1] + D[k])
    return D


def random_groups(n: int, m: int, seed: int) -> list[int]:
    return np.random.default_rng([seed, n, m]).integers(0, m, n).tolist()


COPURCHASE = """
SELECT DISTINCT a.l_partkey AS src, b.l_partkey AS dst, 1 + (a.l_partkey * 7919 + b.l_partkey * 104729) % 1000 AS w
FROM {lineitem} a JOIN {lineitem} b ON a.l_orderkey = b.l_orderkey AND a.l_partkey < b.l_partkey
WHERE a.l_partkey < 350 AND b.l_partkey < 350
"""

#: (ord, grp, coords) of the parts below 350 by paths through one more node at a time, in DuckDB.
PATHS_SQL = """
WITH RECURSIVE e AS MATERIALIZED ({edges}), node AS MATERIALIZED (SELECT p_partkey AS v, row_number() OVER (ORDER BY p_partkey) - 1 AS i FROM part WHERE p_partkey < 350),
ij AS MATERIALIZED (SELECT a.i AS i, b.i AS j, w FROM e JOIN node a ON a.v = src JOIN node b ON b.v = dst),
top AS MATERIALIZED (SELECT CAST(1 + sum(w) AS BIGINT) AS far FROM ij),
m AS MATERIALIZED (SELECT x.i, list(CAST(CASE WHEN x.i = y.i THEN 0 ELSE coalesce(w, far) END AS BIGINT) ORDER BY y.i) AS d FROM node x CROSS JOIN node y CROSS JOIN top LEFT JOIN (SELECT i, j, w FROM ij UNION ALL SELECT j, i, w FROM ij) k ON k.i = x.i AND k.j = y.i GROUP BY x.i),
fw AS (SELECT CAST(0 AS BIGINT) AS k, i, d FROM m
UNION ALL SELECT a.k + 1, a.i, list_transform(list_zip(a.d, b.d), lambda z: least(z[1], a.d[a.k + 1] + z[2])) FROM fw a, (SELECT d FROM fw WHERE i = k) b WHERE a.k < (SELECT count(*) FROM node))
SELECT node.v AS ord, CAST(node.v % 5 AS INTEGER) AS grp, list_prepend(fw.i, fw.d) AS coords FROM fw JOIN node ON node.i = fw.i WHERE fw.k = (SELECT count(*) FROM node)
"""

#: The edges between all parts.
COPURCHASE_ALL = COPURCHASE.replace("WHERE a.l_partkey < 350 AND b.l_partkey < 350\n", "")

#: Graphs of all line items: a part belongs to graph key mod 20 and stands for vertex (key div 20) mod 500 of it; parts of one order are linked.
FOLDED = """
WITH l AS (SELECT DISTINCT l_orderkey AS o, l_partkey % 20 AS graph, CAST(floor(l_partkey / 20) AS BIGINT) % 500 AS v FROM {lineitem})
SELECT DISTINCT a.graph, a.v AS src, b.v AS dst, 1 + (a.v * 7919 + b.v * 104729 + a.graph * 611953) % 999983 AS w FROM l a JOIN l b ON a.o = b.o AND a.graph = b.graph AND a.v < b.v
"""
