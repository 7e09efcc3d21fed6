"""The instance family on which sending subsets of the input cannot beat ratio 4, and a simulator of such protocols."""

from __future__ import annotations

import math
from itertools import combinations_with_replacement

import numpy as np
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

#: The classes of points, seven critical ones and three large sets, and the unit edges between them (hub is no point).
CLASSES = ("a*", "b1*", "b2*", "c*", "a", "b", "c", "S1", "S2", "S3")
EDGES = (
    ("a*", "b1*"), ("a*", "b2*"), ("a*", "a"), ("a*", "S1"), ("b1*", "c*"), ("b1*", "b"), ("b1*", "S2"), ("b2*", "c*"), ("b2*", "b"), ("b2*", "S2"), ("c*", "c"), ("c*", "S3"),
    ("hub", "S1"), ("hub", "S2"), ("hub", "S3"),
)
#: The critical points that go with each part of S1, S2, S3.
SHARED = (("b1*", "b2*", "a"), ("a*", "c*", "b"), ("b1*", "b2*", "c"))
PROCESSORS = 9


def class_distances() -> np.ndarray:
    """Distances between distinct points by class: shortest paths over the edges, with two members for each large set."""
    nodes = [*CLASSES, "S1'", "S2'", "S3'", "hub"]
    d = np.full((len(nodes), len(nodes)), 99)
    np.fill_diagonal(d, 0)
    for u, v in EDGES:
        for x in (u, u + "'"):
            for y in (v, v + "'"):
                if x in nodes and y in nodes:
                    d[nodes.index(x), nodes.index(y)] = d[nodes.index(y), nodes.index(x)] = 1
    for k in range(len(nodes)):
        d = np.minimum(d, d[:, k : k + 1] + d[k : k + 1])
    out = d[:10, :10].copy()
    for i in (7, 8, 9):
        out[i, i] = d[i, i + 3]
    return out


def class_of(n_prime: int) -> np.ndarray:
    """Class number of every point in class order: 9n'+7 of them."""
    return np.concatenate([np.arange(7), np.repeat([7, 8, 9], 3 * n_prime)])


def hard_points(ids: DataFrame) -> DataFrame:
    """(ord, class, part) of an instance over the rows of a table, given by their unique ord.

    The seven smallest are the critical points, in class order; every other row
    belongs to the part ord mod 9, and three parts make a large set.
    """
    few = ids.orderBy("ord").limit(7).select("ord", (F.row_number().over(Window.orderBy("ord")) - 1).alias("critical"))
    part = F.pmod(F.col("ord"), F.lit(PROCESSORS)).cast("int")
    rows = ids.join(F.broadcast(few), "ord", "left")
    return rows.select("ord", F.coalesce("critical", 7 + F.floor(part / 3)).cast("int").alias("class"), F.when(F.col("critical").isNull(), part).alias("part"))


def class_sizes(ids: DataFrame) -> list[int]:
    """Points of each class."""
    found = {r["class"]: r["count"] for r in hard_points(ids).groupBy("class").count().collect()}
    return [found.get(c, 0) for c in range(len(CLASSES))]


def hard_distances(ids: DataFrame) -> DataFrame:
    """(a, b, d, pairs) by class: the distance of different points, and how many ordered pairs of points have it."""
    d, n = class_distances(), class_sizes(ids)
    rows = [(CLASSES[i], CLASSES[j], int(d[i, j]), n[i] * (n[j] - (i == j))) for i in range(10) for j in range(10) if n[i] and n[j]]
    return ids.sparkSession.createDataFrame(rows, "a string, b string, d int, pairs bigint")


def hard_inputs(ids: DataFrame, seed: int | None = None) -> DataFrame:
    """(processor, ord, label): three critical points and a part of one large set for each of nine processors.

    Critical points are on several processors.  A seed relabels points by the
    order of a hash, which takes one task, and deals inputs to processors at random.
    """
    crit = ids.sparkSession.createDataFrame([(3 * i + j, CLASSES.index(c)) for i in range(3) for j in range(3) for c in SHARED[i]], "processor int, class int")
    points = hard_points(ids)
    few = points.where("part IS NULL").join(F.broadcast(crit), "class").select("processor", "ord")
    rows = few.unionByName(points.where("part IS NOT NULL").select(F.col("part").alias("processor"), "ord"))
    if seed is None:
        return rows.withColumn("label", F.col("ord"))
    gamma = np.random.default_rng(seed).permutation(PROCESSORS).tolist()
    names = ids.select("ord", (F.row_number().over(Window.orderBy(F.xxhash64(F.lit(seed), "ord"), "ord")) - 1).cast("bigint").alias("label"))
    return rows.join(names, "ord").select(F.element_at(F.array(*map(F.lit, gamma)), F.col("processor") + 1).alias("processor"), "ord", "label")


def cost_of(classes: np.ndarray, chosen: np.ndarray, d: np.ndarray) -> int:
    """Clustering cost of chosen points (indices) for the whole instance."""
    rows = d[classes[:, None], classes[chosen][None, :]]
    rows = np.where(np.arange(len(classes))[:, None] == chosen[None, :], 0, rows)
    return int(rows.min(1).max())


def optimum(n_prime: int) -> tuple[int, list[int]]:
    """Cost and points of the optimum: a*, b1*, c*."""
    best = np.array([CLASSES.index(c) for c in ("a*", "b1*", "c*")])
    return cost_of(class_of(n_prime), best, class_distances()), best.tolist()


def class_cost(sizes: list[int], chosen: list[int], d: np.ndarray) -> int:
    """Clustering cost of different points, given by their classes, for an instance with classes of these sizes."""
    return max((int(d[c, chosen].min()) for c, n in enumerate(sizes) if n > chosen.count(c)), default=0)


def triples(sizes: list[int]) -> dict[int, int]:
    """How many triples of points have each cost."""
    d, found = class_distances(), {}
    for chosen in combinations_with_replacement(range(len(sizes)), 3):
        if n := math.prod(math.comb(sizes[c], chosen.count(c)) for c in set(chosen)):
            cost = class_cost(sizes, list(chosen), d)
            found[cost] = found.get(cost, 0) + n
    return found


def simulate(ids: DataFrame, ell: int, trials: int, seed: int = 0, coordinator: str = "random") -> DataFrame:
    """(trial, cost, failed): every processor sends ell random points of its input, the coordinator outputs three.

    "random" draws three of the received labels, "farthest" runs farthest-first
    on them, the best deterministic effort.  Trials are rows spread over tasks;
    points of a part are alike, so a task needs only how many each part has.
    """
    found = {r.part: r["count"] for r in hard_points(ids).where("part IS NOT NULL").groupBy("part").count().collect()}
    parts = [found.get(p, 0) for p in range(PROCESSORS)]

    def run(batches):
        import pyarrow as pa

        d, sizes = class_distances(), [1] * 7 + [sum(parts[3 * i : 3 * i + 3]) for i in range(3)]
        for b in batches:
            costs = []
            for t in b.column(0).to_pylist():
                rng = np.random.default_rng([seed, t])
                sent = set()
                for p, n in enumerate(parts):  # the first three of an input are its critical points
                    for x in rng.choice(n + 3, min(ell, n + 3), replace=False).tolist():
                        sent.add((CLASSES.index(SHARED[p // 3][x]), 0, 0) if x < 3 else (7 + p // 3, p, x))
                got = np.array([c for c, _, _ in sorted(sent)])[rng.permutation(len(sent))]
                if coordinator == "farthest":
                    pick, low = [0], np.full(len(got), 99)
                    while len(pick) < 3:
                        row = d[got, got[pick[-1]]]
                        low = np.minimum(low, np.where(np.arange(len(got)) == pick[-1], 0, row))
                        pick.append(int(low.argmax()))
                    got = got[pick]
                costs.append(class_cost(sizes, got[:3].tolist(), d))
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(costs, pa.int32())], ["trial", "cost"])

    return ids.sparkSession.range(trials).toDF("trial").mapInArrow(run, "trial bigint, cost int").withColumn("failed", F.col("cost") >= 4)


def amplification_factor(eps: float, c: float) -> int:
    """Copies needed so that sending a share c < 1/486 of the points fails with probability at least 1 - eps."""
    if not 0 < eps < 1 or not 0 <= c < 1 / 486:
        raise ValueError("eps must lie in (0, 1) and c in [0, 1/486)")
    return math.ceil(84 * math.log(1 / eps) / (1 - 486 * c))


def amplified(ids: DataFrame, copies: int) -> DataFrame:
    """(ord, copy, class): copies of the instance, far apart; a point's ord tells its copy too."""
    return hard_points(ids).select("ord", "class", F.explode(F.sequence(F.lit(0), F.lit(copies - 1))).alias("copy")).select((F.col("ord") * copies + F.col("copy")).alias("ord"), "copy", "class")
