"""The studies over many generated instances: random graphs, and points spread evenly in a cube.

A random instance is small, so instances are the rows that Spark spreads over
tasks, and each task runs every method on arrays.
"""

from __future__ import annotations

import time
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from . import baselines, graphs, methods, metrics
from .model import FairInstance, Points, Summary
from .workloads import uniform_cube

#: Capacity vectors of the ratio study; the published values are lost, these are the survey's own.
CAPACITIES = ((2, 2), (2, 8), (5, 5), (10, 10), (2, 2, 2), (4, 4, 4), (2,) * 5, (1, 2, 3, 4))
METHODS: dict[str, Callable[[FairInstance], Summary]] = {
    "two_pass": methods.two_pass,
    "two_pass_first": lambda inst: methods.two_pass(inst, search="first_success"),
    "distributed": lambda inst: methods.distributed(inst, block_size=25),
    "ball_matching": baselines.ball_matching,
    "quota_two_pass": baselines.quota_two_pass,
    "swap_recursive": baselines.swap_recursive,
}
_RUN = "n int, seed int, capacities string, method string, cost double, ratio double, feasible boolean, seconds double"


def _instance(D: np.ndarray, seed: int, caps: tuple[int, ...]) -> FairInstance:
    """Shortest paths as points held in arrays, with random groups."""
    n = len(D)
    coords = np.concatenate([np.arange(n)[:, None], D], axis=1)
    return FairInstance(Points(np.arange(n), np.array(graphs.random_groups(n, len(caps), seed)), coords), metrics.path_rows(), caps)


def graph_instance(n: int, seed: int, caps: tuple[int, ...]) -> FairInstance:
    """A random graph's shortest paths."""
    return _instance(graphs.path_matrix(n, *graphs.random_edges(n, seed)), seed, caps)


_KINDS = (pa.int32(), pa.int32(), pa.string(), pa.string(), pa.float64(), pa.float64(), pa.bool_(), pa.float64())
_NAMES = ["n", "seed", "capacities", "method", "cost", "ratio", "feasible", "seconds"]


def _runs_of(inst: FairInstance, seed: int, text: str) -> pa.RecordBatch:
    """What every method gives for one instance."""
    low = methods.farthest_lower_bound(inst.points, inst.metric, inst.k)
    rows = []
    for name, method in METHODS.items():
        began = time.perf_counter()
        found = method(inst)
        took = time.perf_counter() - began
        fits = all((found.centres.grp == j).sum() <= c for j, c in enumerate(inst.caps))
        rows.append((len(inst.points), seed, text, name, float(found.cost), found.cost / low if low else None, bool(fits), took))
    return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows), _KINDS)], _NAMES)


def graph_runs(spark: SparkSession, wanted: list[tuple[int, int, tuple[int, ...]]]) -> DataFrame:
    """One row for each (n, seed, capacities) and method; instances are dealt over tasks."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for n, seed, text in zip(*(c.to_pylist() for c in b.columns)):
                yield _runs_of(graph_instance(n, seed, tuple(map(int, text.split(",")))), seed, text)

    tasks = max(1, min(len(wanted), 4 * spark.sparkContext.defaultParallelism))
    rows = [(i, n, seed, ",".join(map(str, caps))) for i, (n, seed, caps) in enumerate(wanted)]
    dealt = spark.createDataFrame(rows, "i int, n int, seed int, capacities string").repartitionByRange(tasks, "i")
    return dealt.select("n", "seed", "capacities").mapInArrow(run, _RUN)


def table_runs(edges: DataFrame, vectors: tuple = CAPACITIES) -> DataFrame:
    """The same for every graph of a table (graph, src, dst, w) and capacity vector; vertices are those that have an edge."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for i, seed in enumerate(b.column(0).to_pylist()):
                src, dst, w = (b.column(1)[i].values.field(c).to_numpy() for c in ("src", "dst", "w"))
                known, at = np.unique(np.concatenate([src, dst]), return_inverse=True)
                D = graphs.path_matrix(len(known), at[: len(src)], at[len(src) :], w)
                for caps in vectors:
                    yield _runs_of(_instance(D, seed, caps), seed, ",".join(map(str, caps)))

    whole = edges.groupBy("graph").agg(F.collect_list(F.struct("src", "dst", "w")).alias("edges"))
    return whole.select(F.col("graph").cast("int"), "edges").repartition(4 * edges.sparkSession.sparkContext.defaultParallelism).mapInArrow(run, _RUN)


def ratio_study(spark: SparkSession, n: int = 500, instances: int = 20, vectors: tuple = CAPACITIES) -> DataFrame:
    """For every capacity vector and method: mean ratio and cost, how often best and second best (ties count for all), and the mean cost over that of the best method."""
    return ratios(graph_runs(spark, [(n, seed, caps) for caps in vectors for seed in range(instances)]))


def ratios(runs: DataFrame) -> DataFrame:
    """The ratio study's means and places over finished runs."""
    names = [m for m in METHODS if m != "two_pass_first"]
    runs = runs.where(F.col("method").isin(names))
    place = F.dense_rank().over(Window.partitionBy("capacities", "seed").orderBy("cost"))
    each = runs.withColumn("place", place).groupBy("capacities", "method").agg(
        F.avg("ratio").alias("mean_ratio"), F.avg("cost").alias("mean_cost"), F.count_if(F.col("place") == 1).alias("wins"), F.count_if(F.col("place") == 2).alias("second"), F.count("*").alias("runs"), F.bool_and("feasible").alias("feasible"))
    return each.withColumn("over_best", F.try_divide(F.col("mean_cost"), F.min("mean_cost").over(Window.partitionBy("capacities")))).drop("mean_cost")


def time_study(spark: SparkSession, sizes: tuple = tuple(range(100, 351, 50)), instances: int = 20) -> DataFrame:
    """Mean seconds of every method on random graphs of each size, five groups of capacity 2, each in one process."""
    return graph_runs(spark, [(n, seed, (2,) * 5) for n in sizes for seed in range(instances)]).groupBy("n", "method").agg(F.avg("seconds").alias("mean_seconds"), F.count("*").alias("runs"))


def cube(spark: SparkSession, n: int = 20_000, dim: int = 16, block: int = 1000, seed: int = 1) -> DataFrame:
    """Both methods on uniform points in a cube with four random groups of capacity 2: cost, ratio to the farthest-first bound, seconds, and seconds over those of a bare scan."""
    points = uniform_cube(spark, n, dim, 4, seed)
    inst = FairInstance(points, metrics.L2, (2,) * 4).prepared()
    low = methods.farthest_lower_bound(inst.points, inst.metric, inst.k)
    inst.points.write.format("noop").mode("overwrite").save()
    began = time.perf_counter()
    inst.points.write.format("noop").mode("overwrite").save()
    read, rows = time.perf_counter() - began, []
    for name, run in (("two_pass", lambda: methods.two_pass(inst, mode="any")), ("distributed", lambda: methods.distributed(inst, block_size=block))):
        began = time.perf_counter()
        found = run()
        took = time.perf_counter() - began
        rows.append((name, float(found.cost), found.cost / low, len(found.centres), took, took / read))
    return spark.createDataFrame(rows, "method string, cost double, ratio double, centres int, seconds double, over_read double")
