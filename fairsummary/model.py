"""The data model: points with a total order and a group, capacities, and results."""

from __future__ import annotations

from dataclasses import dataclass, field, replace

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .metrics import Metric


@dataclass
class Points:
    """A few points on the driver: pivots, representatives, centres.  Their number follows k and m, never n."""

    ord: np.ndarray
    grp: np.ndarray
    coords: np.ndarray

    def __len__(self) -> int:
        return len(self.ord)

    def take(self, at) -> "Points":
        at = np.asarray(at, np.int64) if not (isinstance(at, np.ndarray) and at.dtype == bool) else at
        return Points(self.ord[at], self.grp[at], self.coords[at])

    @staticmethod
    def of(rows: list, metric: Metric) -> "Points":
        """From (ord, grp, coords) tuples, in the order given."""
        import pyarrow as pa

        kinds = {"array<bigint>": pa.list_(pa.int64()), "array<double>": pa.list_(pa.float64()), "bigint": pa.int64(), "string": pa.string(), "array<string>": pa.list_(pa.string())}
        return Points(np.array([r[0] for r in rows], np.int64), np.array([r[1] for r in rows], np.int64), metric.load(pa.array([r[2] for r in rows], kinds[metric.coords])))

    @staticmethod
    def empty(like: "Points | None" = None) -> "Points":
        return Points(np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros((0, 1)) if like is None else like.coords[:0])

    def sorted(self) -> "Points":
        return self.take(np.argsort(self.ord, kind="stable"))

    @staticmethod
    def join(parts: list["Points"]) -> "Points":
        return Points(*(np.concatenate([getattr(p, f) for p in parts]) for f in ("ord", "grp", "coords")))

    def rows(self, metric: Metric) -> list[tuple]:
        return list(zip(self.ord.tolist(), self.grp.tolist(), metric.store(self.coords)))


@dataclass(frozen=True)
class FairInstance:
    """``points`` is (ord, grp, coords); ``caps`` has the capacity of each group.  ``ord`` settles every tie, the smallest first.

    Points may also be held as arrays: then every method runs in the process at
    hand, which is how many small instances are spread over tasks.
    """

    points: DataFrame | Points
    metric: Metric
    caps: tuple[int, ...]
    ready: bool = False

    @property
    def k(self) -> int:
        return sum(self.caps)

    @staticmethod
    def from_table(table: DataFrame, ord_col, grp_col, coords_col, metric: Metric, caps) -> "FairInstance":
        """Project a table to points; rows with a null in any of the three are left out."""
        cols = [c if not isinstance(c, str) else F.col(c) for c in (ord_col, grp_col, coords_col)]
        points = table.select(cols[0].cast("bigint").alias("ord"), cols[1].cast("int").alias("grp"), cols[2].cast(metric.coords).alias("coords")).dropna()
        return FairInstance(points, metric, tuple(caps))

    def prepared(self) -> "FairInstance":
        """The same with its points written once, so that no scan computes what made them again."""
        if self.ready or isinstance(self.points, Points):
            return self
        from .storage import saved

        return replace(self, points=saved(self.points.select("ord", "grp", "coords"), "points"), ready=True)

    def validate(self) -> "FairInstance":
        """Check the contract with one aggregate: unique order, groups within the capacities, coordinates of one length."""
        size = F.size("coords") if self.metric.coords.startswith("array<") and self.metric.coords != "array<string>" else F.lit(1)
        row = self.points.agg(F.count("*").alias("n"), F.count_distinct("ord").alias("u"), F.min("grp").alias("lo"), F.max("grp").alias("hi"), F.min(size).alias("a"), F.max(size).alias("b")).first()
        if row.n != row.u:
            raise ValueError("ord must be unique")
        if row.n and (row.lo < 0 or row.hi >= len(self.caps) or row.a != row.b):
            raise ValueError("groups must be below the number of capacities and coordinates of one length")
        if min(self.caps, default=0) < 0:
            raise ValueError("capacities must not be negative")
        return self


def proportional_caps(counts: list[int], k: int) -> tuple[int, ...]:
    """Largest remainders: k places in proportion to the group sizes, ties to the smaller group number."""
    total = sum(counts)
    if not total:
        return tuple(0 for _ in counts)
    whole = [k * c // total for c in counts]
    order = sorted(range(len(counts)), key=lambda j: (-(k * counts[j] % total), j))
    for j in order[: k - sum(whole)]:
        whole[j] += 1
    return tuple(whole)


@dataclass
class Summary:
    """What every method returns.  ``stats`` has passes over the points, guesses tried, stored and sent points, distance evaluations."""

    method: str
    centres: Points
    tau: float
    cost: float
    hits: int
    sets: int
    stats: dict = field(default_factory=dict)

    def frame(self, spark, metric: Metric) -> DataFrame:
        rows = [(self.method, *r) for r in self.centres.rows(metric)]
        return spark.createDataFrame(rows, f"method string, ord bigint, grp int, coords {metric.coords}")
