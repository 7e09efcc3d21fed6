"""Scans over the points: the only code that touches all n of them.

Each is a narrow pass (Arrow batches against a few centres) whose results are
a few rows per partition and meet in executors before the driver sees them.
Columns are selected before the Arrow stage, so the scan below reads nothing
else.  Points held as arrays take the same path as one batch, without Spark.
"""

from __future__ import annotations

from collections.abc import Iterator
from contextlib import contextmanager
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .metrics import Metric
from .model import Points

#: Rows of a batch that meet the centres at once, which bounds the scratch matrix.
ROWS = 4096
#: Candidate lists that meet in one task or on the driver; more partitions than this merge by levels.
FAN = 256
#: Pivots a scan without a limit may collect.
MOST_PIVOTS = 100_000


@dataclass
class Ledger:
    """Scans of all points and distances measured in them, as executors report."""

    scans: int = 0
    evaluations: int = 0


_BOOKS: list[Ledger] = []


@contextmanager
def ledger() -> Iterator[Ledger]:
    """Counts the scans that run inside."""
    book = Ledger()
    _BOOKS.append(book)
    try:
        yield book
    finally:
        _BOOKS.remove(book)


@contextmanager
def aside() -> Iterator[None]:
    """Scans inside are over a summary, not over the points, and do not count."""
    held = _BOOKS[:]
    _BOOKS.clear()
    try:
        yield
    finally:
        _BOOKS.extend(held)


def _note(evaluations: int) -> None:
    for book in _BOOKS:
        book.scans += 1
        book.evaluations += int(evaluations)


def _arrow(metric: Metric) -> pa.DataType:
    return {"array<bigint>": pa.list_(pa.int64()), "array<double>": pa.list_(pa.float64()), "bigint": pa.int64(), "string": pa.string(), "array<string>": pa.list_(pa.string())}[metric.coords]


def _table(rows: list[dict], fields: dict[str, pa.DataType]) -> pa.RecordBatch:
    return pa.RecordBatch.from_pylist(rows, pa.schema(list(fields.items())))


def _batches(it: Iterator[pa.RecordBatch], metric: Metric) -> Iterator[Points]:
    for batch in it:
        for lo in range(0, batch.num_rows, ROWS):
            b = batch.slice(lo, ROWS)
            yield Points(b.column(0).to_numpy(), b.column(1).to_numpy(), metric.load(b.column(2)))


def _narrow(points: DataFrame) -> DataFrame:
    return points.select("ord", "grp", "coords")


class _Columns:
    """Distances of one batch to single points, measured once however many guesses ask."""

    def __init__(self, X: np.ndarray, metric: Metric):
        self.X, self.metric, self.held, self.count = X, metric, {}, 0

    def to(self, key: int, coords: np.ndarray) -> np.ndarray:
        if key not in self.held:
            self.held[key] = self.metric.batch(self.X, coords)[:, 0]
            self.count += len(self.X)
        return self.held[key]


def cover_distance(points: DataFrame | Points, metric: Metric, sets: list[np.ndarray]) -> list[float]:
    """For several centre sets in one scan: the largest distance of any point to its nearest centre."""

    def worst_of(parts: Iterator[Points]) -> tuple[list[float], int]:
        worst, n = [-1.0] * len(sets), 0
        for b in parts:
            n += len(b)
            for s, P in enumerate(sets):
                if len(b):
                    worst[s] = max(worst[s], float(metric.batch(b.coords, P).min(1).max()) if len(P) else np.inf)
        return worst, n

    if isinstance(points, Points):
        worst, n = worst_of(iter([points]))
    else:

        def run(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            found, rows = worst_of(_batches(it, metric))
            yield pa.RecordBatch.from_arrays([pa.array(range(len(sets)), pa.int32()), pa.array(found, pa.float64()), pa.array([rows] * len(sets), pa.int64())], ["s", "d", "n"])

        got = {r.s: r for r in _narrow(points).mapInArrow(run, "s int, d double, n bigint").groupBy("s").agg(F.max("d").alias("d"), F.sum("n").alias("n")).collect()}
        worst = [got[s].d if s in got else 0.0 for s in range(len(sets))]
        n = got[0].n if 0 in got else 0
    _note(n * sum(map(len, sets)))
    return [max(w, 0.0) for w in worst]


def farthest(points: DataFrame | Points, metric: Metric, centres: np.ndarray) -> tuple | None:
    """(distance, ord, grp, coords) of the point farthest from the centres, ties to the smaller ord; the first point when there are none."""

    def best_of(parts: Iterator[Points]) -> tuple[tuple | None, int]:
        best, n = None, 0
        for b in parts:
            if not len(b):
                continue
            n += len(b)
            d = metric.batch(b.coords, centres).min(1).astype(float) if len(centres) else np.full(len(b), np.inf)
            at = np.lexsort((b.ord, -d))[0]
            if best is None or (-d[at], b.ord[at]) < (-best[0], best[1]):
                best = (float(d[at]), int(b.ord[at]), int(b.grp[at]), metric.store(b.coords[at : at + 1])[0])
        return best, n

    if isinstance(points, Points):
        best, n = best_of(iter([points]))
        _note(n * len(centres))
        return best

    def run(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        best, n = best_of(_batches(it, metric))
        if best:
            yield _table([dict(zip(("d", "ord", "grp", "coords", "n"), (*best, n)))], {"d": pa.float64(), "ord": pa.int64(), "grp": pa.int32(), "coords": _arrow(metric), "n": pa.int64()})

    rows = _narrow(points).mapInArrow(run, f"d double, ord bigint, grp int, coords {metric.coords}, n bigint")
    top = rows.agg(F.max_by(F.struct("d", "ord", "grp", "coords"), F.struct("d", -F.col("ord"))).alias("x"), F.sum("n").alias("n")).first()
    _note((top.n or 0) * len(centres))
    return None if top.x is None else (top.x.d, top.x.ord, top.x.grp, top.x.coords)


def farthest_first(points: DataFrame | Points, metric: Metric, t: int, initial: Points | None = None) -> tuple[Points, list[float]]:
    """Up to t points, each the farthest from those before it, and the distance at which each was taken.

    Starts at the smallest ord, or from ``initial`` centres that are not counted.
    Stops early when every point is at distance zero.  A scan measures against
    all centres so far: t of them are few, and no column of all points is kept.
    """
    start = initial.coords if initial is not None and len(initial) else None
    rows, trace = [], []
    while len(rows) < t:
        own = Points.of(rows, metric).coords if rows else None
        centres = np.concatenate([x for x in (start, own) if x is not None]) if start is not None or own is not None else np.zeros((0, 1))
        top = farthest(points, metric, centres)
        if top is None or top[0] <= 0:
            break
        rows.append(top[1:])
        trace.append(top[0])
    return Points.of(rows, metric), trace


def _candidates(parts: Iterator[Points], metric: Metric, radii: list[float], fixed: dict[int, Points], stop: int) -> tuple[dict[int, list[tuple]], int]:
    """The greedy rule over batches in the order they come: for each guess what is added to its fixed pivots."""
    new: dict[int, list[tuple]] = {g: [] for g in fixed}
    count = 0
    for b in parts:
        if not len(b):
            continue
        far = _Columns(b.coords, metric)
        for g, P in fixed.items():
            room = stop - len(P)
            if len(new[g]) >= room:
                continue
            open_ = np.ones(len(b), bool)
            for held in ([(o, P.coords[i : i + 1]) for i, o in enumerate(P.ord.tolist())], [(n[0], n[2]) for n in new[g]]):
                for o, c in held:
                    open_ &= far.to(o, c) > radii[g]
            while open_.any() and len(new[g]) < room:
                at = int(open_.argmax())
                c = b.coords[at : at + 1]
                new[g].append((int(b.ord[at]), int(b.grp[at]), c))
                open_ &= far.to(int(b.ord[at]), c) > radii[g]
        count += far.count
    return new, count


_LATEST = (1 << 63) - 1


def merge_lists(lists: list[tuple[list[tuple], int]], metric: Metric, radius: float, room: int, ordered: bool) -> tuple[list[tuple], int]:
    """Candidate lists of several sources as one: (candidates by ord, horizon).

    A list is exact for its source up to its horizon.  In order, a candidate
    that another source's accepted one covers makes everything after it
    uncertain, so the merged horizon ends there; out of order it is skipped,
    and a horizon below the latest says that something was.
    """
    horizon = min((h for _, h in lists), default=_LATEST)
    taken: list[tuple[int, tuple]] = []
    for row, source in sorted(((r, i) for i, (rows, _) in enumerate(lists) for r in rows), key=lambda x: (x[0][0], x[1])):
        if len(taken) >= room or (ordered and row[0] >= horizon):
            break
        others = [t[2] for i, t in taken if i != source]
        if others and metric.batch(row[2], np.concatenate(others)).min() <= radius:
            horizon = row[0]
            if ordered:
                break
            continue
        taken.append((source, row))
    return [t for _, t in taken], horizon


def separated_pivots(points: DataFrame | Points, metric: Metric, radii: list[float], limit: int | None = None, mode: str = "ordered") -> tuple[list[Points], list[bool], int]:
    """For every radius the greedy set of points farther than it from all before: (pivots, broken, rounds).

    A radius is broken once it has more than ``limit`` pivots, which proves that
    no ``limit`` points cover everything within half of it.  All radii share
    each scan.  In a round each partition runs the greedy rule against what is
    committed; its candidates merge by levels in executors and on the driver,
    which sees at most FAN lists of a guess however many partitions there are.
    "ordered" gives the result of one pass by ord: partitions are sorted where
    they are, nothing is shuffled, and a round commits the exact prefix that
    the candidates prove.  "any" sorts nothing, skips candidates that another
    partition's cover and needs fewer rounds; separation and cover hold, the
    order does not.  Without a limit more than MOST_PIVOTS raise ValueError.
    """
    stop = limit + 1 if limit is not None else MOST_PIVOTS + 1
    if isinstance(points, Points):
        new, count = _candidates(iter([points.sorted()]), metric, list(radii), {g: Points.empty(points) for g in range(len(radii))}, stop)
        _note(count)
        done = {g: [(o, r, metric.store(c)[0]) for o, r, c in new[g]] for g in new}
        return _kept(done, metric, len(radii), limit, stop, 1)
    ordered = mode == "ordered"
    source = _narrow(points)
    parts = source.rdd.getNumPartitions()
    source = source.sortWithinPartitions("ord") if ordered else source
    fields = {"g": pa.int32(), "part": pa.int64(), "horizon": pa.int64(), "ord": pa.int64(), "grp": pa.int32(), "coords": _arrow(metric)}
    schema = f"g int, part bigint, horizon bigint, ord bigint, grp int, coords {metric.coords}"

    def as_rows(g: int, part: int, found: list[tuple], horizon: int) -> list[dict]:
        return [{"g": g, "part": part, "horizon": horizon, "ord": o, "grp": r, "coords": metric.store(c)[0]} for o, r, c in found]

    def as_lists(rows) -> list[tuple[list[tuple], int]]:
        by: dict[int, tuple[list[tuple], int]] = {}
        for r in rows:
            by.setdefault(r["part"], ([], r["horizon"]))[0].append((r["ord"], r["grp"], Points.of([(0, 0, r["coords"])], metric).coords))
        return list(by.values())

    done: dict[int, list[tuple]] = {g: [] for g in range(len(radii))}
    live, rounds = set(done), 0
    while live:
        rounds += 1
        fixed = {g: Points.of(done[g], metric) for g in live}

        def run(it: Iterator[pa.RecordBatch], fixed=fixed) -> Iterator[pa.RecordBatch]:
            part = TaskContext.get().partitionId()
            new, count = _candidates(_batches(it, metric), metric, list(radii), fixed, stop)
            rows = [{"g": -1, "part": part, "horizon": count, "ord": 0, "grp": 0, "coords": None}]
            yield _table(rows + [x for g, found in new.items() for x in as_rows(g, part, found, _LATEST)], fields)

        def join(table: pa.Table, fixed=fixed) -> pa.Table:
            rows = table.to_pylist()
            g, part = rows[0]["g"], rows[0]["part"] // FAN
            if g < 0:
                return pa.Table.from_batches([_table([rows[0] | {"part": part, "horizon": sum(r["horizon"] for r in rows)}], fields)])
            found, horizon = merge_lists(as_lists(rows), metric, radii[g], stop - len(fixed[g]), ordered)
            return pa.Table.from_batches([_table(as_rows(g, part, found, horizon), fields)])

        got, lists = source.mapInArrow(run, schema), parts
        while lists > FAN:
            got = got.groupBy("g", F.floor(F.col("part") / FAN).alias("bucket")).applyInArrow(lambda t: join(t.drop_columns(["bucket"]) if "bucket" in t.column_names else t), schema)
            lists = -(-lists // FAN)
        by: dict[int, list] = {g: [] for g in live}
        count = 0
        for r in got.collect():
            if r.g < 0:
                count += r.horizon
            else:
                by[r.g].append(r)
        _note(count)
        for g in list(live):
            taken, horizon = merge_lists(as_lists(by[g]), metric, radii[g], stop - len(done[g]), ordered)
            done[g] += [(o, r, metric.store(c)[0]) for o, r, c in taken]
            if len(done[g]) >= stop or horizon == _LATEST:
                live.discard(g)
    return _kept(done, metric, len(radii), limit, stop, rounds)


def _kept(done: dict[int, list[tuple]], metric: Metric, guesses: int, limit: int | None, stop: int, rounds: int) -> tuple[list[Points], list[bool], int]:
    if limit is None and any(len(d) >= stop for d in done.values()):
        raise ValueError(f"more than {MOST_PIVOTS} pivots")
    kept = [done[g][:stop] for g in range(guesses)]
    return [Points.of(d, metric) for d in kept], [limit is not None and len(d) >= stop for d in kept], rounds


def group_reps(points: DataFrame | Points, metric: Metric, pivots: list[Points], radii: list[float], quota: tuple[int, ...] | None = None) -> list[list[Points]]:
    """For every guess and pivot: the pivot, then the first point in range of each other group by ord.

    With ``quota`` up to that many points of each group, the pivot counting in
    its own.  One scan for all guesses; a few rows per pivot and group leave a
    partition, and meet in one small shuffle before the driver.
    """
    most = max(quota) if quota else 1

    def nearby(parts: Iterator[Points]) -> tuple[dict[tuple[int, int, int], list[tuple]], int]:
        best: dict[tuple[int, int, int], list[tuple]] = {}
        count = 0
        for b in parts:
            if not len(b):
                continue
            far = _Columns(b.coords, metric)
            for g, (P, r) in enumerate(zip(pivots, radii)):
                for p, o in enumerate(P.ord.tolist()):
                    at = np.flatnonzero((far.to(o, P.coords[p : p + 1]) <= r) & (b.ord != o))
                    for grp in np.unique(b.grp[at]).tolist():
                        own = at[b.grp[at] == grp]
                        own = own[np.argsort(b.ord[own], kind="stable")[:most]]
                        have = best.setdefault((g, p, grp), [])
                        have += [(int(b.ord[i]), metric.store(b.coords[i : i + 1])[0]) for i in own]
                        have.sort(key=lambda x: x[0])
                        del have[most:]
            count += far.count
        return best, count

    found: dict[tuple[int, int], dict[int, list]] = {}
    if isinstance(points, Points):
        best, count = nearby(iter([points]))
        for (g, p, grp), have in best.items():
            found.setdefault((g, p), {})[grp] = [(o, grp, c) for o, c in have]
    else:

        def run(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            best, count = nearby(_batches(it, metric))
            rows = [{"g": -1, "p": 0, "grp": 0, "ord": count, "coords": None}] + [{"g": g, "p": p, "grp": grp, "ord": o, "coords": c} for (g, p, grp), have in best.items() for o, c in have]
            yield _table(rows, {"g": pa.int32(), "p": pa.int32(), "grp": pa.int32(), "ord": pa.int64(), "coords": _arrow(metric)})

        rows = _narrow(points).mapInArrow(run, f"g int, p int, grp int, ord bigint, coords {metric.coords}")
        keys = ["g", "p", "grp"]
        if most == 1:
            rows = rows.groupBy(*keys).agg(F.sum("ord").alias("count"), F.min_by(F.struct("ord", "coords"), "ord").alias("x")).select(*keys, F.when(F.col("g") < 0, F.col("count")).otherwise(F.col("x.ord")).alias("ord"), "x.coords")
        else:
            rank = F.row_number().over(Window.partitionBy(*keys).orderBy("ord"))
            counts = rows.where("g < 0").groupBy(*keys).agg(F.sum("ord").alias("ord")).withColumn("coords", F.lit(None).cast(metric.coords))
            rows = rows.where("g >= 0").withColumn("n", rank).where(F.col("n") <= most).drop("n").unionByName(counts)
        count = 0
        for r in sorted(rows.collect(), key=lambda r: r.ord):
            if r.g < 0:
                count += r.ord
            else:
                found.setdefault((r.g, r.p), {}).setdefault(r.grp, []).append((r.ord, r.grp, r.coords))
    _note(count)
    out = []
    for g, P in enumerate(pivots):
        sets = []
        for p, pivot in enumerate(P.rows(metric)):
            members = [pivot]
            for grp, have in sorted(found.get((g, p), {}).items()):
                room = (quota[grp] if quota else 1) - (grp == pivot[1])
                members += have[: max(room, 0)]
            sets.append(Points.of(members, metric))
        out.append(sets)
    return out


def ball_members(points: DataFrame, metric: Metric, pivots: list[Points], radii: list[float]) -> DataFrame:
    """(guess, pivot, ord, grp, coords, d) of every point within a guess's radius of its pivot: a theta join against the few broadcast pivots."""
    rows = [(g, o, float(r), c) for g, (P, r) in enumerate(zip(pivots, radii)) for o, _, c in P.rows(metric)]
    few = points.sparkSession.createDataFrame(rows, f"guess int, pivot bigint, within double, at {metric.coords}")
    d = metric.column(F.col("coords"), F.col("at"))
    return _narrow(points).join(F.broadcast(few), d <= F.col("within")).select("guess", "pivot", "ord", "grp", "coords", d.cast("double").alias("d"))


def ball_inventory(points: DataFrame | Points, metric: Metric, pivots: list[Points], radii: list[float]) -> list[tuple[list[Points], int]]:
    """For every guess its balls, each as its member of every group that is nearest to the pivot (ties by ord), and how many members all balls have."""
    rows: list[tuple] = []
    if isinstance(points, Points):
        for g, (P, r) in enumerate(zip(pivots, radii)):
            for p, o in enumerate(P.ord.tolist()):
                d = metric.batch(points.coords, P.coords[p : p + 1])[:, 0]
                for grp in np.unique(points.grp[d <= r]).tolist():
                    own = np.flatnonzero((d <= r) & (points.grp == grp))
                    at = own[np.lexsort((points.ord[own], d[own]))[0]]
                    rows.append((g, o, grp, len(own), int(points.ord[at]), metric.store(points.coords[at : at + 1])[0]))
        _note(len(points) * sum(map(len, pivots)))
    else:
        near = ball_members(points, metric, pivots, radii)
        best = near.groupBy("guess", "pivot", "grp").agg(F.count("*").alias("n"), F.min_by(F.struct("ord", "coords"), F.struct("d", "ord")).alias("x"))
        rows = [(r.guess, r.pivot, r.grp, r.n, r.x.ord, r.x.coords) for r in best.collect()]
        _note(0)
    out = []
    for g, P in enumerate(pivots):
        mine = [r for r in rows if r[0] == g]
        balls = [Points.of([(r[4], r[2], r[5]) for r in sorted(mine, key=lambda r: r[2]) if r[1] == o], metric) for o in P.ord.tolist()]
        out.append((balls, sum(r[3] for r in mine)))
    return out


def first_of_groups(points: DataFrame | Points, metric: Metric, caps: tuple[int, ...]) -> Points:
    """The first points of each group by ord, as many as its capacity: a feasible set.  Ranks are limited before the shuffle."""
    _note(0)
    if isinstance(points, Points):
        own = points.sorted()
        at = [i for j, c in enumerate(caps) for i in np.flatnonzero(own.grp == j)[:c].tolist()]
        return own.take(at)
    most = max(caps, default=0)
    limit = F.element_at(F.array(*map(F.lit, caps or (0,))), F.col("grp") + 1)
    rank = F.row_number().over(Window.partitionBy("grp").orderBy("ord"))
    rows = _narrow(points).withColumn("n", rank).where(F.col("n") <= most).where(F.col("n") <= limit).orderBy("grp", "ord").collect()
    return Points.of([(r.ord, r.grp, r.coords) for r in rows], metric)


def first_distinct(points: DataFrame | Points, metric: Metric, count: int) -> Points:
    """The first ``count`` points in order that differ in position from all before; copies cannot make the set short unless positions run out."""
    (found,), _, _ = separated_pivots(points, metric, [0], limit=count - 1)
    return found


def nearest_centre(points: DataFrame, metric: Metric, centres: Points) -> DataFrame:
    """(ord, grp, centre, d): the nearest centre of every point by expression only, ties to the smaller centre ord."""
    packed = F.array(*[F.struct(F.lit(o).cast("bigint").alias("o"), _literal(c, metric).alias("c")) for o, _, c in centres.rows(metric)])
    near = F.array_min(F.transform(packed, lambda x: F.struct(metric.column(F.col("coords"), x["c"]).alias("d"), x["o"].alias("o"))))
    return points.select("ord", "grp", near.alias("n")).select("ord", "grp", F.col("n.o").alias("centre"), F.col("n.d").alias("d"))


#: Classes of a block meet the queries of a block in one task, some queries at a time.
CLASS_BLOCK, QUERY_BLOCK, CELLS = 256, 16384, 1 << 19


def distances_by_class(points: DataFrame, metric: Metric, asks: Column) -> DataFrame:
    """(ord, class, query, d): the distances of all (ord, coords) to those that ``asks`` marks, without expanding copies.

    Points at one position are a class, named by its smallest ord.  A row with
    an ord puts that point into its class; a row without one is the distance of
    a class to a class that holds a query.  Blocks of both meet as rows, so no
    task and no driver holds all of either.
    """
    places = points.groupBy("coords").agg(F.min("ord").alias("class"), F.bool_or(asks).alias("asked"))
    members = points.select("ord", F.min("ord").over(Window.partitionBy("coords")).alias("class"))

    def blocks(rows: DataFrame, size: int, name: str) -> DataFrame:
        return rows.groupBy(F.floor(F.col("class") / size).alias(name)).agg(F.collect_list("class").alias(f"{name}_class"), F.collect_list("coords").alias(f"{name}_coords"))

    def run(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in it:
            for i in range(batch.num_rows):
                a, x, b, y = (batch.column(j).slice(i, 1).flatten() for j in range(4))
                a, b, X, Y = a.to_numpy(), b.to_numpy(), metric.load(x), metric.load(y)
                step = max(1, CELLS // len(a))
                for lo in range(0, len(b), step):
                    d = metric.batch(X, Y[lo : lo + step])
                    own = b[lo : lo + step]
                    yield pa.RecordBatch.from_arrays([pa.array(np.repeat(a, len(own))), pa.array(np.tile(own, len(a))), pa.array(d.ravel())], ["class", "query", "d"])

    kind = "double" if metric.coords == "array<double>" else "bigint"
    left = blocks(places, CLASS_BLOCK, "a").repartition(4 * points.sparkSession.sparkContext.defaultParallelism, "a")
    right = blocks(places.where("asked"), QUERY_BLOCK, "b")
    pairs = left.join(F.broadcast(right)).select("a_class", "a_coords", "b_class", "b_coords").mapInArrow(run, f"class bigint, query bigint, d {kind}")
    nothing = F.lit(None)
    return members.select("ord", "class", nothing.cast("bigint").alias("query"), nothing.cast(kind).alias("d")).unionByName(pairs.select(nothing.cast("bigint").alias("ord"), "class", "query", "d"))


def _literal(value, metric: Metric):
    return F.array(*map(F.lit, value)).cast(metric.coords) if isinstance(value, list) else F.lit(value).cast(metric.coords)
