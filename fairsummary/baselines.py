"""What the two methods are compared with; all take an instance and return a summary."""

from __future__ import annotations

from collections import Counter
from collections.abc import Callable
from itertools import combinations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import scans
from .hitting import complete, hitting_set
from .methods import DRIVER_BYTES, _finish, _half_gap, block_summaries, coordinate_at, driver_size, guesses_between, method, simple_upper_bound, two_pass
from .metrics import Metric
from .model import FairInstance, Points, Summary
from .storage import saved


def plain_farthest(points: DataFrame | Points, metric: Metric, k: int) -> Summary:
    """Farthest-first centres without regard to groups: at most twice the plain optimum."""
    with scans.ledger() as book:
        centres, _ = scans.farthest_first(points, metric, k)
        cost = scans.cover_distance(points, metric, [centres.coords])[0]
    return Summary("plain_farthest", centres, 0.0, cost, len(centres), len(centres), {"passes": book.scans, "evaluations": book.evaluations})


@method
def ball_matching(inst: FairInstance, eps: float = 0.1) -> Summary:
    """Offline: guesses from the farthest-first bound upward, the whole ball around every pivot, a matching of balls and groups.

    A ball serves with its member nearest to the pivot; ``stored`` counts the
    members of all balls of the largest guess, as an offline run holds them.
    """
    start, high = simple_upper_bound(inst)
    if high == 0 or not len(start):
        return Summary("ball_matching", start, 0.0, high, 0, 0, {"guesses": 0, "stored": len(start)})
    found, trace = scans.farthest_first(inst.points, inst.metric, inst.k + 1)
    guesses = guesses_between(found, inst.k, trace[inst.k] / 2 if len(trace) > inst.k else 0.0, high, inst.metric, eps)
    pivots, broken, _ = scans.separated_pivots(inst.points, inst.metric, [2 * t for t in guesses], inst.k)
    alive = [g for g, b in enumerate(broken) if not b]
    balls = scans.ball_inventory(inst.points, inst.metric, [pivots[g] for g in alive], [guesses[g] for g in alive])
    stats = {"guesses": len(guesses), "stored": max(n for _, n in balls)}
    for g, (sets, _) in zip(alive, balls):
        chosen, hits = hitting_set(sets, inst.caps)
        if hits == len(sets):
            return _finish(inst, "ball_matching", chosen, start, guesses[g], hits, len(sets), stats)
    raise AssertionError("the last guess is at least the optimum")


def _few(inst: FairInstance, most: int) -> Points:
    """All points of a small instance, by ord."""
    if isinstance(inst.points, Points):
        found = inst.points.sorted()
    else:
        found = Points.of([(r.ord, r.grp, r.coords) for r in inst.points.orderBy("ord").limit(most + 1).collect()], inst.metric)
    if len(found) > most:
        raise ValueError(f"more than {most} points")
    return found


def _radii(points: DataFrame | Points, metric: Metric) -> tuple[Callable[[float], float], Callable[[float], int]]:
    """Over all pairwise distances: the smallest that is at least a value (infinite without one), and how many different ones are at most a value."""
    if isinstance(points, Points):
        d = np.unique(metric.batch(points.coords, points.coords).astype(float))
        return (lambda v: float(min(d[d >= v], default=np.inf))), (lambda v: int((d <= v).sum()))
    d = scans.distances_by_class(points, metric, F.lit(True)).where("query IS NOT NULL").select(F.col("d").cast("double").alias("d"))

    def smallest(v: float) -> float:
        found = d.where(F.col("d") >= v).agg(F.min("d")).first()[0]
        return np.inf if found is None else found

    return smallest, lambda v: d.where(F.col("d") <= v).agg(F.count_distinct("d")).first()[0]


def _next_change(points: DataFrame | Points, inst: FairInstance, tau: float) -> tuple[bool, float]:
    """Whether a radius succeeds, and the next larger one at which its pivots, or the groups in reach of them, differ; in between nothing does."""
    (pivots,), (broken,), _ = scans.separated_pivots(points, inst.metric, [2 * tau], inst.k)
    gaps = inst.metric.batch(pivots.coords, pivots.coords).astype(float)[np.triu_indices(len(pivots), 1)]
    after = float(gaps.min(initial=np.inf)) / 2
    if broken:
        return False, after
    ((balls, _),) = scans.ball_inventory(points, inst.metric, [pivots], [np.inf])
    sets = []
    for p, near in enumerate(balls):
        d = inst.metric.batch(near.coords, pivots.coords[p : p + 1])[:, 0].astype(float)
        after = min(after, float(d[d > tau].min(initial=np.inf)))
        sets.append(near.take(d <= tau))
    return hitting_set(sets, inst.caps)[1] == len(sets), after


@method
def ball_matching_exact(inst: FairInstance, most: int = 400) -> Summary:
    """Every pairwise distance is a candidate radius, and the smallest that succeeds wins.

    Between two changes of its pivots or of the groups in their reach a radius
    keeps its outcome, so the search goes from change to change, and pairs are
    measured only where a success wants its distance and its rank.  Of a group's
    copies at a position the first by ord stands for all.  ``most`` rows, and
    more as long as the driver's bound allows, are searched as arrays; any
    number beyond by scans.
    """
    points, start = inst.points, scans.first_of_groups(inst.points, inst.metric, inst.caps)
    if not isinstance(points, Points):
        points = saved(points.groupBy("coords", "grp").agg(F.min("ord").alias("ord")).select("ord", "grp", "coords"), "positions")
        size = points.agg(F.count("*").alias("n"), F.max(F.size("coords") if inst.metric.coords.startswith("array") else F.lit(1)).alias("d")).first()
        if size.n <= most or driver_size(size.n, size.d) <= DRIVER_BYTES:
            points = Points.of([(r.ord, r.grp, r.coords) for r in points.orderBy("ord").collect()], inst.metric)
    smallest, rank = _radii(inst.points, inst.metric)
    tau = 0.0
    while tau < np.inf and sum(inst.caps):
        good, after = _next_change(points, inst, tau)
        if good and (found := smallest(tau)) < after:
            (pivots,), _, _ = scans.separated_pivots(points, inst.metric, [2 * found], inst.k)
            (sets,) = scans.group_reps(points, inst.metric, [pivots], [found])
            chosen, hits = hitting_set(sets, inst.caps)
            ((_, stored),) = scans.ball_inventory(inst.points, inst.metric, [pivots], [found])
            return _finish(inst, "ball_matching_exact", chosen, start, found, hits, len(sets), {"guesses": rank(found), "stored": stored})
        tau = after
    return _finish(inst, "ball_matching_exact", None, start, 0.0, 0, 0, {})


def quota_two_pass(inst: FairInstance, eps: float = 0.1) -> Summary:
    """Two passes that store up to a group's capacity around every pivot, of which the last one kept serves."""
    return two_pass(inst, eps, "all", quota=True, name="quota_two_pass")


class OnePassState:
    """What one stream or shard keeps for a guess: pivots more than 2 tau apart, and around each up to a quota of every group among the arrivals credited to it.

    More than k pivots break the guess for good; a broken state says so and holds nothing else.
    """

    def __init__(self, metric: Metric, caps: tuple[int, ...], tau: float, lean: bool = False):
        self.metric, self.tau, self.k = metric, tau, sum(caps)
        self.quota = [1] * len(caps) if lean else list(caps)
        self.pivots: Points | None = None
        self.reps: list[dict[int, list[tuple]]] = []
        self.broken = False

    def insert(self, more: Points) -> None:
        """Arrivals in the order given."""
        if self.broken or not len(more):
            return
        held = 0 if self.pivots is None else len(self.pivots)
        credit = np.full(len(more), -1)
        for p in range(held):
            near = self.metric.batch(more.coords, self.pivots.coords[p : p + 1])[:, 0] <= 2 * self.tau
            credit[near & (credit < 0)] = p
        while (credit < 0).any():  # the first arrival that no pivot covers is one
            if held == self.k:
                self.broken, self.pivots, self.reps = True, None, []
                return
            at = [int((credit < 0).argmax())]
            own = more.take(at)
            self.pivots = own if self.pivots is None else Points.join([self.pivots, own])
            self.reps.append({})
            near = self.metric.batch(more.coords, own.coords)[:, 0] <= 2 * self.tau
            credit[near & (credit < 0)] = held
            held += 1
        for p in np.unique(credit).tolist():
            for g in np.unique(more.grp[credit == p]).tolist():
                have = self.reps[p].setdefault(g, [])
                at = np.flatnonzero((credit == p) & (more.grp == g))[: max(0, max(self.quota[g], int(not have)) - len(have))]
                have += more.take(at).rows(self.metric)

    def rows(self) -> list[tuple[str, int, tuple]]:
        if self.broken:
            return [("broken", 0, (0, 0, None))]
        mine = [] if self.pivots is None else self.pivots.rows(self.metric)
        return [("pivot", p, r) for p, r in enumerate(mine)] + [("rep", p, r) for p, held in enumerate(self.reps) for have in held.values() for r in have]


def one_pass_shards(points: DataFrame | Points, metric: Metric, caps: tuple[int, ...], guesses: list[float], lean: bool = False, shard_size: int | None = None) -> DataFrame | list[tuple]:
    """What all shards keep for all guesses, in one scan: (g, shard, role, pivot, ord, grp, coords); role "broken" stands for a shard that gave up.

    Shards are ``ord div shard_size`` or, without, the partitions as they are.
    """

    def rows_of(parts, shard: int) -> list[dict]:
        states = [OnePassState(metric, caps, t, lean) for t in guesses]
        for b in parts:
            for state in states:
                state.insert(b)
        return [{"g": g, "shard": shard, "role": role, "pivot": p, "ord": r[0], "grp": r[1], "coords": r[2]} for g, state in enumerate(states) for role, p, r in state.rows()]

    if isinstance(points, Points):
        own = points.sorted()
        shards = own.ord // shard_size if shard_size else np.zeros(len(own), np.int64)
        return [r for b in np.unique(shards).tolist() for r in rows_of([own.take(shards == b)], b)]
    fields = {"g": pa.int32(), "shard": pa.int64(), "role": pa.string(), "pivot": pa.int32(), "ord": pa.int64(), "grp": pa.int32(), "coords": scans._arrow(metric)}
    schema = f"g int, shard bigint, role string, pivot int, ord bigint, grp int, coords {metric.coords}"

    def cut(it):
        from pyspark import TaskContext

        yield scans._table(rows_of(scans._batches(it, metric), TaskContext.get().partitionId()), fields)

    def whole(table: pa.Table) -> pa.Table:
        b = Points(table["ord"].to_numpy(), table["grp"].to_numpy(), metric.load(table["coords"].combine_chunks())).sorted()
        return pa.Table.from_batches([scans._table(rows_of([b], table["shard"][0].as_py()), fields)])

    if shard_size is None:
        return points.select("ord", "grp", "coords").sortWithinPartitions("ord").mapInArrow(cut, schema)
    return points.select(F.floor(F.col("ord") / shard_size).cast("bigint").alias("shard"), "ord", "grp", "coords").groupBy("shard").applyInArrow(whole, schema)


@method
def one_pass(inst: FairInstance, eps: float = 0.1, lean: bool = False, shard_size: int | None = None, driver_bytes: int = DRIVER_BYTES) -> Summary:
    """The one-pass method for all guesses between simple bounds in one scan; the coordinator's 10 tau and 5 tau finish its shards: at most 17 times the optimum.

    A guess that any shard broke has failed, for its other points are not
    covered.  What the shards keep is collected up to ``driver_bytes``; beyond
    that it stays a table, over which each guess is finished by scans.
    """
    metric, caps = inst.metric, inst.caps
    start, high = simple_upper_bound(inst)
    if high == 0 or not len(start):
        return Summary("one_pass", start, 0.0, high, 0, 0, {"guesses": 0, "stored": len(start)})
    first = scans.first_distinct(inst.points, metric, inst.k + 1)
    guesses = guesses_between(first, inst.k, _half_gap(first, metric, inst.k), high, metric, eps)
    shards = one_pass_shards(inst.points, metric, caps, guesses, lean, shard_size)
    scans._note(0)
    if not isinstance(shards, list):
        shards = saved(shards, "shards")
        size = shards.agg(F.count("*").alias("n"), F.max(F.size("coords") if metric.coords.startswith("array") else F.lit(1)).alias("d")).first()
        if driver_size(size.n, size.d or 0) <= driver_bytes:
            shards = [r.asDict() for r in shards.collect()]
    if isinstance(shards, list):
        failed = {r["g"] for r in shards if r["role"] == "broken"}
        by: dict[int, dict[str, list]] = {}
        for r in shards:
            by.setdefault(r["g"], {}).setdefault(r["role"], []).append(r)
        stored = Counter((r["g"], r["shard"]) for r in shards if r["g"] not in failed and r["role"] == "rep")
        most = max(stored.values(), default=0)
    else:
        per = shards.groupBy("g", "shard").agg(F.bool_or(F.col("role") == "broken").alias("broken"), F.count_if(F.col("role") == "rep").alias("n"))
        per = per.groupBy("g").agg(F.bool_or("broken").alias("broken"), F.max("n").alias("n")).collect()
        failed, most = {r.g for r in per if r.broken}, max((r.n for r in per if not r.broken), default=0)
    for g, tau in enumerate(guesses):
        if g in failed:
            continue
        if isinstance(shards, list):
            x, l = (Points.of([(r["ord"], r["grp"], r["coords"]) for r in by[g][role]], metric).sorted() for role in ("pivot", "rep"))
            chosen, hits, sets = coordinate_at(x, l, metric, caps, tau)
        else:  # pivots of shards are separated by ord; representatives aggregate where they are
            x, l = (shards.where((F.col("g") == g) & (F.col("role") == role)) for role in ("pivot", "rep"))
            with scans.aside():
                (kept,), (broken,), _ = scans.separated_pivots(x, metric, [10 * tau], inst.k)
                if broken:
                    continue
                (near,) = scans.group_reps(l, metric, [kept], [5 * tau])
            chosen, hits = hitting_set(near, caps)
            sets = len(near)
        if chosen is not None and hits == sets:
            return _finish(inst, "one_pass", chosen, start, tau, hits, sets, {"guesses": len(guesses), "stored": most})
    raise AssertionError("the last guess is at least the optimum")


def _within(points: DataFrame | Points, metric: Metric, centres: np.ndarray, allowed: set[int]) -> DataFrame | Points:
    """The points whose nearest centre (the first of several) is allowed; a narrow filter."""
    if isinstance(points, Points):
        return points.take(np.isin(metric.batch(points.coords, centres).argmin(1), list(allowed)))

    def run(it):
        for batch in it:
            if batch.num_rows:
                near = metric.batch(metric.load(batch.column(2)), centres).argmin(1)
                yield batch.filter(pa.array(np.isin(near, list(allowed))))

    return points.select("ord", "grp", "coords").mapInArrow(run, f"ord bigint, grp int, coords {metric.coords}")


def _inventory(points: DataFrame | Points, metric: Metric, centres: np.ndarray) -> dict[tuple[int, int], tuple]:
    """First point by ord of every (cluster, group)."""

    def first_of(parts) -> dict[tuple[int, int], tuple]:
        best: dict[tuple[int, int], tuple] = {}
        for b in parts:
            if not len(b):
                continue
            near = metric.batch(b.coords, centres).argmin(1)
            for c in np.unique(near).tolist():
                for g in np.unique(b.grp[near == c]).tolist():
                    own = np.flatnonzero((near == c) & (b.grp == g))
                    at = own[b.ord[own].argmin()]
                    if (c, g) not in best or b.ord[at] < best[c, g][0]:
                        best[c, g] = (int(b.ord[at]), g, metric.store(b.coords[at : at + 1])[0])
        return best

    if isinstance(points, Points):
        scans._note(len(points) * len(centres))
        return first_of([points])

    def run(it):
        best = first_of(scans._batches(it, metric))
        yield scans._table([{"c": c, "grp": g, "ord": o, "coords": x} for (c, g), (o, _, x) in best.items()], {"c": pa.int32(), "grp": pa.int32(), "ord": pa.int64(), "coords": scans._arrow(metric)})

    rows = points.select("ord", "grp", "coords").mapInArrow(run, f"c int, grp int, ord bigint, coords {metric.coords}")
    rows = rows.groupBy("c", "grp").agg(F.min_by(F.struct("ord", "coords"), "ord").alias("x")).collect()
    scans._note(0)
    return {(r.c, r.grp): (r.x.ord, r.grp, r.x.coords) for r in rows}


@method
def swap_recursive(inst: FairInstance) -> Summary:
    """Farthest-first centres, then swaps inside clusters along shortest paths of the group graph; where over-full groups reach no free one, the clusters they reach are solved again with the other centres fixed."""
    metric = inst.metric

    def solve(points, caps: list[int], fixed: list[tuple], depth: int) -> list[tuple]:
        present = set(points.grp.tolist()) if isinstance(points, Points) else {r.grp for r in points.select("grp").distinct().collect()}
        room = [c if j in present else 0 for j, c in enumerate(caps)]
        if not sum(room):
            return []
        known = Points.of(fixed, metric) if fixed else None
        centres = scans.farthest_first(points, metric, sum(room), known)[0].rows(metric)
        if len(present) <= 1 or not centres:
            return centres
        everyone = Points.of([*centres, *fixed], metric).coords
        stock = _inventory(points, metric, everyone)
        while True:
            count = [sum(c[1] == j for c in centres) for j in range(len(room))]
            over = [j for j in range(len(room)) if count[j] > room[j]]
            if not over:
                return centres
            came: dict[int, tuple[int, int]] = {j: (-1, -1) for j in over}
            queue, goal = list(over), None
            while queue and goal is None:
                i = queue.pop(0)
                for n, c in enumerate(centres):
                    for j in range(len(room)):
                        if c[1] == i and j not in came and (n, j) in stock:
                            came[j] = (i, n)
                            queue.append(j)
                            goal = j if count[j] < room[j] and goal is None else goal
            if goal is None:
                break
            while came[goal][0] >= 0:
                i, n = came[goal]
                centres[n] = stock[n, goal]
                goal = i
        reached = set(came)
        kept = [c for c in centres if c[1] not in reached]
        inside = {n for n, c in enumerate(centres) if c[1] in reached}
        own = _within(points, metric, everyone, inside)
        return kept + solve(own, [c if j in reached else 0 for j, c in enumerate(room)], [*fixed, *kept], depth + 1)

    chosen = Points.of(solve(inst.points, list(inst.caps), [], 0), metric)
    start = scans.first_of_groups(inst.points, metric, inst.caps)
    return _finish(inst, "swap_recursive", chosen, start, 0.0, len(chosen), inst.k, {"stored": inst.k * (len(inst.caps) + 1)})


def distributed_plain(points: DataFrame | Points, metric: Metric, k: int, block_size: int) -> Summary:
    """Farthest-first in every block, then farthest-first on what was sent: at most four times the plain optimum."""
    sent = block_summaries(points, metric, k, block_size=block_size, reps=False)
    X = Points.join([x[3] for x in sent]).sorted() if isinstance(sent, list) else Points.of([(r.ord, r.grp, r.coords) for r in sorted(sent.collect(), key=lambda r: r.ord)], metric)
    picked, low = [], np.full(len(X), np.inf)
    while len(picked) < min(k, len(X)) and low.max(initial=0) > 0:
        picked.append(int(low.argmax()) if picked else 0)
        low = np.minimum(low, metric.batch(X.coords, X.coords[picked[-1:]])[:, 0])
    centres = X.take(picked)
    return Summary("distributed_plain", centres, 0.0, scans.cover_distance(points, metric, [centres.coords])[0], len(picked), len(picked), {"sent": len(X), "passes": 2})


@method
def arbitrary_feasible(inst: FairInstance) -> Summary:
    """The first points of every group."""
    chosen, cost = simple_upper_bound(inst)
    return Summary("arbitrary_feasible", chosen, 0.0, cost, 0, 0, {"stored": len(chosen)})


def exact_small(inst: FairInstance, most: int = 24) -> Summary:
    """The optimum by trying every feasible set of full size; for at most ``most`` points."""
    P = _few(inst, most)
    d = inst.metric.batch(P.coords, P.coords).astype(float)
    room = [min(c, int((P.grp == j).sum())) for j, c in enumerate(inst.caps)]
    best = (np.inf, ())
    for chosen in combinations(range(len(P)), sum(room)):
        if all(sum(P.grp[i] == j for i in chosen) <= room[j] for j in range(len(room))):
            best = min(best, (float(d[:, chosen].min(1).max()) if chosen else np.inf, chosen))
    return Summary("exact_small", P.take(list(best[1])), best[0], best[0], 0, 0, {})

