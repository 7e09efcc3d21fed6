"""The two methods: two passes over the points, and one round of block summaries with a coordinator."""

from __future__ import annotations

import functools
import math
from collections.abc import Callable

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from . import scans
from .hitting import complete, hitting_set
from .metrics import Metric
from .model import FairInstance, Points, Summary
from .storage import saved, scratch

#: A summary of at most this many bytes is finished on the driver; a larger one by scans over it as a table.
DRIVER_BYTES = 96 << 20


def driver_size(rows: int, width: int) -> int:
    """Bytes of collected summary rows in this process: objects for the row, its fields and each coordinate, not their plain values."""
    return rows * (700 + 40 * width)


def method(run: Callable[..., Summary]) -> Callable[..., Summary]:
    """A method over an instance: its points are written once, its intermediate tables go at the end, its scans are counted."""

    @functools.wraps(run)
    def whole(inst: FairInstance, *args, **options) -> Summary:
        with scratch(), scans.ledger() as book:
            out = run(inst.prepared(), *args, **options)
        out.stats |= {"passes": book.scans, "evaluations": book.evaluations}
        return out

    return whole


def geometric_guesses(low: float, high: float, eps: float = 0.1) -> list[float]:
    """low, low(1+eps), ... up to the first value that is at least high; [0] when low is 0."""
    if low <= 0:
        return [0.0]
    out = [low]
    while out[-1] < high:
        out.append(low * (1 + eps) ** len(out))
    return out


def smallest_gap(P: Points, metric: Metric) -> float:
    """The smallest positive distance among a few points; zero when there is none."""
    d = metric.batch(P.coords, P.coords).astype(float) if len(P) > 1 else np.zeros(0)
    return float(d[d > 0].min()) if (d > 0).any() else 0.0


def guesses_between(first: Points, k: int, low: float, high: float, metric: Metric, eps: float) -> list[float]:
    """The ladder from a lower bound.  A bound of zero means at most k positions: then the cost is zero or at least their smallest gap."""
    if low > 0:
        return geometric_guesses(low, high, eps)
    gap = smallest_gap(first, metric)
    return [0.0] + (geometric_guesses(gap, high, eps) if gap > 0 else [])


def _half_gap(first: Points, metric: Metric, k: int) -> float:
    return smallest_gap(first, metric) / 2 if len(first) > k else 0.0


def simple_lower_bound(points: DataFrame | Points, metric: Metric, k: int) -> float:
    """Half the smallest distance among the first k+1 points that differ in position; zero when there are at most k."""
    return _half_gap(scans.first_distinct(points, metric, k + 1), metric, k)


def simple_upper_bound(inst: FairInstance) -> tuple[Points, float]:
    """The first points of every group, and their cost."""
    chosen = scans.first_of_groups(inst.points, inst.metric, inst.caps)
    return chosen, scans.cover_distance(inst.points, inst.metric, [chosen.coords])[0]


def farthest_lower_bound(points: DataFrame | Points, metric: Metric, k: int) -> float:
    """Half the distance at which farthest-first traversal takes its (k+1)-st point."""
    _, trace = scans.farthest_first(points, metric, k + 1)
    return trace[k] / 2 if len(trace) > k else 0.0


def two_pass_at(inst: FairInstance, tau: float, *, quota: bool = False, formulation: str = "canonical") -> tuple[Points | None, int, list[Points]]:
    """(centres, sets met, sets) for one guess; all sets met and at most k pivots is success, and then the cost is at most 3 tau."""
    (pivots,), (broken,), _ = scans.separated_pivots(inst.points, inst.metric, [2 * tau], inst.k)
    if broken:
        return None, 0, []
    (sets,) = scans.group_reps(inst.points, inst.metric, [pivots], [tau], inst.caps if quota else None)
    return *hitting_set(sets, inst.caps, formulation, -1 if quota else 0), sets


def _finish(inst: FairInstance, name: str, chosen: Points | None, pool: Points, tau: float, hits: int, sets: int, stats: dict) -> Summary:
    centres = complete(chosen, inst.caps, pool)
    return Summary(name, centres, tau, scans.cover_distance(inst.points, inst.metric, [centres.coords])[0], hits, sets, stats)


def _size(sets: list[Points]) -> int:
    return sum(map(len, sets))


@method
def two_pass(inst: FairInstance, eps: float = 0.1, search: str = "all", *, quota: bool = False, mode: str = "ordered", name: str = "two_pass") -> Summary:
    """Two passes at every guess between simple bounds, completed to full capacity.

    "all" shares one pair of scans among all guesses and keeps the smallest that
    succeeds; "first_success" and "bisect" run guesses one by one; "best_cost"
    measures every success in one more scan; "relay" needs no upper bound.
    ``mode`` "any" trades the order of pivots for fewer rounds (not with the
    searches that run guesses one by one).
    """
    start, high = simple_upper_bound(inst)
    if high == 0 or not len(start):
        return Summary(name, start, 0.0, high, 0, 0, {"guesses": 0, "stored": len(start)})
    first = scans.first_distinct(inst.points, inst.metric, inst.k + 1)
    if search == "relay":
        return relay(inst, eps, start, first)
    guesses = guesses_between(first, inst.k, _half_gap(first, inst.metric, inst.k), high, inst.metric, eps)
    pick = -1 if quota else 0
    if search in ("all", "best_cost"):
        pivots, broken, rounds = scans.separated_pivots(inst.points, inst.metric, [2 * t for t in guesses], inst.k, mode=mode)
        alive = [g for g, b in enumerate(broken) if not b]
        sets = scans.group_reps(inst.points, inst.metric, [pivots[g] for g in alive], [guesses[g] for g in alive], inst.caps if quota else None)
        good = []
        for g, s in zip(alive, sets):
            chosen, hits = hitting_set(s, inst.caps, pick=pick)
            if hits == len(s):
                good.append((guesses[g], chosen, hits, s))
                if search == "all":
                    break
        stats = {"guesses": len(guesses), "rounds": rounds, "stored": max(map(_size, sets), default=0)}
        if search == "best_cost":
            full = [complete(c, inst.caps, start) for _, c, _, _ in good]
            costs = scans.cover_distance(inst.points, inst.metric, [f.coords for f in full])
            at = int(np.argmin(costs))
            return Summary(name, full[at], good[at][0], costs[at], good[at][2], len(good[at][3]), stats)
        tau, chosen, hits, s = good[0]
        return _finish(inst, name, chosen, start, tau, hits, len(s), stats)
    tried: dict[int, tuple[Points | None, int, list[Points]]] = {}

    def attempt(g: int) -> bool:
        if g not in tried:
            tried[g] = two_pass_at(inst, guesses[g], quota=quota)
        return tried[g][0] is not None and tried[g][1] == len(tried[g][2])

    if search == "first_success":
        at = next(g for g in range(len(guesses)) if attempt(g))
    else:  # the last guess is at least the optimum and succeeds; what lies below a failure is not needed
        lo, at = -1, len(guesses) - 1
        attempt(at)
        while at - lo > 1:
            mid = (lo + at) // 2
            lo, at = (lo, mid) if attempt(mid) else (mid, at)
    chosen, hits, sets = tried[at]
    return _finish(inst, name, chosen, start, guesses[at], hits, len(sets), {"guesses": len(tried), "stored": max(_size(t[2]) for t in tried.values())})


class RelaySlot:
    """A guess that starts again 1/eps higher when it breaks, with its own pivots replayed as the prefix."""

    def __init__(self, tau: float, metric: Metric, k: int, eps: float):
        self.tau, self.metric, self.k, self.eps = tau, metric, k, eps
        self.pivots: Points | None = None

    def insert(self, more: Points) -> None:
        while True:
            open_ = np.ones(len(more), bool) if self.pivots is None else self.metric.batch(more.coords, self.pivots.coords).min(1) > 2 * self.tau
            if not open_.any():
                return
            at = [int(open_.argmax())]
            self.pivots = more.take(at) if self.pivots is None else Points.join([self.pivots, more.take(at)])
            while len(self.pivots) > self.k:
                self.raise_guess()

    def raise_guess(self) -> None:
        self.tau /= self.eps
        old, self.pivots = self.pivots, None
        self.insert(old)


def relay(inst: FairInstance, eps: float, start: Points, first: Points) -> Summary:
    """One scan without an upper bound: live guesses span a factor 1/eps, and one that breaks is relayed 1/eps higher.

    Partitions relay on their own; their few pivots are relayed again as they
    meet, by levels.  A point ends within about 2 tau (1 + O(eps)) of a pivot
    for each level it went through, so one level of partitions gives about 5
    times the optimum and a single partition about 3.  The second scan collects
    representatives; guesses that cannot be met are relayed and tried again.
    """
    metric, k = inst.metric, inst.k
    if len(first) <= k:  # all positions are known: the optimum is zero, or at least their smallest gap
        (at_zero,) = scans.group_reps(inst.points, metric, [first], [0.0])
        chosen, hits = hitting_set(at_zero, inst.caps)
        if hits == len(at_zero):
            return _finish(inst, "two_pass_relay", chosen, start, 0.0, hits, hits, {"guesses": 1, "stored": _size(at_zero)})
    low = _half_gap(first, metric, k) or smallest_gap(first, metric)
    slots = max(1, math.ceil(math.log(1 / eps) / math.log(1 + eps)))
    taus = [low * (1 + eps) ** i for i in range(slots)]
    fields = {"s": pa.int32(), "part": pa.int64(), "tau": pa.float64(), "ord": pa.int64(), "grp": pa.int32(), "coords": scans._arrow(metric)}
    schema = f"s int, part bigint, tau double, ord bigint, grp int, coords {metric.coords}"

    def as_rows(s: int, part: int, slot: RelaySlot) -> list[dict]:
        return [] if slot.pivots is None else [{"s": s, "part": part, "tau": slot.tau, "ord": o, "grp": g, "coords": c} for o, g, c in slot.pivots.rows(metric)]

    def meet(rows: list) -> RelaySlot:
        slot = RelaySlot(max(r["tau"] for r in rows), metric, k, eps)
        slot.insert(Points.of([(r["ord"], r["grp"], r["coords"]) for r in sorted(rows, key=lambda r: r["ord"])], metric))
        return slot

    if isinstance(inst.points, Points):
        state = [RelaySlot(t, metric, k, eps) for t in taus]
        for slot in state:
            slot.insert(inst.points.sorted())
        scans._note(0)
    else:

        def run(it):
            from pyspark import TaskContext

            own = [RelaySlot(t, metric, k, eps) for t in taus]
            for b in scans._batches(it, metric):
                for slot in own:
                    slot.insert(b)
            part = TaskContext.get().partitionId()
            yield scans._table([x for s, slot in enumerate(own) for x in as_rows(s, part, slot)], fields)

        def join(table: pa.Table) -> pa.Table:
            rows = table.to_pylist()
            return pa.Table.from_batches([scans._table(as_rows(rows[0]["s"], rows[0]["part"] // scans.FAN, meet(rows)), fields)])

        points = inst.points.select("ord", "grp", "coords")
        got, lists = points.sortWithinPartitions("ord").mapInArrow(run, schema), points.rdd.getNumPartitions()
        while lists > scans.FAN:
            got = got.groupBy("s", F.floor(F.col("part") / scans.FAN).alias("bucket")).applyInArrow(lambda t: join(t), schema)
            lists = -(-lists // scans.FAN)
        by: dict[int, list] = {}
        for r in got.collect():
            by.setdefault(r.s, []).append(r)
        scans._note(0)
        state = [meet(rows) for rows in by.values()]
    live, stored = state, 0
    while True:
        live.sort(key=lambda slot: slot.tau)
        sets = scans.group_reps(inst.points, metric, [slot.pivots for slot in live], [slot.tau for slot in live])
        stored = max([stored, *map(_size, sets)])
        for slot, s in zip(live, sets):
            chosen, hits = hitting_set(s, inst.caps)
            if hits == len(s):
                return _finish(inst, "two_pass_relay", chosen, start, slot.tau, hits, len(s), {"guesses": slots, "stored": stored})
        for slot in live:
            slot.raise_guess()


def optimal_blocks(n: int, m: int, k: int) -> int:
    """Number of blocks that balances block and coordinator work: about sqrt(n / (m k))."""
    return max(1, round(math.sqrt(n / (m * k))))


def summarise(ords: np.ndarray, grps: np.ndarray, X: np.ndarray, metric: Metric, k: int) -> tuple[list[int], list[tuple[int, int]], float]:
    """One block: rows of its farthest-first pivots, (pivot, row) of representatives within 2r, and r.

    Sweeps keep a running minimum and the distance column of every pivot, which
    the representatives reuse.  At most k positions: all of them, and r is zero.
    """
    order = np.argsort(ords, kind="stable")
    ords, grps, X = ords[order], grps[order], X[order]
    pivots, columns, low, r = [], [], np.full(len(X), np.inf), 0.0
    while len(X):
        at = 0 if not pivots else int(low.argmax())
        if pivots and low[at] <= 0:
            break
        if len(pivots) == k:
            r = float(low[at]) / 2
            break
        pivots.append(at)
        columns.append(metric.batch(X, X[at : at + 1])[:, 0].astype(float))
        low = np.minimum(low, columns[-1])
    reps = []
    for p, at in enumerate(pivots):
        near = np.flatnonzero(columns[p] <= 2 * r)
        reps.append((p, at))
        for g in np.unique(grps[near]):
            if g != grps[at]:
                reps.append((p, int(near[grps[near] == g][0])))
    return [int(order[p]) for p in pivots], [(p, int(order[i])) for p, i in reps], r


def block_summaries(points: DataFrame | Points, metric: Metric, k: int, *, block_size: int | None = None, reps: bool = True) -> DataFrame | list[tuple]:
    """The message of every block: (block, role, pivot, ord, grp, coords, r), role "pivot" or "rep"; a point may have several rows.

    Blocks are ``ord div block_size``, a column named ``block``, or, with
    neither, the partitions as they are: then nothing is shuffled.  Of points
    held as arrays the message is a list of (block, role, pivot, point, r).
    """
    if isinstance(points, Points):
        out = []
        for b in np.unique(points.ord // block_size if block_size else np.zeros(len(points), np.int64)).tolist():
            own = points.take(points.ord // block_size == b) if block_size else points
            at, found, r = summarise(own.ord, own.grp, own.coords, metric, k)
            out += [(b, "pivot", p, own.take([i]), r) for p, i in enumerate(at)] + ([(b, "rep", p, own.take([i]), r) for p, i in found] if reps else [])
        return out
    schema = f"block bigint, role string, pivot int, ord bigint, grp int, coords {metric.coords}, r double"

    def rows_of(number: int, ords, grps, column) -> pa.Table:
        X = metric.load(column)
        pivots, found, r = summarise(ords, grps, X, metric, k)
        rows = [("pivot", p, i) for p, i in enumerate(pivots)] + ([("rep", p, i) for p, i in found] if reps else [])
        at = pa.array([i for _, _, i in rows], pa.int64())
        return pa.table({"block": pa.array([number] * len(rows), pa.int64()), "role": pa.array([x for x, _, _ in rows], pa.string()), "pivot": pa.array([p for _, p, _ in rows], pa.int32()), "ord": pa.array(ords).take(at), "grp": pa.array(grps, pa.int32()).take(at), "coords": column.take(at), "r": pa.array([r] * len(rows), pa.float64())})

    def whole(table):
        column = table["coords"].combine_chunks()
        return rows_of(table["block"][0].as_py(), table["ord"].to_numpy(), table["grp"].to_numpy(), column)

    def cut(batches):
        from pyspark import TaskContext

        for i, b in enumerate(batches):  # Arrow batches are blocks: bounded rows, no shuffle
            if b.num_rows:
                yield from rows_of((TaskContext.get().partitionId() << 32) + i, b.column(0).to_numpy(), b.column(1).to_numpy(), b.column(2)).to_batches()

    if block_size is None and "block" not in points.columns:
        return points.select("ord", "grp", "coords").mapInArrow(cut, schema)
    number = F.col("block").cast("bigint") if block_size is None else F.floor(F.col("ord") / block_size).cast("bigint")
    return points.select(number.alias("block"), "ord", "grp", "coords").groupBy("block").applyInArrow(whole, schema)


def separated_at(X: Points, metric: Metric, radius: float, k: int) -> list[int]:
    """Places of greedy pivots in the order given, at most k+1 of them."""
    kept: list[int] = []
    low = np.full(len(X), np.inf)
    while len(kept) <= k and (low > radius).any():
        kept.append(int((low > radius).argmax()))
        low = np.minimum(low, metric.batch(X.coords, X.coords[kept[-1:]])[:, 0])
    return kept


def coordinate_at(pivots: Points, reps: Points, metric: Metric, caps: tuple[int, ...], tau: float, pick: int = 0) -> tuple[Points | None, int, int]:
    """The coordinator at one guess: separated pivots of all block pivots at 10 tau, in the order given, representatives at 5 tau, a hitting set."""
    k = sum(caps)
    kept = separated_at(pivots, metric, 10 * tau, k)
    if len(kept) > k:
        return None, 0, len(kept)
    with scans.aside():
        (sets,) = scans.group_reps(reps, metric, [pivots.take(kept)], [5 * tau])
    chosen, hits = hitting_set(sets, caps, pick=pick)
    return chosen, hits, len(sets)


@method
def distributed(inst: FairInstance, block_size: int | None = None, eps: float = 0.1, scale: float = 5.1, ordering: str = "block", name: str = "distributed", driver_bytes: int = DRIVER_BYTES) -> Summary:
    """Block summaries, then the coordinator from the largest block radius (divided by ``scale``) upward until every set is met.

    ``ordering`` is the order in which the coordinator sees block pivots: by
    block, or "widest_first".  A summary of more than ``driver_bytes`` stays a
    table and the coordinator runs its guesses as scans over it, with the same
    result.
    """
    message = block_summaries(inst.points, inst.metric, inst.k, block_size=block_size)
    if isinstance(message, list):
        scans._note(0)
        blocks = {b: r for b, _, _, _, r in message}
        rank = {b: i for i, b in enumerate(sorted(blocks, key=(lambda b: (-blocks[b], b)) if ordering == "widest_first" else None))}
        message.sort(key=lambda x: (rank[x[0]], x[2], x[3].ord[0]))
        pivots, reps = (Points.join([x[3] for x in message if x[1] == role]) if message else Points.empty() for role in ("pivot", "rep"))
        n, radius, sizes, on_driver = len(message), max(blocks.values(), default=0.0), [len({int(x[3].ord[0]) for x in message if x[0] == b}) for b in blocks], True
    else:
        table = saved(message, "summaries")
        scans._note(0)
        width = F.size("coords") if inst.metric.coords.startswith("array") else F.lit(1)
        per = table.groupBy("block").agg(F.count("*").alias("n"), F.max("r").alias("r"), F.count_distinct("ord").alias("sent"), F.max(width).alias("d"))
        total = per.agg(F.sum("n").alias("n"), F.max("r").alias("r"), F.count("*").alias("b"), F.sum("sent").alias("sent"), F.max("sent").alias("most"), F.max("d").alias("d")).first()
        n, radius = total.n or 0, float(total.r or 0)
        if n:
            sizes, on_driver = [total.most, *[0] * (total.b - 1)], driver_size(n, total.d) <= driver_bytes
            # one small row a block in one task, at most a ten-thousandth of the points: their place in the coordinator's order
            order = [F.desc("r"), "block"] if ordering == "widest_first" else ["block"]
            place = per.select("block", (F.row_number().over(Window.orderBy(*order)) * (inst.k + 1)).cast("long").alias("at"))
            table = table.join(place, "block").withColumn("pos", F.col("at") + F.col("pivot"))
            if on_driver:
                rows = sorted(table.collect(), key=lambda r: (r.pos, r.ord))
                pivots, reps = (Points.of([(r.ord, r.grp, r.coords) for r in rows if r.role == role], inst.metric) for role in ("pivot", "rep"))
    if not n:
        return Summary(name, Points.empty(), 0.0, 0.0, 0, 0, {"sent": 0, "blocks": 0, "guesses": 0, "stored": 0})
    sent = sum(sizes) if isinstance(message, list) else total.sent
    stats = {"sent": sent, "blocks": len(sizes), "stored": max(sizes)}
    if on_driver:
        x, l = Points(np.arange(len(pivots)), pivots.grp, pivots.coords), reps.take(np.unique(reps.ord, return_index=True)[1])
        attempt = lambda t: coordinate_at(pivots, reps, inst.metric, inst.caps, t)
    else:
        x = saved(table.where("role = 'pivot'").select(F.col("pos").alias("ord"), "grp", "coords", F.col("ord").alias("own")), "pivots")
        l = saved(table.where("role = 'rep'").groupBy("ord").agg(F.any_value("grp").alias("grp"), F.any_value("coords").alias("coords")), "reps")

        def attempt(t: float):
            (p,), (broken,), _ = scans.separated_pivots(x, inst.metric, [10 * t], inst.k)
            if broken:
                return None, 0, len(p)
            own = {r.ord: r.own for r in x.where(F.col("ord").isin(p.ord.tolist())).select("ord", "own").collect()}
            p = Points(np.array([own[o] for o in p.ord.tolist()]), p.grp, p.coords)
            (sets,) = scans.group_reps(l, inst.metric, [p], [5 * t])
            chosen, hits = hitting_set(sets, inst.caps)
            return chosen, hits, len(sets)

    with scans.aside():
        pool = scans.first_of_groups(l, inst.metric, inst.caps)
        if not len(pool):
            raise ValueError("no group that has points has a capacity")
        base, step, tried = radius / scale, 0, 0
        while True:
            tau = base * (1 + eps) ** step
            tried += 1
            chosen, hits, sets = attempt(tau)
            if chosen is not None and hits == sets:
                break
            step += 1
            if base == 0:  # every block has at most k positions, and not all costs are zero: below any positive cost
                few, trace = scans.farthest_first(x, inst.metric, inst.k + 1)
                base, step = (trace[inst.k] / 2 if len(few) > inst.k else smallest_gap(few, inst.metric)) / scale, 0
    return _finish(inst, name, chosen, pool, tau, hits, sets, stats | {"guesses": tried})
