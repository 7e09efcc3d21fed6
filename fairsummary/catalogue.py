"""All queries of the library and their SQL, kept in one registry so that a key never lacks its pair."""

from __future__ import annotations

import math
from collections.abc import Callable
from contextlib import nullcontext

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import baselines, graphs, hardness, methods, metrics, oracles as sql, relational, scans, studies
from .hitting import certificate, hitting_set
from .model import FairInstance, Points, Summary
from .session import find_package
from .storage import saved, scratch
from .workloads import FIXTURES, Fixture, duck_sql, spark_sql, whole

FLAGSHIP = "two_pass_emb_m2"
_QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
_ORACLES: dict[str, str] = {}


def _add(name: str, query: Callable[[SparkSession, str], DataFrame], oracle: str | None = None, lazy: bool = False) -> None:
    """``lazy`` queries return a plan over the tables; the others return rows of the driver, and what they saved goes with them."""

    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        with nullcontext() if lazy else scratch():
            return query(find_package(spark), sf_dir)

    _QUERIES[name] = run
    if oracle:
        _ORACLES[name] = oracle


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return dict(_QUERIES)


def oracles() -> dict[str, str]:
    return dict(_ORACLES)


def _rows(spark: SparkSession, rows: list, schema: str) -> DataFrame:
    return spark.createDataFrame(rows, schema)


# ---------------------------------------------------------------- SQL pieces


def _greedy(f: Fixture, radius: float, most: int) -> str:
    """Rows (step, pv) of greedy pivots: all points carry their distance to the pivots so far."""
    return f"""p AS ({f.duck}),
run AS (SELECT CAST(0 AS BIGINT) AS step, ord, coords, CAST(4e18 AS DOUBLE) AS md, CAST(NULL AS BIGINT) AS pv FROM p
UNION ALL SELECT r.step + 1, r.ord, r.coords, least(r.md, CAST({f.metric.sql("r.coords", "c.coords")} AS DOUBLE)), c.ord
FROM run r, (SELECT ord, coords FROM run WHERE md > {radius!r} AND step < {most} ORDER BY ord LIMIT 1) c),
piv AS (SELECT DISTINCT step, pv FROM run WHERE pv IS NOT NULL)"""


def _farthest(f: Fixture, t: int) -> str:
    """Rows (step, pv, far) of farthest-first traversal; far is the distance at which a point is taken."""
    return f"""p AS ({f.duck}),
run AS (SELECT CAST(0 AS BIGINT) AS step, ord, coords, CAST(4e18 AS DOUBLE) AS md, CAST(NULL AS BIGINT) AS pv, CAST(NULL AS DOUBLE) AS far FROM p
UNION ALL SELECT r.step + 1, r.ord, r.coords, least(r.md, CAST({f.metric.sql("r.coords", "c.coords")} AS DOUBLE)), c.ord, c.md
FROM run r, (SELECT ord, coords, md FROM run WHERE md > 0 AND step < {t} ORDER BY md DESC, ord LIMIT 1) c),
piv AS (SELECT DISTINCT step, pv, far FROM run WHERE pv IS NOT NULL)"""


def _first(f: Fixture) -> str:
    caps = ", ".join(map(str, f.caps))
    return f"p AS ({f.duck}), s AS (SELECT * FROM (SELECT *, row_number() OVER (PARTITION BY grp ORDER BY ord) AS n FROM p) x WHERE n <= ([{caps}])[grp + 1])"


def _reps(f: Fixture, radius: float, quota: bool = False) -> str:
    """Rows (pv, grp, ord) of representatives; needs p and piv."""
    d = f.metric.sql("a.coords", "b.coords")
    room = f"([{', '.join(map(str, f.caps))}])[grp + 1]" if quota else "1"
    return f"""near AS (SELECT piv.pv, b.grp AS pgrp, a.grp, a.ord FROM piv JOIN p b ON b.ord = piv.pv JOIN p a ON a.ord <> piv.pv AND {d} <= {radius!r}),
rep AS (SELECT pv, grp, ord FROM (SELECT *, row_number() OVER (PARTITION BY pv, grp ORDER BY ord) AS n FROM near) x WHERE n <= {room} - CASE WHEN grp = pgrp THEN 1 ELSE 0 END
UNION ALL SELECT piv.pv, b.grp, b.ord FROM piv JOIN p b ON b.ord = piv.pv)"""


def _cut(f: Fixture) -> str:
    """Column hits of the largest matching as a minimum cut over group subsets; needs rep."""
    m = len(f.caps)
    held = " + ".join(f"CASE WHEN (j >> {i}) & 1 = 1 THEN {c} ELSE 0 END" for i, c in enumerate(f.caps))
    return f"masks AS (SELECT pv, CAST(bit_or(1 << grp) AS BIGINT) AS b FROM rep GROUP BY pv), cuts AS (SELECT j, {held} + (SELECT count(*) FROM masks WHERE (b & ~j) <> 0) AS v FROM range(0, {1 << m}) t(j))"


#: Radii used where a query fixes one; chosen once from the fixtures' distance ranges.
TAU = {"emb_m2": 5_000_000, "emb_m4": 5_000_000, "part_shape": 9000, "customer_bal": 150000, "pref_rank_m2": 4, "supplier_bal": 150000, "turn_shape": 120, "doc_letters": 150, "page_shape": 9000, "events": 20000}
TAU |= {"emb_all_m2": TAU["emb_m2"], "emb_all_m4": TAU["emb_m4"], "pref_rank_all_m2": TAU["pref_rank_m2"]}


def _points(name: str, f: Fixture) -> None:
    many = f.metric.coords.startswith("array")
    flat = (lambda d: d.select("ord", "grp", F.array_join(F.transform("coords", lambda x: x.cast("string")), ",").alias("coords"))) if many else (lambda d: d)
    _add(f"points_{name}", lambda s, d: flat(f.points(s, d)), f"SELECT ord, grp, {'array_to_string(coords, chr(44))' if many else 'coords'} AS coords FROM ({f.duck}) q", lazy=True)


def _building_blocks(name: str) -> None:
    f, tau = FIXTURES[name], float(TAU[name])
    k = sum(f.caps)
    metric = f.metric

    def arbitrary(s, d):
        return _rows(s, [(o, g) for o, g, _ in scans.first_of_groups(f.points(s, d), metric, f.caps).rows(metric)], "ord bigint, grp int")

    _add(f"first_of_groups_{name}", arbitrary, f"WITH {_first(f)} SELECT ord, grp FROM s")
    worst = f"d AS (SELECT a.ord, a.grp, min({metric.sql('a.coords', 's.coords')}) AS d FROM p a, s GROUP BY a.ord, a.grp)"
    _add(f"simple_upper_bound_{name}", lambda s, d: _rows(s, [(methods.simple_upper_bound(f.instance(s, d))[1],)], "cost double"), f"WITH {_first(f)}, {worst} SELECT CAST(max(d) AS DOUBLE) AS cost FROM d")

    def assigned(s, d):
        points = f.points(s, d)
        return scans.nearest_centre(points, metric, scans.first_of_groups(points, metric, f.caps)).withColumn("d", F.col("d").cast("double"))

    near = f"n AS (SELECT a.ord, a.grp, s.ord AS centre, CAST({metric.sql('a.coords', 's.coords')} AS DOUBLE) AS d FROM p a, s)"
    _add(f"cover_assignment_{name}", assigned, f"WITH {_first(f)}, {near} SELECT ord, grp, centre, d FROM (SELECT *, row_number() OVER (PARTITION BY ord ORDER BY d, centre) AS r FROM n) x WHERE r = 1")
    _add(f"cost_per_group_{name}", lambda s, d: assigned(s, d).groupBy("grp").agg(F.max("d").alias("cost")), f"WITH {_first(f)}, {near} SELECT grp, max(d) AS cost FROM (SELECT ord, grp, min(d) AS d FROM n GROUP BY ord, grp) x GROUP BY grp")

    def points_of(s, d):
        return saved(f.points(s, d).repartition(4), "points")

    def low(s, d):
        return _rows(s, [(methods.simple_lower_bound(points_of(s, d), metric, k),)], "low double")

    _add(f"simple_lower_bound_{name}", low, f"WITH RECURSIVE {_greedy(f, 0, k + 1)}, q AS (SELECT p.ord, p.coords FROM p JOIN piv ON pv = ord) SELECT CASE WHEN (SELECT count(*) FROM q) <= {k} THEN 0.0 ELSE (SELECT CAST(min({metric.sql('a.coords', 'b.coords')}) AS DOUBLE) / 2 FROM q a JOIN q b ON a.ord < b.ord) END AS low")

    def pivots(s, d, r=2 * tau):
        (found,), _, _ = scans.separated_pivots(points_of(s, d), metric, [r], None)
        return found

    _add(f"separated_pivots_{name}", lambda s, d: _rows(s, list(enumerate(pivots(s, d).ord.tolist(), 1)), "step bigint, pivot bigint"), f"WITH RECURSIVE {_greedy(f, 2 * tau, 10**6)} SELECT step, pv AS pivot FROM piv")

    def reps(s, d, quota=None):
        points = f.points(s, d)
        P = pivots(s, d)
        (sets,) = scans.group_reps(points, metric, [P], [tau], quota)
        return _rows(s, [(int(o), int(x.grp[i]), int(x.ord[i])) for o, x in zip(P.ord, sets) for i in range(len(x))], "pivot bigint, grp int, rep bigint")

    base = f"WITH RECURSIVE {_greedy(f, 2 * tau, 10**6)}, "
    _add(f"group_reps_{name}", reps, base + _reps(f, tau) + " SELECT pv AS pivot, grp, ord AS rep FROM rep")
    _add(f"quota_reps_{name}", lambda s, d: reps(s, d, f.caps), base + _reps(f, tau, True) + " SELECT pv AS pivot, grp, ord AS rep FROM rep")
    _add(f"ball_members_{name}", lambda s, d: scans.ball_members(f.points(s, d), metric, [pivots(s, d)], [tau]).select("pivot", "ord", "grp"), base.removesuffix(", ") + f" SELECT piv.pv AS pivot, a.ord, a.grp FROM piv JOIN p b ON b.ord = piv.pv JOIN p a ON {metric.sql('a.coords', 'b.coords')} <= {tau!r}")

    def hits(s, d):
        (sets,) = scans.group_reps(f.points(s, d), metric, [pivots(s, d)], [tau])
        edges = [set(x.grp.tolist()) for x in sets]
        return _rows(s, [(len(sets), hitting_set(sets, f.caps)[1], hitting_set(sets, f.caps, "slots")[1], hitting_set(sets, f.caps, "canonical")[1], certificate(edges, f.caps))], "sets bigint, flow bigint, slots bigint, canonical bigint, cut bigint")

    _add(f"hitting_set_{name}", hits, base + _reps(f, tau) + ", " + _cut(f) + " SELECT (SELECT count(*) FROM masks) AS sets, CAST(min(v) AS BIGINT) AS flow, CAST(min(v) AS BIGINT) AS slots, CAST(min(v) AS BIGINT) AS canonical, CAST(min(v) AS BIGINT) AS cut FROM cuts")

    def traversal(s, d):
        found, trace = scans.farthest_first(points_of(s, d), metric, k + 1)
        return _rows(s, [(i, int(o), None if math.isinf(t) else t) for i, (o, t) in enumerate(zip(found.ord, trace), 1)], "step bigint, ord bigint, far double")

    _add(f"farthest_first_{name}", traversal, f"WITH RECURSIVE {_farthest(f, k + 1)} SELECT step, pv AS ord, CASE WHEN step = 1 THEN NULL ELSE far END AS far FROM piv")
    _add(f"farthest_lower_bound_{name}", lambda s, d: _rows(s, [(methods.farthest_lower_bound(points_of(s, d), metric, k),)], "low double"), f"WITH RECURSIVE {_farthest(f, k + 1)} SELECT coalesce(max(CASE WHEN step = {k + 1} THEN far / 2 END), 0.0) AS low FROM piv")
    _add(f"plain_farthest_{name}", lambda s, d: _rows(s, [(baselines.plain_farthest(points_of(s, d), metric, k).cost,)], "cost double"), f"WITH RECURSIVE {_farthest(f, k)}, c AS (SELECT p.coords FROM p JOIN piv ON pv = ord) SELECT CAST(max(d) AS DOUBLE) AS cost FROM (SELECT a.ord, min({metric.sql('a.coords', 'c.coords')}) AS d FROM p a, c GROUP BY a.ord) x")

    guesses = [tau * 1.5**i for i in range(-2, 3)]

    def trace(s, d):
        out = []
        points = points_of(s, d)
        found, broken, _ = scans.separated_pivots(points, metric, [2 * t for t in guesses], k)
        alive = [g for g, b in enumerate(broken) if not b]
        sets = dict(zip(alive, scans.group_reps(points, metric, [found[g] for g in alive], [guesses[g] for g in alive])))
        for g, t in enumerate(guesses):
            n = hitting_set(sets[g], f.caps)[1] if g in sets else None
            out.append((g, t, len(found[g]), n, g in sets and n == len(sets[g])))
        return _rows(s, out, "guess int, tau double, pivots bigint, hits bigint, success boolean")

    parts = []
    for g, t in enumerate(guesses):
        parts.append(f"SELECT * FROM (WITH RECURSIVE {_greedy(f, 2 * t, k + 1)}, {_reps(f, t)}, {_cut(f)}, c AS (SELECT count(*) AS n FROM piv) SELECT CAST({g} AS INTEGER) AS guess, CAST({t!r} AS DOUBLE) AS tau, n AS pivots, CASE WHEN n <= {k} THEN (SELECT CAST(min(v) AS BIGINT) FROM cuts) END AS hits, n <= {k} AND (SELECT min(v) FROM cuts) = n AS success FROM c) g{g}")
    _add(f"two_pass_trace_{name}", trace, " UNION ALL ".join(parts))


def _blocks(name: str, size: int) -> None:
    f = FIXTURES[name]
    k, metric = sum(f.caps), f.metric
    run = f"""WITH RECURSIVE p AS (SELECT *, CAST(floor(ord / {size}) AS BIGINT) AS block FROM ({f.duck}) q),
run AS (SELECT CAST(0 AS BIGINT) AS step, block, ord, coords, CAST(4e18 AS DOUBLE) AS md, CAST(NULL AS BIGINT) AS pv, CAST(NULL AS DOUBLE) AS far FROM p
UNION ALL SELECT r.step + 1, r.block, r.ord, r.coords, least(r.md, CAST({metric.sql("r.coords", "c.coords")} AS DOUBLE)), c.ord, c.md
FROM run r JOIN (SELECT block, ord, coords, md FROM (SELECT *, row_number() OVER (PARTITION BY block ORDER BY md DESC, ord) AS n FROM run WHERE md > 0 AND step <= {k}) x WHERE n = 1) c ON c.block = r.block),
piv AS (SELECT DISTINCT block, step, pv, far FROM run WHERE pv IS NOT NULL),
rad AS (SELECT block, coalesce(max(CASE WHEN step = {k + 1} THEN far / 2 END), 0.0) AS r FROM piv GROUP BY block)"""
    rep = f""", near AS (SELECT piv.block, piv.step, a.ord, a.grp, b.grp AS pgrp FROM piv JOIN rad ON rad.block = piv.block JOIN p b ON b.ord = piv.pv JOIN p a ON a.block = piv.block AND {metric.sql("a.coords", "b.coords")} <= 2 * r WHERE step <= {k}),
rep AS (SELECT block, step, min(ord) AS ord FROM near WHERE grp <> pgrp GROUP BY block, step, grp UNION ALL SELECT block, step, pv FROM piv WHERE step <= {k})"""

    def message(s, d):
        return methods.block_summaries(f.points(s, d), metric, k, block_size=size)

    _add(f"block_summaries_{name}", lambda s, d: message(s, d).select("block", "role", F.col("pivot").cast("bigint").alias("pivot"), "ord", F.round("r", 3).alias("r")), run + rep + f" SELECT piv.block, 'pivot' AS role, step - 1 AS pivot, pv AS ord, round(r, 3) AS r FROM piv JOIN rad ON rad.block = piv.block WHERE step <= {k} UNION ALL SELECT rep.block, 'rep', step - 1, ord, round(r, 3) FROM rep JOIN rad ON rad.block = rep.block")
    _add(f"block_radii_{name}", lambda s, d: message(s, d).groupBy("block").agg(F.max("r").alias("r")), run + " SELECT block, r FROM rad")
    _add(f"message_sizes_{name}", lambda s, d: message(s, d).groupBy("block").agg(F.count_distinct("ord").alias("sent")), run + rep + " SELECT block, count(DISTINCT ord) AS sent FROM rep GROUP BY block")


_METHOD = "method string, tau double, cost double, ratio double, centres int, group_counts string, feasible boolean, hits int, sets int, guesses int, stored bigint, sent bigint, chosen string"


def method_row(caps: tuple[int, ...], summary: Summary, low: float) -> tuple:
    """A method's result: ratio is cost to the farthest-first bound; stored and sent are points; chosen lists the centres by ord."""
    count = [int((summary.centres.grp == j).sum()) for j in range(len(caps))]
    st = summary.stats
    return (summary.method, round(float(summary.tau), 6), float(summary.cost), round(summary.cost / low, 6) if low else None, len(summary.centres), ",".join(map(str, count)), all(c <= q for c, q in zip(count, caps)), int(summary.hits), int(summary.sets), int(st.get("guesses", 0)), int(st.get("stored", 0)), int(st.get("sent", 0)), ",".join(map(str, sorted(summary.centres.ord.tolist()))))


#: Points of a block in the comparisons, and of a shard of the one-pass method.
BLOCK, SHARD = 25, 125


def _run(name: str, inst: FairInstance, block: int = BLOCK) -> Summary:
    summary = {
        "two_pass": lambda: methods.two_pass(inst),
        "two_pass_first": lambda: methods.two_pass(inst, search="first_success"),
        "two_pass_bisect": lambda: methods.two_pass(inst, search="bisect"),
        "two_pass_best_cost": lambda: methods.two_pass(inst, search="best_cost"),
        "two_pass_any_order": lambda: methods.two_pass(inst, mode="any"),
        "two_pass_relay": lambda: methods.two_pass(inst, search="relay"),
        "distributed": lambda: methods.distributed(inst, block_size=block),
        "distributed_scale1": lambda: methods.distributed(inst, block_size=block, scale=1.0),
        "distributed_widest": lambda: methods.distributed(inst, block_size=block, ordering="widest_first"),
        "ball_matching": lambda: baselines.ball_matching(inst),
        "quota_two_pass": lambda: baselines.quota_two_pass(inst),
        "one_pass": lambda: baselines.one_pass(inst, shard_size=SHARD),
        "one_pass_lean": lambda: baselines.one_pass(inst, lean=True, shard_size=SHARD),
        "swap_recursive": lambda: baselines.swap_recursive(inst),
        "arbitrary_feasible": lambda: baselines.arbitrary_feasible(inst),
    }[name]()
    summary.method = name
    return summary


def _method_sql(f: Fixture, name: str, block: int = BLOCK) -> str | None:
    makers = {
        "two_pass": lambda: sql.two_pass(f, name),
        "two_pass_first": lambda: sql.two_pass(f, name, "first_success"),
        "two_pass_bisect": lambda: sql.two_pass(f, name, "bisect"),
        "two_pass_best_cost": lambda: sql.two_pass(f, name, "best_cost"),
        "distributed": lambda: sql.distributed(f, name, block),
        "distributed_scale1": lambda: sql.distributed(f, name, block, 1.0),
        "distributed_widest": lambda: sql.distributed(f, name, block, widest=True),
        "ball_matching": lambda: sql.two_pass(f, name, kind="nearest", low="low11"),
        "quota_two_pass": lambda: sql.two_pass(f, name, kind="quota"),
        "arbitrary_feasible": lambda: sql.arbitrary(f, name),
        "one_pass": lambda: sql.one_pass(f, name, SHARD),
        "one_pass_lean": lambda: sql.one_pass(f, name, SHARD, lean=True),
    }
    return makers[name]() if name in makers else None


ALL = ["two_pass", "two_pass_first", "two_pass_bisect", "two_pass_best_cost", "two_pass_any_order", "two_pass_relay", "distributed", "distributed_scale1", "distributed_widest", "ball_matching", "quota_two_pass", "one_pass", "one_pass_lean", "swap_recursive", "arbitrary_feasible"]
#: The methods of the published comparison; the last one has no SQL form.
PAPER = ["two_pass", "distributed", "ball_matching", "quota_two_pass", "swap_recursive"]


def compare(s: SparkSession, inst: FairInstance, which: list[str], block: int = BLOCK) -> list[tuple]:
    """A row for each method on one instance."""
    inst = inst.prepared().validate()
    low = methods.farthest_lower_bound(inst.points, inst.metric, inst.k)
    return [method_row(inst.caps, _run(m, inst, block), low) for m in which]


def _compared(key: str, fixture: str, which: list[str], block: int = BLOCK, oracle: bool = True) -> None:
    f = FIXTURES[fixture]
    texts = [_method_sql(f, m, block) for m in which] if oracle else [None]
    _add(key, lambda s, d: _rows(s, compare(s, f.instance(s, d), which, block), _METHOD), None if None in texts else " UNION ALL ".join(texts))


REAL = ["emb_m2", "emb_m4", "emb_m10", "li6_m2", "li6_m5", "li6_m10", "pref_rank_m2", "pref_rank_m6", "pref_rank_m12", "pref_score_m2", "pref_score_m6", "pref_score_m12"]


def _method_queries() -> None:
    for name in ("emb_m2", "customer_bal", "nation_trade"):
        for m in ALL:
            _compared(f"{m}_{name}", name, [m])
    for name in REAL:
        _compared(f"compare_{name}", name, PAPER[:4])
        _compared(f"compare_swap_{name}", name, PAPER[4:])
    for name in ("emb_all_m2", "emb_all_m10", "pref_rank_all_m2", "pref_rank_all_m6", "pref_score_all_m2", "doc_letters", "doc_labels", "turn_shape", "page_shape"):
        _compared(f"compare_{name}", name, [*PAPER[:4], "one_pass"])
    for name in ("li6_all_m2", "li6_all_m5", "li6_all_m10", "li6_full"):  # a block spans ids of 10000 line items, as rows of one order share a range of 512
        _compared(f"distributed_{name}", name, ["distributed"], 1_280_000)
        _compared(f"two_pass_{name}", name, ["two_pass"], oracle=False)
    emb, nation = FIXTURES["emb_m2"], FIXTURES["nation_trade"]

    def plain(s, d):
        found = baselines.distributed_plain(emb.points(s, d), metrics.L1, 4, BLOCK)
        return _rows(s, [(found.cost, int(found.stats["sent"]))], "cost double, sent bigint")

    _add("distributed_plain_emb", plain, sql.plain(emb, BLOCK))

    def one_group(f: Fixture) -> Fixture:
        return Fixture(f"SELECT ord, 0 AS grp, coords FROM ({f.text}) g", f.metric, (sum(f.caps),))

    for m in ("two_pass", "distributed"):  # plain centres: a single group
        FIXTURES["emb_single"] = one_group(emb)
        _compared(f"{m}_emb_single", "emb_single", [m])

    def exact(s, d):
        found = baselines.exact_small(nation.instance(s, d), 25)
        return _rows(s, [("exact_small", found.cost, ",".join(map(str, sorted(found.centres.ord.tolist()))))], "method string, cost double, chosen string")

    _add("exact_small_nation", exact, sql.exact_ones(nation, "exact_small"))

    def true_ratios(s, d):
        inst = nation.instance(s, d).prepared()
        best = baselines.exact_small(inst, 25).cost
        return _rows(s, [(m, (x := _run(m, inst, 5)).cost, best, x.cost / best) for m in ALL], "method string, cost double, optimum double, true_ratio double")

    _add("true_ratio_nation", true_ratios)

    def ball_exact(s, d):
        inst = FIXTURES["supplier_bal"].instance(s, d).prepared()
        return _rows(s, [method_row(inst.caps, baselines.ball_matching_exact(inst, 1000), methods.farthest_lower_bound(inst.points, inst.metric, inst.k))], _METHOD)

    _add("ball_matching_exact_supplier", ball_exact, sql.ball_exact(FIXTURES["supplier_bal"], "ball_matching_exact"))
    ranks = FIXTURES["pref_rank_all_m6"]
    for m in ("two_pass", "distributed"):

        def ranked(s, d, m=m):
            inst = ranks.instance(s, d)
            found = _run(m, inst).centres
            return _rows(s, sorted((int(o), int(g), int(c)) for o, g, c in found.rows(metrics.INVERSIONS)), "ord bigint, grp int, ranking bigint")

        _add(f"fair_rank_{m}", ranked, f"SELECT q.ord, q.grp, q.coords AS ranking FROM ({ranks.duck}) q WHERE q.ord IN (SELECT CAST(unnest(string_split(chosen, ',')) AS BIGINT) FROM ({_method_sql(ranks, m)}) w)")
    guesses = 12
    for name, block in (("emb_m2", BLOCK), ("customer_bal", BLOCK), ("pref_rank_m6", BLOCK)):
        f = FIXTURES[name]
        _add(f"coordinator_trace_{name}", lambda s, d, f=f, block=block: _rows(s, coordinator_trace(f.instance(s, d), block, guesses), "guess int, tau double, pivots bigint, success boolean"), sql.coordinator_trace(f, block, guesses))

    def measured(s, d):
        inst = emb.instance(s, d).prepared()
        rows = [(m, int((x := _run(m, inst)).stats["passes"]), int(x.stats["evaluations"]), int(x.stats.get("rounds", 0))) for m in ALL]
        return _rows(s, rows, "method string, passes int, evaluations bigint, rounds int")

    _add("measures_emb_m2", measured)

    def sweep(s, d):
        inst = FIXTURES["customer_bal"].instance(s, d).prepared()
        n, best = inst.points.count(), None
        best = methods.optimal_blocks(n, len(inst.caps), inst.k)
        out = []
        for blocks in sorted({1, max(1, best // 4), best, 4 * best, round(math.sqrt(n)), max(1, n // 25)}):
            x = methods.distributed(inst, block_size=-(-n // blocks) + 1)
            out.append((blocks, blocks == best, float(x.cost), int(x.stats["sent"]), int(x.stats["stored"])))
        return _rows(s, out, "blocks int, balanced boolean, cost double, sent bigint, largest_message bigint")

    _add("block_count_sweep", sweep)
    _add("cube_methods", lambda s, d: studies.cube(s))


def coordinator_trace(inst: FairInstance, block: int, guesses: int) -> list[tuple]:
    """(guess, tau, pivots, success) of the coordinator's first guesses."""
    rows = sorted(methods.block_summaries(inst.points, inst.metric, inst.k, block_size=block).collect(), key=lambda r: (r.block, r.pivot, r.ord))
    pivots, reps = (Points.of([(r.ord, r.grp, r.coords) for r in rows if r.role == role], inst.metric) for role in ("pivot", "rep"))
    out = []
    for g in range(guesses):
        tau = max(r.r for r in rows) / 5.1 * 1.1**g
        kept = methods.separated_at(pivots, inst.metric, 10 * tau, inst.k)
        chosen, hits, sets = methods.coordinate_at(pivots, reps, inst.metric, inst.caps, tau)
        out.append((g, round(tau, 6), len(kept), chosen is not None and hits == sets))
    return out


#: Distance queries on tables of any size: copies stay one class, and pairs are those of classes.
BY_CLASS = ("dist_inversions", "dist_hamming", "dist_l2", "dist_linf", "dist_angular")


def _distances() -> None:
    pairs = {
        "dist_l1": (metrics.L1, FIXTURES["emb_m2"].text, "bigint"), "dist_linf": (metrics.LINF, FIXTURES["part_shape"].text, "bigint"), "dist_hamming": (metrics.HAMMING, FIXTURES["part_shape"].text, "bigint"),
        "dist_l2": (metrics.L2, "SELECT p_partkey AS ord, LIST(CAST(p_size AS DOUBLE), CAST(p_retailprice AS DOUBLE)) AS coords FROM {part}", "double"),
        "dist_angular": (metrics.ANGULAR, "SELECT p_partkey AS ord, LIST(CAST(p_size AS DOUBLE), CAST(p_retailprice AS DOUBLE)) AS coords FROM {part}", "double"),
        "dist_inversions": (metrics.INVERSIONS, FIXTURES["pref_rank_m2"].text, "bigint"),
        "dist_levenshtein": (metrics.LEVENSHTEIN, "SELECT n_nationkey AS ord, n_name AS coords FROM {nation}", "bigint"),
        "dist_jaccard": (metrics.JACCARD, "SELECT n_nationkey AS ord, LIST(substr(n_name, 1, 1), substr(n_name, 2, 1), substr(n_name, 3, 1)) AS coords FROM {nation}", "double"),
    }
    for name, (metric, text, kind) in pairs.items():
        everything = whole(Fixture(text, metric, ())).text
        exact = (lambda c: c) if kind == "bigint" else (lambda c: F.round(c.cast("double"), 5))
        text = metric.sql("a.coords", "b.coords")
        if name in BY_CLASS:

            def classes(s, d, metric=metric, everything=everything, exact=exact):
                t = spark_sql(s, d, f"SELECT ord, coords FROM ({everything}) q")
                return scans.distances_by_class(t, metric, F.col("ord") % 50 == 0).withColumn("d", exact(F.col("d")))

            _add(name, classes, f"""WITH t AS ({duck_sql(everything)}), p AS (SELECT coords, min(ord) AS class, bool_or(ord % 50 = 0) AS asked FROM t GROUP BY coords)
SELECT ord, min(ord) OVER (PARTITION BY coords) AS class, CAST(NULL AS BIGINT) AS query, CAST(NULL AS {kind}) AS d FROM t
UNION ALL SELECT NULL, a.class, b.class, {text if kind == 'bigint' else f'round(CAST({text} AS DOUBLE), 5)'} FROM p a JOIN p b ON b.asked""", lazy=True)
            continue

        def query(s, d, metric=metric, everything=everything, exact=exact):
            t = spark_sql(s, d, f"SELECT ord, coords FROM ({everything}) q")
            b = t.where("ord % 50 = 0").toDF("query", "cb")  # the stated query set, against every point
            return t.toDF("ord", "ca").join(F.broadcast(b)).select("ord", "query", exact(metric.column(F.col("ca"), F.col("cb"))).alias("d"))

        _add(name, query, f"WITH t AS ({duck_sql(everything)}) SELECT a.ord, b.ord AS query, {text if kind == 'bigint' else f'round(CAST({text} AS DOUBLE), 5)'} AS d FROM t a JOIN (SELECT ord, {'coords'} FROM t) b ON b.ord % 50 = 0", lazy=True)


def _hardness() -> None:
    """The instance over all customers: the seven smallest keys are critical, the others are dealt to the parts of the large sets."""

    def ids(s, d):
        return s.read.parquet(f"{d}/customer.parquet").select(F.col("c_custkey").alias("ord"))

    points = "SELECT c_custkey AS ord, CAST(CASE WHEN n <= 7 THEN n - 1 ELSE 7 + (c_custkey % 9) // 3 END AS INTEGER) AS class, CASE WHEN n > 7 THEN CAST(c_custkey % 9 AS INTEGER) END AS part FROM (SELECT c_custkey, row_number() OVER (ORDER BY c_custkey) AS n FROM customer) x"
    names = "['" + "', '".join(hardness.CLASSES) + "']"
    sizes = f"size AS (SELECT class AS i, ({names})[class + 1] AS c, count(*) AS n FROM ({points}) x GROUP BY class)"
    _add("hard_instance_points", lambda s, d: hardness.hard_points(ids(s, d)).select("ord", "class"), f"SELECT ord, class FROM ({points}) x", lazy=True)
    near = """cls AS (SELECT * FROM (VALUES ('a*', 1), ('b1*', 1), ('b2*', 1), ('c*', 1), ('a', 1), ('b', 1), ('c', 1), ('S1', 2), ('S2', 2), ('S3', 2)) t(c, n)),
node AS (SELECT c, i AS i FROM cls, range(1, 3) r(i) WHERE i <= n UNION ALL SELECT 'hub', 1),
joined AS (SELECT * FROM (VALUES ('a*', ['b1*', 'b2*', 'a', 'S1']), ('c*', ['b1*', 'b2*', 'c', 'S3']), ('b1*', ['b', 'S2']), ('b2*', ['b', 'S2']), ('hub', ['S1', 'S2', 'S3'])) t(u, vs)),
one AS (SELECT u, unnest(vs) AS v FROM joined), way AS (SELECT u, v FROM one UNION ALL SELECT v, u FROM one),
edge AS (SELECT x.c AS a, x.i AS i, y.c AS b, y.i AS j FROM way JOIN node x ON x.c = u JOIN node y ON y.c = v),
walk AS (SELECT c AS a, i, c AS b, i AS j, 0 AS d FROM node UNION SELECT w.a, w.i, e.b, e.j, w.d + 1 FROM walk w JOIN edge e ON e.a = w.b AND e.i = w.j WHERE w.d < 5),
near AS (SELECT a, i, b, j, min(d) AS d FROM walk GROUP BY ALL),
dist AS (SELECT a, b, CAST(max(d) AS INTEGER) AS d FROM near WHERE a <> 'hub' AND b <> 'hub' AND i = 1 AND j = CASE WHEN a = b AND a LIKE 'S%' THEN 2 ELSE 1 END GROUP BY a, b)"""
    _add("hard_instance_distances", lambda s, d: hardness.hard_distances(ids(s, d)), f"WITH RECURSIVE {near}, {sizes} SELECT a, b, d, CAST(x.n * (y.n - CASE WHEN a = b THEN 1 ELSE 0 END) AS BIGINT) AS pairs FROM dist JOIN size x ON x.c = a JOIN size y ON y.c = b")
    crit = ", ".join(f"({3 * i + j}, {hardness.CLASSES.index(c)})" for i in range(3) for j in range(3) for c in hardness.SHARED[i])
    _add("hard_instance_inputs", lambda s, d: hardness.hard_inputs(ids(s, d)), f"WITH p AS ({points}) SELECT CAST(t.p AS INTEGER) AS processor, ord, ord AS label FROM (VALUES {crit}) t(p, c) JOIN p ON part IS NULL AND class = c UNION ALL SELECT part, ord, ord FROM p WHERE part IS NOT NULL", lazy=True)
    _add("hard_instance_optimum", lambda s, d: _rows(s, sorted(hardness.triples(hardness.class_sizes(ids(s, d))).items()), "cost int, triples bigint"), f"""
WITH RECURSIVE {near}, {sizes}, three AS (SELECT a.c AS a, b.c AS b, c.c AS c, CASE WHEN a.i = c.i THEN a.n * (a.n - 1) * (a.n - 2) // 6 WHEN a.i = b.i THEN a.n * (a.n - 1) // 2 * c.n WHEN b.i = c.i THEN a.n * (b.n * (b.n - 1) // 2) ELSE a.n * b.n * c.n END AS n FROM size a JOIN size b ON b.i >= a.i JOIN size c ON c.i >= b.i),
each AS (SELECT t.a, t.b, t.c, t.n, s.c AS q, min(d) AS d FROM three t JOIN size s ON s.n > CASE WHEN s.c = t.a THEN 1 ELSE 0 END + CASE WHEN s.c = t.b THEN 1 ELSE 0 END + CASE WHEN s.c = t.c THEN 1 ELSE 0 END JOIN dist ON dist.a = s.c AND dist.b IN (t.a, t.b, t.c) WHERE t.n > 0 GROUP BY ALL)
SELECT cost, CAST(sum(n) AS BIGINT) AS triples FROM (SELECT a, b, c, n, CAST(max(d) AS INTEGER) AS cost FROM each GROUP BY a, b, c, n) x GROUP BY cost""")

    def frequencies(s, d):
        customers, rows = s.read.parquet(f"{d}/customer.parquet"), []
        for segment, n in sorted(tuple(r) for r in customers.groupBy("c_mktsegment").count().collect()):  # an instance for each segment
            own, n_prime = customers.where(F.col("c_mktsegment") == segment).select(F.col("c_custkey").alias("ord")), max(0, n - 7) // hardness.PROCESSORS
            for ell in sorted({1, max(1, (n_prime + 3) // 54)}):  # up to the bound of (n' + 3) / 54 points a processor
                for how in ("random", "farthest"):
                    share = hardness.simulate(own, ell, 400, coordinator=how).agg(F.avg(F.col("failed").cast("double"))).first()[0]
                    rows.append((segment, n_prime, ell, how, share, share >= 1 / 84))
        return _rows(s, rows, "segment string, n_prime int, sent int, coordinator string, frequency double, above_bound boolean")

    def failures(how):
        return lambda s, d: hardness.simulate(ids(s, d), 1, 400, coordinator=how).agg(F.avg(F.col("failed").cast("double")).alias("frequency"), F.count("*").alias("trials"))

    _add("hard_instance_frequencies", frequencies)
    _add("hard_instance_failures", failures("random"), lazy=True)
    _add("hard_instance_failures_farthest", failures("farthest"), lazy=True)
    copies = hardness.amplification_factor(0.5, 0.001)
    _add("hard_instance_amplified", lambda s, d: hardness.amplified(ids(s, d), copies).groupBy("class").agg(F.count("*").alias("n")), f"SELECT class, count(*) * {copies} AS n FROM ({points}) x GROUP BY class", lazy=True)


def _graphs() -> None:
    _add("graph_edges_copurchase", lambda s, d: spark_sql(s, d, graphs.COPURCHASE), duck_sql(graphs.COPURCHASE))
    _add("graph_edges_copurchase_all", lambda s, d: spark_sql(s, d, graphs.COPURCHASE_ALL), duck_sql(graphs.COPURCHASE_ALL))

    def copurchase(s, d):
        nodes = [r.p_partkey for r in spark_sql(s, d, "SELECT p_partkey FROM {part} WHERE p_partkey < 350 ORDER BY 1").collect()]
        return graphs.shortest_paths(spark_sql(s, d, graphs.COPURCHASE), nodes)

    _add("graph_apsp", lambda s, d: copurchase(s, d).select("ord", F.posexplode(F.slice("coords", 2, F.size("coords") - 1))).select("ord", F.col("pos").cast("bigint").alias("other"), F.col("col").alias("d")), f"SELECT ord, CAST(o - 1 AS BIGINT) AS other, coords[o + 1] AS d FROM ({graphs.PATHS_SQL.format(edges=duck_sql(graphs.COPURCHASE))}) q, range(1, len(coords)) t(o)", lazy=True)

    class Graph(Fixture):
        @property
        def duck(self) -> str:
            return graphs.PATHS_SQL.format(edges=duck_sql(graphs.COPURCHASE))

    f = Graph("", metrics.path_rows(), (2,) * 5)
    for name in PAPER:
        _add(f"graph_{name}", lambda s, d, name=name: _rows(s, compare(s, FairInstance(copurchase(s, d).select("ord", (F.col("ord") % 5).cast("int").alias("grp"), "coords"), f.metric, f.caps), [name]), _METHOD), _method_sql(f, name))

    _add("random_graph_ratios", lambda s, d: studies.ratios(studies.table_runs(spark_sql(s, d, graphs.FOLDED))), lazy=True)
    _add("random_graph_times", lambda s, d: studies.time_study(s), lazy=True)


def _surroundings() -> None:
    for name, text in relational.QUERIES.items():
        _add(name, lambda s, d, text=text: spark_sql(s, d, text), duck_sql(text))
    for name, (mine, theirs) in relational.PAIRS.items():
        _add(name, lambda s, d, mine=mine: spark_sql(s, d, mine), theirs)
    bal = FIXTURES["customer_bal"]

    def ladder(s, d):
        points = bal.points(s, d)
        first = F.broadcast(points.orderBy("ord").limit(1).select(F.col("coords").alias("at")))
        far = points.join(first).select(bal.metric.column(F.col("coords"), F.col("at")).cast("double").alias("d"))
        ends = far.agg(F.min(F.when(F.col("d") > 0, F.col("d"))).alias("low"), F.max("d").alias("high")).first()
        return _rows(s, list(enumerate(methods.geometric_guesses(ends.low or 0.0, ends.high or 0.0, 0.1))), "guess int, tau double").withColumn("tau", F.round("tau", 6))

    _add("guess_ladder", ladder, f"""WITH p AS ({bal.duck}), far AS (SELECT CAST({bal.metric.sql("p.coords", "c.coords")} AS DOUBLE) AS d FROM p, (SELECT coords FROM p ORDER BY ord LIMIT 1) c), ends AS (SELECT coalesce(min(d) FILTER (d > 0), 0.0) AS low, max(d) AS high FROM far)
SELECT CAST(i AS INTEGER) AS guess, round(low * power(1.1, i), 6) AS tau FROM ends, range(0, 1000) t(i) WHERE i = 0 OR low * power(1.1, i - 1) < high""")
    other = "SELECT item_id AS ord, 0 AS grp, LIST(CAST(length(text) AS BIGINT)) AS coords FROM {benchmark}"
    docs = "SELECT doc_id AS ord, 0 AS grp, LIST(CAST(length(text) AS BIGINT)) AS coords FROM {documents}"

    def between(s, d):
        centres = spark_sql(s, d, other).orderBy("ord").collect()
        X = Points.of([(r.ord, 0, r.coords) for r in centres], metrics.L1).coords
        return _rows(s, [(scans.cover_distance(spark_sql(s, d, docs), metrics.L1, [X])[0],)], "cost double")

    _add("cost_benchmark_vs_documents", between, f"WITH a AS ({duck_sql(other)}), b AS ({duck_sql(docs)}) SELECT CAST(max(d) AS DOUBLE) AS cost FROM (SELECT b.ord, min({metrics.L1.sql('a.coords', 'b.coords')}) AS d FROM a, b GROUP BY b.ord) x")
    ev = FIXTURES["events"]

    def windows(s, d):
        from .streaming import window_summaries

        points = ev.points(s, d).join(s.read.parquet(f"{d}/events.parquet").select(F.col("event_id").alias("ord"), F.col("ts").cast("timestamp").alias("ts")), "ord")
        return window_summaries(points, metrics.L1, ev.caps, "1 day").groupBy("window_start").agg(F.max("r").alias("r"), F.count("*").alias("sent")).select(F.to_date("window_start").cast("string").alias("day"), "r", "sent")

    _add("stream_window_summary", windows, sql.window_messages(ev, "events", "event_id", "ts"), lazy=True)

    def stream(s, d):
        from .streaming import event_stream, watermark_counts

        return watermark_counts(event_stream(s, d).select("ts", F.col("event_type").alias("grp")), "1 hour", "1 day", "watermark_counts").select(F.to_date("window_start").cast("string").alias("day"), "grp", "n")

    _add("stream_watermark_counts", stream, "SELECT CAST(CAST(ts AS DATE) AS VARCHAR) AS day, event_type AS grp, count(*) AS n FROM events GROUP BY 1, 2")

    def sessions(s, d):
        from .streaming import event_stream, session_counts

        return session_counts(event_stream(s, d).select("ts", F.col("user_id").alias("key")), "1 hour", "2 hours", "session_counts").select(F.col("key").alias("user_id"), "n")

    _add("stream_sessions", sessions, relational.PAIRS["relational_session"][1], lazy=True)

    def distinct(s, d):
        from .streaming import distinct_within, event_stream

        twice = event_stream(s, d).select("ts", "event_id", "event_type", F.explode(F.array(F.lit(0), F.lit(1))).alias("copy"))
        found = distinct_within(twice, "1 hour", ["event_id"], "distinct_events").groupBy("event_type").agg(F.count("*").alias("n")).collect()
        return _rows(s, [tuple(r) for r in found], "event_type string, n bigint")

    _add("stream_distinct", distinct, "SELECT event_type, count(*) AS n FROM events GROUP BY 1")

    def event_points(s, d):
        from .streaming import event_stream

        kind = F.expr("CASE event_type WHEN 'click' THEN 0 WHEN 'view' THEN 1 WHEN 'purchase' THEN 2 WHEN 'signup' THEN 3 ELSE 4 END")
        return event_stream(s, d).select("ts", F.col("event_id").alias("ord"), kind.alias("grp"), F.array((F.hour("ts") * 3600 + F.minute("ts") * 60 + F.second("ts")).cast("bigint"), F.round(F.col("value") * 100).cast("bigint")).alias("coords"))

    def replay(s, d):
        from .streaming import two_pass_stream

        chosen, hits, sets = two_pass_stream(lambda: event_points(s, d).drop("ts"), metrics.L1, ev.caps, float(TAU["events"]))
        return _rows(s, [(hits, sets)], "hits bigint, sets bigint")

    ladder = [float(TAU["events"]) * 1.1**i for i in range(-20, 20)]

    def one_stream(s, d):
        from .streaming import one_pass_stream

        tau, centres, sets = one_pass_stream(event_points(s, d).drop("ts"), metrics.L1, ev.caps, ladder)
        return _rows(s, [(round(tau, 6), sets, ",".join(map(str, sorted(centres.ord.tolist()))))], "tau double, sets bigint, chosen string")

    _add("stream_one_pass", one_stream, sql.one_pass_centres(ev, ladder))

    def keyed(s, d):
        from .streaming import finish_key, one_pass_keyed

        days = event_points(s, d).select(F.to_date("ts").cast("string").alias("key"), "ord", "grp", "coords")
        rows = one_pass_keyed(days, metrics.L1, ev.caps, ladder, "one_pass_days").collect()
        done = [(r.key, r.arrivals, finish_key(r.kept, metrics.L1, ev.caps, ladder)) for r in rows]
        return _rows(s, [(k, n, None if x is None else ladder[x[0]], None if x is None else ",".join(map(str, sorted(x[1].ord.tolist())))) for k, n, x in done], "day string, arrivals bigint, tau double, chosen string")

    _add("stream_one_pass_days", keyed)

    def functions(s, d):
        from . import sql_api

        sql_api.register(s)
        f = FIXTURES["nation_trade"]
        t = f.points(s, d)
        return s.sql("SELECT a.ord AS a, b.ord AS b, l1_distance(a.coords, b.coords) AS d FROM {t} a JOIN {t} b ON a.ord < b.ord", t=t)

    nation = FIXTURES["nation_trade"]
    _add("sql_distance", functions, f"WITH p AS ({nation.duck}) SELECT a.ord AS a, b.ord AS b, {metrics.L1.sql('a.coords', 'b.coords')} AS d FROM p a JOIN p b ON a.ord < b.ord", lazy=True)

    def table_function(s, d):
        from . import sql_api

        sql_api.register(s)
        f = FIXTURES["customer_bal"]
        t = f.points(s, d).withColumn("block", F.floor(F.col("ord") / 50))
        return s.sql("SELECT block, role, pivot, ord, round(r, 3) AS r FROM fair_block_message(TABLE(SELECT * FROM {t}) PARTITION BY (block), 5)", t=t)

    _add("sql_block_message", table_function, _ORACLES["block_summaries_customer_bal"], lazy=True)

    def formats(s, d):
        from .storage import new_path

        points, out = FIXTURES["part_shape"].points(s, d), []
        for kind in ("parquet", "orc", "json"):
            path = new_path(s, kind)
            points.write.format(kind).save(path)
            back = s.read.format(kind).schema(points.schema).load(path)
            out.append((kind, *back.agg(F.count("*"), F.sum("ord"), F.sum(F.col("coords")[1])).first()))
        return _rows(s, out, "format string, n bigint, ords bigint, total bigint")

    part = FIXTURES["part_shape"]
    _add("sink_formats", formats, f"SELECT format, count(*) AS n, CAST(sum(ord) AS BIGINT) AS ords, CAST(sum(coords[2]) AS BIGINT) AS total FROM ({part.duck}) q, (VALUES ('parquet'), ('orc'), ('json')) t(format) GROUP BY format")

    def files(s, d):
        from .storage import new_path
        from .workloads import two_files

        points, paths = part.points(s, d), [new_path(s, "features"), new_path(s, "attributes")]
        points.select("ord", F.col("coords")[0].alias("x0"), F.col("coords")[1].alias("x1")).write.csv(paths[0])
        points.select("ord", "grp").write.csv(paths[1])
        found = two_files(s, *paths, 2).groupBy("grp").agg(F.count("*").alias("n"), F.sum(F.col("coords")[1]).alias("total")).collect()
        return _rows(s, [tuple(r) for r in found], "grp int, n bigint, total double")

    _add("source_two_files", files, f"SELECT grp, count(*) AS n, CAST(sum(coords[2]) AS DOUBLE) AS total FROM ({part.duck}) q GROUP BY grp")

    tau, k = float(TAU["events"]), sum(ev.caps)
    _add("stream_two_pass", replay, f"WITH RECURSIVE {_greedy(ev, 2 * tau, k + 1)}, {_reps(ev, tau)}, {_cut(ev)}, c AS (SELECT count(*) AS n FROM piv) SELECT CASE WHEN n > {k} THEN 0 ELSE (SELECT CAST(min(v) AS BIGINT) FROM cuts) END AS hits, n AS sets FROM c")


for _name, _f in FIXTURES.items():
    _points(_name, _f)
for _name in ("emb_m2", "emb_m4", "part_shape", "events", "customer_bal", "pref_rank_m2", "supplier_bal", "turn_shape", "page_shape", "emb_all_m2", "emb_all_m4", "pref_rank_all_m2"):
    _building_blocks(_name)
for _name, _size in (("emb_m2", 25), ("emb_all_m2", 25), ("customer_bal", 50), ("turn_shape", 640)):
    _blocks(_name, _size)
_distances()
_method_queries()
_hardness()
_graphs()
_surroundings()
