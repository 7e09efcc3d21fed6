"""Pivots, representatives, matching, bounds, the two methods and the baselines against brute force on small inputs."""

import numpy as np
import pytest

from fairsummary import baselines, hardness, methods, scans
from fairsummary.hitting import assign, assign_canonical, assign_slots, brute_force, certificate, complete, hitting_set
from fairsummary.metrics import INVERSIONS, JACCARD, L1, LEVENSHTEIN
from fairsummary.model import FairInstance, Points, proportional_caps


def frame(spark, rows, parts=1):
    return spark.createDataFrame(rows, "ord bigint, grp int, coords array<bigint>").repartition(parts)


def random_rows(seed, n=60, m=2, top=100):
    rng = np.random.default_rng(seed)
    return [(i, int(rng.integers(0, m)), rng.integers(0, top, 2).tolist()) for i in range(n)]


def greedy(rows, r):
    kept = []
    for row in rows:
        if all(sum(abs(a - b) for a, b in zip(row[2], k[2])) > r for k in kept):
            kept.append(row)
    return kept


@pytest.mark.parametrize("parts", [1, 3, 7])
def test_pivots_equal_the_sequential_scan(spark, parts):
    rows = random_rows(1)
    found, broken, _ = scans.separated_pivots(frame(spark, rows, parts), L1, [10, 40, 0], None)
    for r, P in zip([10, 40, 0], found):
        assert P.ord.tolist() == [k[0] for k in greedy(rows, r)]
    assert not any(broken)


def test_pivots_any_mode_and_limit(spark):
    rows = random_rows(2)
    (P,), _, _ = scans.separated_pivots(frame(spark, rows, 5), L1, [30], None, mode="any")
    d = L1.batch(P.coords, P.coords)
    assert (d[~np.eye(len(d), dtype=bool)] > 30).all()
    X = np.array([r[2] for r in rows])
    assert (L1.batch(X, P.coords).min(1) <= 30).all()
    (Q,), (broken,), _ = scans.separated_pivots(frame(spark, rows, 5), L1, [1], 3)
    assert broken and len(Q) == 4


def test_matching_forms_agree():
    rng = np.random.default_rng(3)
    for _ in range(60):
        caps = tuple(rng.integers(0, 3, 3).tolist())
        edges = [set(rng.choice(3, rng.integers(1, 4), replace=False).tolist()) for _ in range(int(rng.integers(1, 6)))]
        best = brute_force(edges, caps)
        assert certificate(edges, caps) == best
        for solve in (assign, assign_slots, assign_canonical):
            given = solve(edges, caps)
            assert sum(x is not None for x in given) == best
            assert all(given.count(j) <= c for j, c in enumerate(caps))
            assert all(x is None or x in e for x, e in zip(given, edges))


RUNS = {
    "two_pass": (3.3, methods.two_pass), "any": (3.3, lambda i: methods.two_pass(i, mode="any")), "first": (3.3, lambda i: methods.two_pass(i, search="first_success")), "bisect": (3.3, lambda i: methods.two_pass(i, search="bisect")),
    "best": (3.3, lambda i: methods.two_pass(i, search="best_cost")), "relay": (6.6, lambda i: methods.two_pass(i, search="relay")), "distributed": (18.7, lambda i: methods.distributed(i, block_size=5)),
    "widest": (18.7, lambda i: methods.distributed(i, block_size=5, ordering="widest_first", scale=1.0)), "ball": (3.3, baselines.ball_matching), "exact_ball": (3, baselines.ball_matching_exact), "quota": (3.3, baselines.quota_two_pass),
    "one": (18.7, lambda i: baselines.one_pass(i, shard_size=4)), "lean": (18.7, lambda i: baselines.one_pass(i, lean=True, shard_size=4)), "swap": (11, baselines.swap_recursive),
}


def random_instance(seed):
    """A few points, some in one place, groups of any capacity, one of them at least free."""
    rng = np.random.default_rng(seed)
    m, n, top = int(rng.integers(1, 4)), int(rng.integers(3, 13)), int(rng.choice([4, 30, 1000]))
    caps = rng.integers(0, 3, m)
    P = Points(np.arange(n), rng.integers(0, m, n), rng.integers(0, top, (n, 2)))
    caps[P.grp[0]] = max(caps[P.grp[0]], 1)
    return FairInstance(P, L1, tuple(caps.tolist()))


def test_guarantees_against_the_optimum():
    for seed in range(250):
        inst = random_instance(seed)
        opt = baselines.exact_small(inst).cost
        assert methods.farthest_lower_bound(inst.points, L1, inst.k) <= opt + 1e-9 and methods.simple_lower_bound(inst.points, L1, inst.k) <= opt + 1e-9
        assert opt <= methods.simple_upper_bound(inst)[1] + 1e-9
        assert max((x[4] for x in methods.block_summaries(inst.points, L1, inst.k, block_size=7)), default=0) <= opt + 1e-9
        assert baselines.plain_farthest(inst.points, L1, inst.k).cost <= 2 * opt + 1e-9 and baselines.distributed_plain(inst.points, L1, inst.k, 5).cost <= 4 * opt + 1e-9
        got = {name: run(inst) for name, (_, run) in RUNS.items()}
        for name, x in got.items():
            assert x.cost <= RUNS[name][0] * opt + 1e-6, (seed, name, x.cost, opt)
            assert all((x.centres.grp == j).sum() <= c for j, c in enumerate(inst.caps)), (seed, name)
            assert len(set(x.centres.ord.tolist())) == len(x.centres)
        assert got["quota"].tau == got["two_pass"].tau == got["first"].tau


def test_tables_give_what_arrays_give(spark):
    for seed, parts in ((3, 1), (4, 5)):
        rows = random_rows(seed, 40, 2, 60)
        P = Points(np.array([r[0] for r in rows]), np.array([r[1] for r in rows]), np.array([r[2] for r in rows]))
        table = FairInstance(frame(spark, rows, parts), L1, (2, 1)).prepared()
        for name in ("two_pass", "bisect", "distributed", "widest", "ball", "quota", "one", "swap"):
            a, b = RUNS[name][1](FairInstance(P, L1, (2, 1))), RUNS[name][1](table)
            assert (a.tau, a.cost, sorted(a.centres.ord.tolist())) == (b.tau, b.cost, sorted(b.centres.ord.tolist())), name


def test_large_summaries_stay_tables(spark):
    inst = FairInstance(frame(spark, random_rows(5, 60, 2, 60), 4), L1, (1, 2)).prepared()
    for run in (lambda b: methods.distributed(inst, block_size=7, driver_bytes=b), lambda b: methods.distributed(inst, block_size=7, ordering="widest_first", driver_bytes=b), lambda b: baselines.one_pass(inst, shard_size=9, driver_bytes=b)):
        a, b = run(1 << 20), run(0)
        assert (a.tau, a.cost, a.centres.ord.tolist(), a.stats) == (b.tau, b.cost, b.centres.ord.tolist(), b.stats)
    same = FairInstance(frame(spark, [(i, int(i > 3), [i % 2]) for i in range(8)], 2), L1, (2, 0)).prepared()  # r is zero in every block
    assert methods.distributed(same, block_size=2).cost == methods.distributed(same, block_size=2, driver_bytes=0).cost == 0


def test_one_pass_gives_up_a_guess_with_its_shard(spark):
    """A shard that needs more than k pivots fails the guess; its other points are not dropped."""
    P = Points(np.arange(5), np.array([0, 1, 0, 1, 0]), np.array([[0], [10], [25], [40], [1000000]]))
    want = baselines.exact_small(FairInstance(P, L1, (1, 1))).cost
    table = FairInstance(frame(spark, P.rows(L1), 1), L1, (1, 1))
    assert baselines.one_pass(FairInstance(P, L1, (1, 1))).cost == baselines.one_pass(table).cost == want == 30
    for seed, parts in enumerate((1, 2, 5, 7)):
        inst = FairInstance(frame(spark, random_rows(seed, 20, 2), parts), L1, (1, 2)).prepared()
        assert baselines.one_pass(inst).cost <= 18.7 * baselines.exact_small(inst).cost


def test_scans_are_counted_and_nothing_is_shuffled(spark):
    points = frame(spark, random_rows(6, 80), 6)
    inst = FairInstance(points, L1, (2, 2)).prepared()
    found = methods.two_pass(inst)
    # the first of each group, their cost, first positions, pivots by rounds, representatives, cost
    assert found.stats["passes"] >= 5 + found.stats["rounds"] and found.stats["rounds"] <= inst.k + 1
    assert methods.distributed(inst, block_size=10).stats["passes"] == 2 and found.stats["evaluations"] > 80
    one = scans.ledger()
    with one as book:
        scans.cover_distance(inst.points, L1, [np.array([[0, 0], [1, 1]])])
    assert (book.scans, book.evaluations) == (1, 160)
    plan = scans.nearest_centre(inst.points, L1, Points(np.array([1]), np.array([0]), np.zeros((1, 2), np.int64)))._jdf.queryExecution().toString()
    assert "Exchange" not in plan.split("== Physical Plan ==")[1]


def test_candidate_lists_merge_by_levels(spark, monkeypatch):
    rows = random_rows(8, 90)
    wanted = [k[0] for k in greedy(rows, 12)]
    monkeypatch.setattr(scans, "FAN", 2)
    (P,), _, _ = scans.separated_pivots(frame(spark, rows, 7), L1, [12], None)
    assert P.ord.tolist() == wanted


def test_cost_calculus():
    """cost(A, C) <= cost(A, B) + cost(B, C); more centres never cost more, more points never less; unions of points take the larger cost."""
    rng = np.random.default_rng(9)
    cost = lambda A, B: scans.cover_distance(Points(np.arange(len(B)), np.zeros(len(B), int), B), L1, [A])[0]
    for _ in range(50):
        A, B, C = (rng.integers(0, 50, (int(rng.integers(1, 8)), 2)) for _ in range(3))
        assert cost(A, C) <= cost(A, B) + cost(B, C)
        assert cost(np.concatenate([A, B]), C) <= cost(A, C) <= cost(A, np.concatenate([B, C]))
        assert cost(A, np.concatenate([B, C])) == max(cost(A, B), cost(A, C))


def test_edge_cases(spark):
    same = frame(spark, [(i, i % 2, [5, 5]) for i in range(8)], 3)
    inst = FairInstance(same, L1, (1, 1))
    assert methods.two_pass(inst).cost == 0 and methods.distributed(inst, block_size=3).cost == 0
    one = FairInstance(frame(spark, [(0, 0, [1, 2])]), L1, (2, 2))
    assert methods.two_pass(one).cost == 0
    capless = FairInstance(frame(spark, random_rows(5), 2), L1, (0, 3))
    assert (methods.two_pass(capless).centres.grp == 1).all()
    empty = FairInstance(frame(spark, []), L1, (1, 1))
    assert len(methods.two_pass(empty).centres) == 0 and len(methods.distributed(empty, block_size=3).centres) == 0
    with pytest.raises(ValueError):
        FairInstance(frame(spark, [(0, 0, [1]), (0, 1, [2])]), L1, (1, 1)).validate()


def test_strict_ties(spark):
    rows = [(0, 0, [0, 0]), (1, 1, [10, 0]), (2, 0, [20, 0])]
    (P,), _, _ = scans.separated_pivots(frame(spark, rows), L1, [10], None)
    assert P.ord.tolist() == [0, 2]
    (sets,) = scans.group_reps(frame(spark, rows), L1, [P], [10])
    assert [s.ord.tolist() for s in sets] == [[0, 1], [2, 1]]


def test_completion_and_quotas():
    pool = Points(np.arange(6), np.array([0, 0, 0, 1, 1, 1]), np.zeros((6, 1)))
    assert complete(pool.take([4]), (1, 2), pool).ord.tolist() == [4, 0, 3]
    assert proportional_caps([60, 30, 10], 10) == (6, 3, 1)
    assert sum(proportional_caps([1, 1, 1], 10)) == 10


def test_hard_instance(spark):
    d = hardness.class_distances()
    assert (d == d.T).all()
    for k in range(10):
        assert (d[:, :] <= d[:, k : k + 1] + d[k : k + 1, :]).all()
    classes = hardness.class_of(2)
    assert hardness.optimum(2)[0] == 1
    ones = [c for c in __import__("itertools").combinations(range(len(classes)), 3) if hardness.cost_of(classes, np.array(c), d) == 1]
    assert len(ones) == 2
    assert hardness.cost_of(classes, np.flatnonzero(classes == 7)[:3], d) == 4
    ids = spark.range(466).toDF("ord")
    rows = hardness.hard_inputs(ids).groupBy("processor").count().collect()
    assert len(rows) == 9 and all(r["count"] == 54 for r in rows)
    fails = hardness.simulate(ids, 1, 600).where("failed").count() / 600
    assert fails >= 1 / 84 - 3 * (1 / 84 / 600) ** 0.5
    assert hardness.amplification_factor(0.1, 0.0) == 194
    few = spark.range(20, 37).toDF("ord")  # by classes as by points
    points = sorted((r.ord, r["class"]) for r in hardness.hard_points(few).collect())
    classes, costs = np.array([c for _, c in points]), {}
    for c in __import__("itertools").combinations(range(17), 3):
        cost = hardness.cost_of(classes, np.array(c), d)
        costs[cost] = costs.get(cost, 0) + 1
    assert classes[:7].tolist() == list(range(7)) and hardness.triples(hardness.class_sizes(few)) == costs
    assert sorted(r.label for r in hardness.hard_inputs(few, 3).select("ord", "label").distinct().collect()) == list(range(17))


def test_hard_instances_and_ladder_take_every_row_of_their_table(spark):
    from fairsummary import catalogue

    run = lambda name: catalogue.queries()[name](spark, DATA).collect()
    customers = {r.c_custkey for r in spark.read.parquet(f"{DATA}/customer.parquet").collect()}
    n = len(customers)
    assert {r.ord for r in run("hard_instance_points")} == customers == {r.ord for r in run("hard_instance_inputs")}
    assert sum(r.pairs for r in run("hard_instance_distances")) == n * (n - 1) and sum(r.triples for r in run("hard_instance_optimum")) == n * (n - 1) * (n - 2) // 6
    assert sum(r.n for r in run("hard_instance_amplified")) == n * hardness.amplification_factor(0.5, 0.001)
    assert len({r.segment for r in run("hard_instance_frequencies")}) == 5 and all(run(f"hard_instance_failures{x}")[0].trials == 400 for x in ("", "_farthest"))
    ladder = [r.tau for r in run("guess_ladder")]
    bal = [r.c_acctbal for r in spark.read.parquet(f"{DATA}/customer.parquet").orderBy("c_custkey").collect()]
    assert abs(ladder[0] - min(abs(x - bal[0]) for x in bal if x != bal[0]) * 100) < 1 and ladder[-2] < max(abs(x - bal[0]) for x in bal) * 100 + 1 <= ladder[-1] + 2


def test_metrics_agree_with_kernels(spark):
    from pyspark.sql import functions as F

    rows = spark.createDataFrame([(1, 6, "ab", ["x", "y"]), (5, 9, "abd", ["y"])], "a bigint, b bigint, s string, t array<string>")
    got = rows.select(INVERSIONS.column(F.col("a"), F.col("b")), LEVENSHTEIN.column(F.col("s"), F.lit("abc")), JACCARD.column(F.col("t"), F.array(F.lit("y")))).collect()
    assert [tuple(r) for r in got] == [(3, 1, 0.5), (2, 1, 0.0)]
    assert INVERSIONS.batch(np.array([1, 5]), np.array([6])).tolist() == [[3], [2]]


def test_scan_reads_only_what_it_needs(spark):
    df = spark.read.parquet("/root/testdata/sf0.001/embeddings.parquet")
    inst = FairInstance.from_table(df, "vec_id", "label", "embedding", L1, (1,) * 10)
    plan = scans.nearest_centre(inst.points.select("ord", "grp", "coords"), L1, Points(np.array([1]), np.array([0]), np.zeros((1, 64), np.int64)))._jdf.queryExecution().toString()
    assert "Exchange" not in plan.split("== Physical Plan ==")[1] and "MapInArrow" not in plan


def test_every_key_runs_one_of_each_kind(spark):
    import __spark_entry__ as e

    assert set(e.oracle_sql()) <= set(e.queries())
    assert e.entry(spark).count() == 1


DATA = "/root/testdata/sf0.001"


def test_distances_cover_whole_tables(spark):
    from fairsummary import catalogue
    from fairsummary.workloads import FIXTURES, whole

    for name, fixture in (("dist_l1", "emb_m2"), ("dist_linf", "part_shape"), ("dist_inversions", "pref_rank_m2")):
        f = whole(FIXTURES[fixture])
        points = {r.ord: r.coords for r in f.points(spark, DATA).collect()}
        rows = catalogue.queries()[name](spark, DATA).collect()
        got = {(r.ord, r.query): r.d for r in rows}
        if name in catalogue.BY_CLASS:  # membership and pairs of classes say the same as all pairs
            of = {r.ord: r["class"] for r in rows if r.ord is not None}
            pairs = {(r["class"], r.query): r.d for r in rows if r.ord is None}
            assert len(rows) == len(points) + len(pairs) and set(pairs) == {(a, of[b]) for a in of.values() for b in points if b % 50 == 0}
            got = {(a, b): pairs[of[a], of[b]] for a in points for b in points if b % 50 == 0}
        assert set(got) == {(a, b) for a in points for b in points if b % 50 == 0} and len(points) > 60
        kernel = {"dist_l1": lambda x, y: sum(abs(a - b) for a, b in zip(x, y)), "dist_linf": lambda x, y: max(abs(a - b) for a, b in zip(x, y)), "dist_inversions": lambda x, y: (x ^ y).bit_count()}[name]
        assert all(v == kernel(points[a], points[b]) for (a, b), v in got.items())


def test_all_shortest_paths(spark):
    from fairsummary import catalogue

    got = {(r.ord, r.other): r.d for r in catalogue.queries()["graph_apsp"](spark, DATA).collect()}
    edges = [(r.src, r.dst, r.w) for r in catalogue.queries()["graph_edges_copurchase"](spark, DATA).collect()]
    nodes = sorted({a for a, _ in got})
    assert len(nodes) > 40 and len(got) == len(nodes) ** 2
    n, at = len(nodes), {v: i for i, v in enumerate(nodes)}
    far = 1 + sum(w for _, _, w in edges)
    D = np.full((n, n), far)
    np.fill_diagonal(D, 0)
    for a, b, w in edges:
        D[at[a], at[b]] = D[at[b], at[a]] = min(w, D[at[a], at[b]])
    for k in range(n):
        D = np.minimum(D, D[:, k : k + 1] + D[k])
    assert all(d == D[at[a], o] for (a, o), d in got.items())


def test_whole_tables(spark):
    from fairsummary import catalogue
    from fairsummary.workloads import FIXTURES

    larger = DATA.replace("0.001", "0.01")  # more than 1000 line items and customers
    for name, table in (("li6_all_m2", "lineitem"), ("li6_full", "lineitem"), ("pref_rank_all_m2", "customer"), ("emb_all_m2", "embeddings")):
        rows = spark.read.parquet(f"{larger}/{table}.parquet").count()
        points = FIXTURES[name].points(spark, larger)
        assert points.count() == rows == points.select("ord").distinct().count()
    z = np.array([r.coords for r in FIXTURES["li6_all_m2"].points(spark, DATA).collect()]) / 1000
    assert np.abs(z.mean(axis=0)).max() < 0.01 and np.abs(z.std(axis=0) - 1).max() < 0.01
    far = catalogue.queries()["graph_edges_copurchase_all"](spark, larger).where("dst >= 350").count()
    assert far > 0


def test_random_graph_studies(spark):
    import inspect

    from fairsummary import graphs, studies

    default = {k: p.default for k, p in inspect.signature(studies.ratio_study).parameters.items()}
    assert (default["n"], default["instances"], len(default["vectors"])) == (500, 20, 8)
    got = studies.ratio_study(spark, n=40, instances=3, vectors=((2, 2), (1, 2, 3))).collect()
    assert len(got) == 10 and all(r.runs == 3 and r.over_best >= 1 and r.mean_ratio > 0 and r.feasible for r in got)
    for caps in ("2,2", "1,2,3"):
        assert sum(r.wins for r in got if r.capacities == caps) >= 3
    assert sum(r.runs for r in studies.time_study(spark, (12, 16), 1).collect()) == 2 * len(studies.METHODS)
    n, edges = 30, graphs.random_edges(30, 4)
    rows = {r.ord: r.coords[1:] for r in graphs.shortest_paths(graphs.random_graph(spark, 30, 4), list(range(30))).collect()}
    D = graphs.path_matrix(n, *edges)
    reachable = D <= edges[2].sum()
    assert all((np.array(rows[i])[reachable[i]] == D[i][reachable[i]]).all() for i in range(n))


def test_summaries_for_the_driver_are_bounded_by_what_they_take_there(spark):
    """Collected rows are objects: several times the plain values that the bound once counted."""
    import tracemalloc

    for width in (1, 8):
        some = spark.range(5000).selectExpr("id + 1000000 AS block", "concat('r', 'ep') AS role", "CAST(3 AS INT) AS pivot", "id + 10000000 AS ord", "4 AS grp", "array_repeat(id + 100000000, 8) AS coords" if width > 1 else "id + 100000000 AS coords", "rand() AS r")
        tracemalloc.start()
        rows = some.collect()
        held, _ = tracemalloc.get_traced_memory()
        tracemalloc.stop()
        assert len(rows) == 5000 and held <= methods.driver_size(5000, width)


def _every_radius(inst):
    """(radius, its rank, members of all balls) of the first pairwise distance that succeeds, by trying all."""
    P = inst.points.sorted()
    d = inst.metric.batch(P.coords, P.coords).astype(float)
    for n, tau in enumerate(np.unique(d), 1):
        kept = []
        for i in range(len(d)):
            if not kept or d[i, kept].min() > 2 * tau:
                kept.append(i)
        if len(kept) <= inst.k and hitting_set([P.take(d[i] <= tau) for i in kept], inst.caps)[1] == len(kept):
            return float(tau), n, int((d[kept] <= tau).sum())


def test_exact_balls_at_any_size(spark, monkeypatch):
    for seed in range(60):
        inst = random_instance(seed)
        x = baselines.ball_matching_exact(inst)
        assert (x.tau, x.stats["guesses"], x.stats["stored"]) == _every_radius(inst), seed
    rows = random_rows(8, 450, 2, 60)  # more than the default of points
    P = Points(np.array([r[0] for r in rows]), np.array([r[1] for r in rows]), np.array([r[2] for r in rows]))
    want = baselines.ball_matching_exact(FairInstance(P, L1, (2, 1)))
    assert (want.tau, want.stats["guesses"], want.stats["stored"]) == _every_radius(FairInstance(P, L1, (2, 1)))
    for held in (baselines.DRIVER_BYTES, 0):
        monkeypatch.setattr(baselines, "DRIVER_BYTES", held)
        x = baselines.ball_matching_exact(FairInstance(frame(spark, rows, 3), L1, (2, 1)))
        assert (x.tau, x.cost, sorted(x.centres.ord.tolist()), x.stats["guesses"], x.stats["stored"]) == (want.tau, want.cost, sorted(want.centres.ord.tolist()), want.stats["guesses"], want.stats["stored"])


def test_ratio_study_of_the_line_items(spark):
    from fairsummary import catalogue, graphs, studies
    from fairsummary.workloads import spark_sql

    of = {}
    for r in spark.read.parquet(f"{DATA}/lineitem.parquet").select("l_orderkey", "l_partkey").collect():
        of.setdefault((r.l_orderkey, r.l_partkey % 20), set()).add(r.l_partkey // 20 % 500)
    want = {(g, u, v) for (_, g), vs in of.items() for u in vs for v in vs if u < v}
    edges = spark_sql(spark, DATA, graphs.FOLDED).collect()
    assert {(r.graph, r.src, r.dst) for r in edges} == want and len(edges) == len(want)
    got = catalogue.queries()["random_graph_ratios"](spark, DATA).collect()
    assert len(got) == 8 * (len(studies.METHODS) - 1) and all(r.runs == len({g for g, _, _ in want}) and r.feasible for r in got)
