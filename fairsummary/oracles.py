"""DuckDB SQL for whole runs of the methods, from the bounds to the cost, as chains of common table expressions.

Every arbitrary choice follows ``ord`` and every matching is the first of the
largest ones (group 0 before 1, set by set), so a run has one right answer.
Greedy pivots keep only the points that are still uncovered: the next pivot is
the smallest of them.  Matchings are built set by set over states of used
capacity, each with its first assignment.
"""

from __future__ import annotations

import re

from .workloads import Fixture

#: Guesses the SQL lays out at most; a run that needs more shows as a missing row.
MOST_GUESSES = 140


def _caps(f: Fixture) -> str:
    return f"([{', '.join(map(str, f.caps))}])"


def ladder_values(eps: float, count: int = MOST_GUESSES) -> str:
    """(g, mult, prev): the powers of 1 + eps exactly as the driver computes them."""
    steps = [(1 + eps) ** i for i in range(count)]
    return ", ".join(f"({i}, {m!r}e0, {(steps[i - 1] if i else 0.0)!r}e0)" for i, m in enumerate(steps))


def bounds(f: Fixture) -> str:
    """p, s (first of the groups), u.high, fft (farthest-first), low11.v, fp (first distinct positions), low9.v."""
    k, d = sum(f.caps), f.metric.sql
    return f"""p AS MATERIALIZED ({f.duck}),
s AS MATERIALIZED (SELECT ord, grp, coords FROM (SELECT *, row_number() OVER (PARTITION BY grp ORDER BY ord) AS n FROM p) x WHERE n <= {_caps(f)}[grp + 1]),
u AS MATERIALIZED (SELECT CAST(max(d) AS DOUBLE) AS high FROM (SELECT a.ord, min({d("a.coords", "s.coords")}) AS d FROM p a, s GROUP BY a.ord) x),
ff AS (SELECT CAST(0 AS BIGINT) AS step, ord, coords, CAST(4e18 AS DOUBLE) AS md, CAST(NULL AS BIGINT) AS pv, CAST(NULL AS DOUBLE) AS far FROM p
UNION ALL SELECT r.step + 1, r.ord, r.coords, least(r.md, CAST({d("r.coords", "c.coords")} AS DOUBLE)), c.ord, c.md
FROM ff r, (SELECT ord, coords, md FROM ff WHERE md > 0 AND step < {k + 1} ORDER BY md DESC, ord LIMIT 1) c),
low11 AS MATERIALIZED (SELECT coalesce(max(CASE WHEN step = {k + 1} THEN far / 2 END), 0.0) AS v FROM ff),
fd AS (SELECT CAST(0 AS BIGINT) AS step, ord, coords FROM p
UNION ALL SELECT r.step + 1, r.ord, r.coords FROM fd r, (SELECT ord, coords FROM fd ORDER BY ord LIMIT 1) c WHERE r.step < {k} AND {d("r.coords", "c.coords")} > 0),
fp AS MATERIALIZED (SELECT p.ord, p.coords FROM p JOIN (SELECT step, min(ord) AS ord FROM fd GROUP BY step) x USING (ord)),
low9 AS MATERIALIZED (SELECT CAST(min({d("a.coords", "b.coords")}) AS DOUBLE) / 2 AS v FROM fp a JOIN fp b ON a.ord < b.ord WHERE (SELECT count(*) FROM fp) > {k})"""


def ladder(low: str, eps: float = 0.1) -> str:
    return f"lad AS MATERIALIZED (SELECT CAST(g AS INTEGER) AS g, {low}.v * mult AS tau FROM (VALUES {ladder_values(eps)}) t(g, mult, prev), {low}, u WHERE g = 0 OR {low}.v * prev < u.high)"


def pivots(f: Fixture, source: str, factor: int, own: bool = False) -> str:
    """piv(g, step, pv, tau) and alive(g): greedy pivots of source(ord, pos, coords) at factor times tau; with ``own`` the source has a column g."""
    k = sum(f.caps)
    match = "JOIN " + source + " x ON x.g = lad.g" if own else ", " + source + " x"
    return f"""run AS (SELECT CAST(0 AS BIGINT) AS step, lad.g, lad.tau, x.pos, x.ord, x.coords FROM lad {match}
UNION ALL SELECT r.step + 1, r.g, r.tau, r.pos, r.ord, r.coords FROM run r JOIN (SELECT g, min_by(coords, pos) AS at FROM run GROUP BY g) c ON c.g = r.g WHERE r.step < {k} AND {f.metric.sql("r.coords", "c.at")} > {factor} * r.tau),
piv0 AS MATERIALIZED (SELECT g, step, min_by(ord, pos) AS pv, any_value(tau) AS tau FROM run GROUP BY g, step),
alive AS MATERIALIZED (SELECT g, max(step) + 1 AS n FROM piv0 GROUP BY g HAVING max(step) < {k}),
piv AS MATERIALIZED (SELECT piv0.* FROM piv0 JOIN alive USING (g))"""


def members(f: Fixture, source: str, factor: int, kind: str, own: bool = False) -> str:
    """rep(g, step, grp, ord), the member that serves for its group, and size(g, n), how many points a guess holds."""
    d = f.metric.sql("a.coords", "b.coords")
    near = f"near AS MATERIALIZED (SELECT v.g, v.step, v.pv, b.grp AS pgrp, a.ord, a.grp, {d} AS d FROM piv v JOIN p b ON b.ord = v.pv JOIN {source} a ON {'a.g = v.g AND ' if own else ''}{d} <= {factor} * v.tau)"
    if kind == "nearest":
        rep = "rep AS MATERIALIZED (SELECT g, step, grp, ord FROM (SELECT *, row_number() OVER (PARTITION BY g, step, grp ORDER BY d, ord) AS n FROM near) x WHERE n = 1), size AS (SELECT g, count(*) AS n FROM near GROUP BY g)"
    elif kind == "quota":
        rep = f"""kept AS MATERIALIZED (SELECT * FROM (SELECT *, row_number() OVER (PARTITION BY g, step, grp ORDER BY ord) AS n FROM near WHERE ord <> pv) x WHERE n <= {_caps(f)}[grp + 1] - CASE WHEN grp = pgrp THEN 1 ELSE 0 END),
rep AS MATERIALIZED (SELECT g, step, grp, max(ord) AS ord FROM kept GROUP BY g, step, grp UNION ALL SELECT v.g, v.step, b.grp, v.pv FROM piv v JOIN p b ON b.ord = v.pv WHERE NOT EXISTS (SELECT 1 FROM kept k WHERE k.g = v.g AND k.step = v.step AND k.grp = b.grp)),
size AS (SELECT g, count(*) AS n FROM (SELECT g FROM kept UNION ALL SELECT g FROM piv) x GROUP BY g)"""
    else:
        rep = "rep AS MATERIALIZED (SELECT g, step, grp, min(ord) AS ord FROM near WHERE grp <> pgrp GROUP BY g, step, grp UNION ALL SELECT v.g, v.step, b.grp, v.pv FROM piv v JOIN p b ON b.ord = v.pv), size AS (SELECT g, count(*) AS n FROM rep GROUP BY g)"
    return f"{near},\n{rep}"


def matching(f: Fixture) -> str:
    """good(g, vec, n): the guesses whose sets are all met, with the first assignment as letters."""
    return f"""st AS (SELECT g, CAST(0 AS BIGINT) AS step, CAST(0 AS BIGINT) AS code, '' AS vec FROM alive
UNION ALL SELECT t.g, t.step + 1, t.code + (CAST(1 AS BIGINT) << (4 * r.grp)), min(t.vec || chr(97 + r.grp)) FROM st t JOIN rep r ON r.g = t.g AND r.step = t.step WHERE ((t.code >> (4 * r.grp)) & 15) < {_caps(f)}[r.grp + 1] GROUP BY 1, 2, 3),
good AS MATERIALIZED (SELECT alive.g, any_value(alive.n) AS n, min(vec) AS vec FROM st JOIN alive ON alive.g = st.g AND alive.n = st.step GROUP BY alive.g)"""


def finish(f: Fixture, pool: str, final: str) -> str:
    """cen(g, grp, ord): chosen points filled up to capacity from the pool, and cost(g, cost), for the guesses of ``final``."""
    return f"""fin AS MATERIALIZED ({final}),
ch AS MATERIALIZED (SELECT fin.g, r.grp, r.ord FROM fin JOIN rep r ON r.g = fin.g AND substr(fin.vec, CAST(r.step + 1 AS BIGINT), 1) = chr(97 + r.grp)),
more AS (SELECT x.g, x.grp, x.ord FROM (SELECT fin.g, q.grp, q.ord, row_number() OVER (PARTITION BY fin.g, q.grp ORDER BY q.ord) AS n FROM fin, {pool} q WHERE NOT EXISTS (SELECT 1 FROM ch WHERE ch.g = fin.g AND ch.ord = q.ord)) x
LEFT JOIN (SELECT g, grp, count(*) AS c FROM ch GROUP BY g, grp) h ON h.g = x.g AND h.grp = x.grp WHERE x.n <= {_caps(f)}[x.grp + 1] - coalesce(h.c, 0)),
cen AS MATERIALIZED (SELECT * FROM ch UNION ALL SELECT * FROM more),
cost AS MATERIALIZED (SELECT g, CAST(max(d) AS DOUBLE) AS cost FROM (SELECT c.g, a.ord, min({f.metric.sql("a.coords", "b.coords")}) AS d FROM cen c JOIN p b ON b.ord = c.ord, p a GROUP BY c.g, a.ord) x GROUP BY g)"""


def row(f: Fixture, name: str, winner: str = "SELECT g FROM fin", guesses: str = "(SELECT count(*) FROM lad)", stored: str = "(SELECT max(n) FROM size)", sent: str = "0") -> str:
    """One row as :func:`catalogue.method_row` makes it."""
    count = ", ',', ".join(f"(SELECT count(*) FROM cen WHERE cen.g = w.g AND grp = {j})" for j in range(len(f.caps)))
    return f"""SELECT '{name}' AS method, round(lad.tau, 6) AS tau, cost.cost, CASE WHEN low11.v > 0 THEN round(cost.cost / low11.v, 6) END AS ratio, CAST((SELECT count(*) FROM cen WHERE cen.g = w.g) AS INTEGER) AS centres, concat({count}) AS group_counts,
(SELECT count(*) FROM cen WHERE cen.g = w.g) <= {sum(f.caps)} AND NOT EXISTS (SELECT 1 FROM cen WHERE cen.g = w.g GROUP BY grp HAVING count(*) > any_value({_caps(f)}[grp + 1])) AS feasible,
CAST(fin.n AS INTEGER) AS hits, CAST(fin.n AS INTEGER) AS sets, CAST({guesses} AS INTEGER) AS guesses, CAST({stored} AS BIGINT) AS stored, CAST({sent} AS BIGINT) AS sent, (SELECT string_agg(CAST(ord AS VARCHAR), ',' ORDER BY ord) FROM cen WHERE cen.g = w.g) AS chosen
FROM ({winner}) w JOIN fin ON fin.g = w.g JOIN lad ON lad.g = w.g JOIN cost ON cost.g = w.g, low11"""


_FIRST = "SELECT * FROM good ORDER BY g LIMIT 1"


def _with(*parts: str) -> str:
    return "SELECT * FROM (WITH RECURSIVE " + ",\n".join(parts[:-1]) + "\n" + parts[-1] + ") q"


def two_pass(f: Fixture, name: str, search: str = "all", kind: str = "first", low: str = "low9") -> str:
    """The two-pass method, or with other members and another bound the baselines that share its shape."""
    head = [bounds(f), "src AS (SELECT ord, ord AS pos, coords FROM p)", ladder(low), pivots(f, "src", 2), members(f, "p", 1, kind), matching(f)]
    if search == "first_success":
        return _with(*head, finish(f, "s", _FIRST), row(f, name, guesses="fin.g + 1", stored="(SELECT max(size.n) FROM size, fin WHERE size.g <= fin.g)"))
    if search == "best_cost":
        return _with(*head, finish(f, "s", "SELECT * FROM good"), row(f, name, winner="SELECT g FROM cost ORDER BY cost, g LIMIT 1"))
    if search == "bisect":
        walk = """walk AS (SELECT -1 AS lo, max(g) AS hi, max(g) AS tried FROM lad
UNION ALL SELECT CASE WHEN ok THEN lo ELSE mid END, CASE WHEN ok THEN mid ELSE hi END, mid FROM (SELECT lo, hi, (lo + hi) // 2 AS mid, good.g IS NOT NULL AS ok FROM walk LEFT JOIN good ON good.g = (lo + hi) // 2 WHERE hi - lo > 1) x)"""
        return _with(*head, walk, finish(f, "s", "SELECT good.* FROM good JOIN (SELECT hi FROM walk ORDER BY hi - lo LIMIT 1) b ON good.g = b.hi"), row(f, name, guesses="(SELECT count(DISTINCT tried) FROM walk)", stored="(SELECT max(n) FROM size WHERE g IN (SELECT tried FROM walk))"))
    return _with(*head, finish(f, "s", _FIRST), row(f, name))


def ball_exact(f: Fixture, name: str) -> str:
    """Every pairwise distance is a guess; ``stored`` is that of the guess that won."""
    lad = f"lad AS MATERIALIZED (SELECT CAST(row_number() OVER (ORDER BY tau) - 1 AS INTEGER) AS g, tau FROM (SELECT DISTINCT CAST({f.metric.sql('a.coords', 'b.coords')} AS DOUBLE) AS tau FROM p a, p b) x)"
    whole = members(f, "p", 1, "first")
    return _with(bounds(f), "src AS (SELECT ord, ord AS pos, coords FROM p)", lad, pivots(f, "src", 2), whole, matching(f), finish(f, "p", _FIRST), row(f, name, guesses="fin.g + 1", stored="(SELECT count(*) FROM near, fin WHERE near.g = fin.g)"))


def blocks(f: Fixture, size: int, number: str = "") -> str:
    """bp(block, step, pv): block pivots, rad(block, r), lr(block, ord): block representatives; blocks are ord div size or the number given."""
    k, d = sum(f.caps), f.metric.sql
    return f"""pb AS MATERIALIZED (SELECT *, {number or f'CAST(floor(ord / {size}) AS BIGINT)'} AS block FROM p),
bl AS (SELECT CAST(0 AS BIGINT) AS step, block, ord, coords, CAST(4e18 AS DOUBLE) AS md, CAST(NULL AS BIGINT) AS pv, CAST(NULL AS DOUBLE) AS far FROM pb
UNION ALL SELECT r.step + 1, r.block, r.ord, r.coords, least(r.md, CAST({d("r.coords", "c.coords")} AS DOUBLE)), c.ord, c.md
FROM bl r JOIN (SELECT block, ord, coords, md FROM (SELECT *, row_number() OVER (PARTITION BY block ORDER BY md DESC, ord) AS n FROM bl WHERE md > 0 AND step <= {k}) x WHERE n = 1) c ON c.block = r.block),
bp0 AS MATERIALIZED (SELECT DISTINCT block, step, pv, far FROM bl WHERE pv IS NOT NULL),
rad AS MATERIALIZED (SELECT block, coalesce(max(CASE WHEN step = {k + 1} THEN far / 2 END), 0.0) AS r FROM bp0 GROUP BY block),
bp AS MATERIALIZED (SELECT * FROM bp0 WHERE step <= {k}),
lr AS MATERIALIZED (SELECT block, min(ord) AS ord FROM (SELECT bp.block, bp.step, a.ord, a.grp, b.grp AS pgrp FROM bp JOIN rad ON rad.block = bp.block JOIN p b ON b.ord = bp.pv JOIN pb a ON a.block = bp.block AND {d("a.coords", "b.coords")} <= 2 * r) x WHERE grp <> pgrp GROUP BY block, step, grp UNION ALL SELECT block, pv FROM bp)"""


def coordinator(f: Fixture, size: int, scale: float = 5.1, widest: bool = False, eps: float = 0.1) -> list[str]:
    """From the points to good(g, vec, n) of the coordinator."""
    order = "r DESC, block, step" if widest else "block, step"
    return [
        bounds(f), blocks(f, size), f"src AS MATERIALIZED (SELECT p.ord, p.coords, row_number() OVER (ORDER BY {order}) AS pos FROM bp JOIN rad USING (block) JOIN p ON p.ord = bp.pv)",
        "l AS MATERIALIZED (SELECT p.* FROM p WHERE ord IN (SELECT ord FROM lr))",
        f"lad AS MATERIALIZED (SELECT CAST(g AS INTEGER) AS g, (SELECT max(r) FROM rad) / {scale!r}e0 * mult AS tau FROM (VALUES {ladder_values(eps)}) t(g, mult, prev))",
        pivots(f, "src", 10), members(f, "l", 5, "first"), matching(f),
    ]


def distributed(f: Fixture, name: str, size: int, scale: float = 5.1, widest: bool = False) -> str:
    sent = "(SELECT block, count(DISTINCT ord) AS n FROM lr GROUP BY block)"
    return _with(*coordinator(f, size, scale, widest), finish(f, "l", _FIRST), row(f, name, guesses="fin.g + 1", stored=f"(SELECT max(n) FROM {sent} x)", sent=f"(SELECT sum(n) FROM {sent} x)"))


def coordinator_trace(f: Fixture, size: int, guesses: int) -> str:
    """(guess, tau, pivots, success) of the first guesses; pivots stop at k + 1."""
    return _with(*coordinator(f, size), f"SELECT lad.g AS guess, round(lad.tau, 6) AS tau, x.n AS pivots, lad.g IN (SELECT g FROM good) AS success FROM lad JOIN (SELECT g, count(*) AS n FROM piv0 GROUP BY g) x ON x.g = lad.g WHERE lad.g < {guesses}")


def plain(f: Fixture, size: int) -> str:
    """Cost of farthest-first on what farthest-first in blocks sends, without groups."""
    k, d = sum(f.caps), f.metric.sql
    return _with(f"p AS MATERIALIZED ({f.duck})", blocks(f, size), f"""gf AS (SELECT CAST(0 AS BIGINT) AS step, p.ord, p.coords, CAST(4e18 AS DOUBLE) AS md, CAST(NULL AS BIGINT) AS pv FROM p WHERE ord IN (SELECT pv FROM bp)
UNION ALL SELECT r.step + 1, r.ord, r.coords, least(r.md, CAST({d("r.coords", "c.coords")} AS DOUBLE)), c.ord FROM gf r, (SELECT ord, coords FROM gf WHERE md > 0 AND step < {k} ORDER BY md DESC, ord LIMIT 1) c)""",
        f"SELECT CAST(max(d) AS DOUBLE) AS cost, CAST((SELECT count(DISTINCT (block, pv)) FROM bp) AS BIGINT) AS sent FROM (SELECT a.ord, min({d('a.coords', 'b.coords')}) AS d FROM p a, p b WHERE b.ord IN (SELECT pv FROM gf) GROUP BY a.ord) x")


def one_pass(f: Fixture, name: str, size: int, lean: bool = False) -> str:
    """Shards are ord div size; a guess that any of them breaks has failed."""
    k, d = sum(f.caps), f.metric.sql
    quota = "1" if lean else f"{_caps(f)}[grp + 1]"
    shards = f"""sh AS (SELECT CAST(0 AS BIGINT) AS step, lad.g, lad.tau, CAST(floor(ord / {size}) AS BIGINT) AS shard, ord, coords FROM lad, p
UNION ALL SELECT r.step + 1, r.g, r.tau, r.shard, r.ord, r.coords FROM sh r JOIN (SELECT g, shard, min_by(coords, ord) AS at FROM sh GROUP BY g, shard) c ON c.g = r.g AND c.shard = r.shard WHERE r.step < {k} AND {d("r.coords", "c.at")} > 2 * r.tau),
sp0 AS MATERIALIZED (SELECT g, shard, step, min(ord) AS pv, any_value(tau) AS tau FROM sh GROUP BY g, shard, step),
sp AS MATERIALIZED (SELECT * FROM sp0 WHERE g NOT IN (SELECT g FROM sp0 WHERE step = {k})),
cr AS MATERIALIZED (SELECT sp.g, sp.shard, a.ord, a.grp, min(sp.step) AS step FROM sp JOIN p b ON b.ord = sp.pv JOIN p a ON floor(a.ord / {size}) = sp.shard AND {d("a.coords", "b.coords")} <= 2 * sp.tau GROUP BY ALL),
held AS MATERIALIZED (SELECT g, shard, ord, grp FROM (SELECT *, row_number() OVER (PARTITION BY g, shard, step, grp ORDER BY ord) AS n FROM cr) x WHERE n <= {quota}),
src AS MATERIALIZED (SELECT sp.g, p.ord, p.ord AS pos, p.coords FROM sp JOIN p ON p.ord = sp.pv),
l AS MATERIALIZED (SELECT held.g, p.* FROM held JOIN p ON p.ord = held.ord)"""
    return _with(bounds(f), ladder("low9"), shards, pivots(f, "src", 10, own=True), members(f, "l", 5, "first", own=True), matching(f), finish(f, "s", _FIRST), row(f, name, stored="(SELECT max(n) FROM (SELECT count(*) AS n FROM held GROUP BY g, shard) x)"))


def exact_ones(f: Fixture, name: str) -> str:
    """The optimum for capacities of one with all groups present: every choice of a point of each group, of equal costs the first by ord."""
    m, d = len(f.caps), f.metric.sql
    froms = ", ".join(f"(SELECT ord AS o{j}, coords AS c{j} FROM p WHERE grp = {j}) g{j}" for j in range(m))
    least = f"least({', '.join(d('a.coords', f'c{j}') for j in range(m))})"
    sorted_ = f"list_sort([{', '.join(f'o{j}' for j in range(m))}])"
    return _with(f"p AS MATERIALIZED ({f.duck})", f"t AS (SELECT {sorted_} AS c, CAST(max({least}) AS DOUBLE) AS cost FROM p a, {froms} GROUP BY c)", f"SELECT '{name}' AS method, cost, array_to_string(c, ',') AS chosen FROM t ORDER BY cost, c LIMIT 1")


def arbitrary(f: Fixture, name: str) -> str:
    """The first points of the groups as a method."""
    count = ", ',', ".join(f"(SELECT count(*) FROM s WHERE grp = {j})" for j in range(len(f.caps)))
    return _with(bounds(f), f"""SELECT '{name}' AS method, CAST(0 AS DOUBLE) AS tau, u.high AS cost, CASE WHEN low11.v > 0 THEN round(u.high / low11.v, 6) END AS ratio, CAST((SELECT count(*) FROM s) AS INTEGER) AS centres, concat({count}) AS group_counts, true AS feasible,
CAST(0 AS INTEGER) AS hits, CAST(0 AS INTEGER) AS sets, CAST(0 AS INTEGER) AS guesses, CAST((SELECT count(*) FROM s) AS BIGINT) AS stored, CAST(0 AS BIGINT) AS sent, (SELECT string_agg(CAST(ord AS VARCHAR), ',' ORDER BY ord) FROM s) AS chosen FROM u, low11""")


def window_messages(f: Fixture, table: str, key: str, ts: str) -> str:
    """(day, r, sent) of every day as a block."""
    day = f"(SELECT date_diff('day', DATE '2000-01-01', CAST({ts} AS DATE)) FROM {table} e WHERE e.{key} = p.ord)"
    return _with(f"p AS MATERIALIZED ({f.duck})", blocks(f, 0, day), "SELECT CAST(DATE '2000-01-01' + CAST(lr.block AS INTEGER) AS VARCHAR) AS day, any_value(r) AS r, count(DISTINCT ord) AS sent FROM lr JOIN rad ON rad.block = lr.block GROUP BY lr.block")


def one_pass_centres(f: Fixture, guesses: list[float]) -> str:
    """(tau, sets, chosen) of the one-pass method on the whole as one shard, at given guesses; filled up from what it keeps."""
    k, d = sum(f.caps), f.metric.sql
    lad = f"lad AS MATERIALIZED (SELECT * FROM (VALUES {', '.join(f'({i}, {t!r}e0)' for i, t in enumerate(guesses))}) t(g, tau))"
    kept = f"""cr AS MATERIALIZED (SELECT v.g, a.ord, a.grp, min(v.step) AS step FROM piv v JOIN p b ON b.ord = v.pv JOIN p a ON {d("a.coords", "b.coords")} <= 2 * v.tau GROUP BY ALL),
held AS MATERIALIZED (SELECT x.g, p.* FROM (SELECT *, row_number() OVER (PARTITION BY g, step, grp ORDER BY ord) AS n FROM cr) x JOIN p ON p.ord = x.ord WHERE n <= {_caps(f)}[x.grp + 1])"""
    second = pivots(f, "xsrc", 10, own=True)
    for old in ("run", "piv0", "piv", "alive"):
        second = re.sub(rf"\b{old}\b", f"{old}_b", second)
    rest = ",\n".join([members(f, "held", 5, "first", own=True), matching(f)])
    for old in ("piv", "alive"):
        rest = re.sub(rf"\b{old}\b", f"{old}_b", rest)
    done = finish(f, "(SELECT DISTINCT ord, grp FROM held JOIN fin USING (g))", _FIRST)
    return _with(f"p AS MATERIALIZED ({f.duck})", "src AS (SELECT ord, ord AS pos, coords FROM p)", lad, pivots(f, "src", 2), kept, "xsrc AS MATERIALIZED (SELECT v.g, p.ord, p.ord AS pos, p.coords FROM piv v JOIN p ON p.ord = v.pv)", second, rest, done, "SELECT round(lad.tau, 6) AS tau, CAST(fin.n AS BIGINT) AS sets, (SELECT string_agg(CAST(ord AS VARCHAR), ',' ORDER BY ord) FROM cen) AS chosen FROM fin JOIN lad ON lad.g = fin.g")
