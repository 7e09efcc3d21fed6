"""Choosing one point of as many representative sets as capacities allow.  Sizes here follow k and m, so this stays on the driver."""

from __future__ import annotations

from itertools import combinations, product

from .model import Points


def _augment(edges: list[set[int]], room: list[int], used: list[list[int]], start: int, barred: set[int]) -> bool:
    """Find a place for one more set by moving others; breadth first over groups."""
    came: dict[int, tuple[int, int]] = {}
    queue = [(start, j) for j in sorted(edges[start])]
    while queue:
        s, j = queue.pop(0)
        if j in came or j in barred:
            continue
        came[j] = (s, -1)
        if len(used[j]) < room[j]:
            while True:
                s = came[j][0]
                old = next((g for g in range(len(room)) if s in used[g]), None)
                used[j].append(s)
                if old is None:
                    return True
                used[old].remove(s)
                j = old
        queue += [(t, g) for t in used[j] for g in sorted(edges[t]) if g not in came]
    return False


def assign(edges: list[set[int]], caps: tuple[int, ...]) -> list[int | None]:
    """Group given to each set, or None: a maximum flow with one node for each group and its capacity as the sink edge."""
    room, used = list(caps), [[] for _ in caps]
    for s in range(len(edges)):
        _augment([e & set(range(len(caps))) for e in edges], room, used, s, set())
    return [next((j for j, u in enumerate(used) if s in u), None) for s in range(len(edges))]


def assign_slots(edges: list[set[int]], caps: tuple[int, ...]) -> list[int | None]:
    """The same by matching sets to single slots of groups."""
    slots = [j for j, c in enumerate(caps) for _ in range(c)]
    held: list[int | None] = [None] * len(slots)

    def place(s: int, seen: set[int]) -> bool:
        for n, j in enumerate(slots):
            if j in edges[s] and n not in seen:
                seen.add(n)
                if held[n] is None or place(held[n], seen):
                    held[n] = s
                    return True
        return False

    for s in range(len(edges)):
        place(s, set())
    return [next((slots[n] for n, h in enumerate(held) if h == s), None) for s in range(len(edges))]


def assign_canonical(edges: list[set[int]], caps: tuple[int, ...]) -> list[int | None]:
    """Of all largest assignments the first in the order group 0, 1, ..., none, set by set."""
    best = sum(x is not None for x in assign(edges, caps))
    room, out, got = list(caps), [], 0
    for s in range(len(edges)):
        for j in [*sorted(j for j in edges[s] if j < len(caps) and room[j]), None]:
            left = [r - (i == j) for i, r in enumerate(room)]
            rest = sum(x is not None for x in assign(edges[s + 1 :], tuple(left)))
            if got + (j is not None) + rest == best:
                out.append(j)
                got += j is not None
                room = left
                break
    return out


def certificate(edges: list[set[int]], caps: tuple[int, ...]) -> int:
    """The matching size as a minimum cut: over group subsets, their capacities plus the sets that reach outside."""
    groups = range(len(caps))
    return min(sum(caps[j] for j in chosen) + sum(bool(e - set(chosen)) for e in edges) for r in range(len(caps) + 1) for chosen in combinations(groups, r))


def brute_force(edges: list[set[int]], caps: tuple[int, ...]) -> int:
    """Largest number of sets served, by trying every assignment."""
    best = 0
    for choice in product(*[[*sorted(e), None] for e in edges]):
        if all(choice.count(j) <= c for j, c in enumerate(caps)):
            best = max(best, sum(x is not None for x in choice))
    return best


def hitting_set(sets: list[Points], caps: tuple[int, ...], formulation: str = "canonical", pick: int = 0) -> tuple[Points | None, int]:
    """Chosen points, one of each served set, and how many sets are served; ``pick`` is the place of the member taken among those of its group."""
    solve = {"flow": assign, "slots": assign_slots, "canonical": assign_canonical}[formulation]
    edges = [set(s.grp.tolist()) for s in sets]
    given = solve(edges, caps)
    chosen = [s.take([[i for i, g in enumerate(s.grp.tolist()) if g == j][pick]]) for s, j in zip(sets, given) if j is not None]
    return (Points.join(chosen) if chosen else None), len(chosen)


def complete(chosen: Points | None, caps: tuple[int, ...], pool: Points) -> Points:
    """Fill every group to its capacity from the pool, in the pool's order, without repeating a point."""
    parts = [chosen] if chosen is not None else []
    have = set(chosen.ord.tolist()) if chosen is not None else set()
    count = [0] * len(caps) if chosen is None else [int((chosen.grp == j).sum()) for j in range(len(caps))]
    take = []
    for i, (o, g) in enumerate(zip(pool.ord.tolist(), pool.grp.tolist())):
        if o not in have and count[g] < caps[g]:
            have.add(o)
            count[g] += 1
            take.append(i)
    return Points.join([*parts, pool.take(take)])
