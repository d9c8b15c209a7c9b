"""Exact selection from a pool for one query, in plain Python: a pool holds at most k records of each cell.

Records of one cell differ only in their distance, so a solution is how many to take from each cell, nearest first; a cell's
i-th record costs its i-th smallest distance, which makes costs convex.
"""

from __future__ import annotations

import heapq
import time
from collections import Counter, defaultdict
from itertools import combinations

INF = float("inf")


def flow(costs: dict, need_a: dict, need_b: dict) -> dict | None:
    """Min-cost flow from values of one attribute to values of another. costs: (a, b) -> increasing distances. Returns
    (a, b) -> how many, or None where the needs cannot be met.

    Cheapest augmenting paths, one unit at a time. Potentials (each node's distance so far) keep all residual costs at 0 or
    more, so a heap finds a path without going over arcs again and again."""
    left_a, left_b = dict(need_a), dict(need_b)
    took = dict.fromkeys(costs, 0)
    a_no = {v: i for i, v in enumerate(v for v, n in left_a.items() if n > 0)}
    b_no = {v: len(a_no) + i for i, v in enumerate(v for v, n in left_b.items() if n > 0)}
    names = [*a_no, *b_no]
    m, arcs = len(a_no), [[] for _ in names]
    for e, own in costs.items():
        if own and e[0] in a_no and e[1] in b_no:
            i, j = a_no[e[0]], b_no[e[1]]
            arcs[i].append((j, e, own))
            arcs[j].append((i, e, own))
    lift = [0.0] * len(names)
    for _ in range(sum(need_a.values())):
        dist, come, done = [INF] * len(names), [None] * len(names), [False] * len(names)
        heap = []
        for v, i in a_no.items():
            if left_a[v] > 0:
                dist[i] = -lift[i]
                heap.append((dist[i], i))
        heapq.heapify(heap)
        while heap:
            d, i = heapq.heappop(heap)
            if done[i]:
                continue
            done[i] = True
            for j, e, own in arcs[i]:
                x = took[e]
                if i < m:
                    if x == len(own):
                        continue
                    step = own[x]
                elif x:
                    step = -own[x - 1]
                else:
                    continue
                to = d + max(0.0, step + lift[i] - lift[j])
                if to < dist[j] - 1e-13:
                    dist[j], come[j] = to, (i, e)
                    heapq.heappush(heap, (to, j))
        end = min((j for v, j in b_no.items() if left_b[v] > 0 and dist[j] < INF), key=lambda j: dist[j] + lift[j], default=None)
        if end is None:
            return None
        for i, d in enumerate(dist):
            if d < INF:
                lift[i] += d
        left_b[names[end]] -= 1
        at = end
        while come[at] is not None:
            prev, e = come[at]
            took[e] += 1 if prev < m else -1
            at = prev
        left_a[names[at]] -= 1
    return took


def certified(costs: dict, took: dict) -> bool:
    """No cheaper rearrangement exists: the residual graph of a flow has no negative cycle."""
    nodes = {("a", a) for a, _ in costs} | {("b", b) for _, b in costs}
    d = dict.fromkeys(nodes, 0.0)
    for _ in range(len(nodes) + 1):
        moved = False
        for (a, b), own in costs.items():
            x = took[a, b]
            if x < len(own) and d["a", a] + own[x] < d["b", b] - 1e-9:
                d["b", b], moved = d["a", a] + own[x], True
            if x > 0 and d["b", b] - own[x - 1] < d["a", a] - 1e-9:
                d["a", a], moved = d["b", b] - own[x - 1], True
        if not moved:
            return True
    return False


class TooManyStates(Exception):
    pass


def cell_dp(cells: list[tuple], needs: list[dict], most: int | None = None) -> tuple[float, list[int]] | None:
    """cells: (values, increasing distances); needs: for each attribute value -> count. Least cost over all cells in turn,
    with the needs still open as the state; a state that the cells to come cannot serve is dropped. Reaching more than `most`
    states in all raises TooManyStates."""
    index = {(j, v): i for i, (j, v) in enumerate((j, v) for j, own in enumerate(needs) for v, n in own.items() if n > 0)}
    start = tuple(needs[j][v] for j, v in index)
    usable = [(c, [index[j, v] for j, v in enumerate(values)], costs) for c, (values, costs) in enumerate(cells) if all((j, v) in index for j, v in enumerate(values))]
    later = [0] * len(start)
    supply = []
    for _, at, costs in reversed(usable):
        supply.append(tuple(later))
        for i in at:
            later[i] += len(costs)
    supply.reverse()
    states, reached = {start: (0.0, None)}, 0
    for (c, at, costs), rest in zip(usable, supply):
        reached += len(states)
        if most is not None and reached > most:
            raise TooManyStates
        nxt: dict = {}
        for state, (cost, path) in states.items():
            total = cost
            for t in range(min([len(costs), *(state[i] for i in at)]) + 1):
                if t:
                    total += costs[t - 1]
                new = list(state)
                for i in at:
                    new[i] -= t
                if any(n > r for n, r in zip(new, rest)):
                    continue
                key = tuple(new)
                if key not in nxt or total < nxt[key][0]:
                    nxt[key] = (total, (path, c, t) if t else path)
        states = nxt
    end = states.get(tuple([0] * len(start)))
    if end is None:
        return None
    took, path = [0] * len(cells), end[1]
    while path:
        path, c, t = path
        took[c] = t
    return end[0], took


class OutOfTime(Exception):
    pass


def branch(cells: list[tuple], needs: list[dict], node_limit: int = 200_000, seconds: float = 60.0) -> tuple[str, float, list[int] | None]:
    """Integer search for any number of attributes: (status, cost, counts). The two attributes with the most values stay a
    flow; the others' equations are priced into the costs (a bound for any prices), and prices are improved a few steps at
    each node. A flow that breaks an equation is branched on a cell with the value concerned. The first solution known is the
    greedy one, if that meets the counts."""
    if not needs or not sum(needs[0].values()):
        return "ok", 0.0, [0] * len(cells)
    m = len(needs)
    order = sorted(range(m), key=lambda j: -len(needs[j]))
    if m == 1:
        first, second, rest = 0, None, []
    else:
        first, second, rest = order[0], order[1], order[2:]
    live = [i for i, (values, costs) in enumerate(cells) if costs and all(needs[j].get(v, 0) > 0 for j, v in enumerate(values))]
    best, best_took = INF, None
    began, nodes = time.monotonic(), 0
    records = [(values, d) for values, costs in cells for d in costs]
    of_cell = [i for i, (_, costs) in enumerate(cells) for _ in costs]
    first_took = greedy(records, needs, swaps=sum(needs[0].values())) if rest else None
    if first_took is not None:
        best, best_took = sum(records[r][1] for r in first_took), dict(Counter(of_cell[r] for r in first_took))

    def relaxed(lo: dict, hi: dict, price: dict):
        """Value and counts of the priced flow with lo <= count <= hi, or None."""
        a_left = dict(needs[first])
        b_left = dict(needs[second]) if second is not None else {"": sum(a_left.values())}
        pay = 0.0
        for i, n in lo.items():
            values, costs = cells[i]
            pay += sum(costs[:n]) + n * sum(price.get((j, values[j]), 0.0) for j in rest)
            a_left[values[first]] -= n
            b = values[second] if second is not None else ""
            b_left[b] -= n
        if min(a_left.values()) < 0 or min(b_left.values()) < 0:
            return None
        units = defaultdict(list)
        for i in live:
            values, costs = cells[i]
            extra = sum(price.get((j, values[j]), 0.0) for j in rest)
            arc = (values[first], values[second] if second is not None else "")
            units[arc] += [(c + extra, i) for c in costs[lo.get(i, 0) : hi.get(i, len(costs))]]
        base = min((c for own in units.values() for c, _ in own), default=0.0)
        shift = -min(0.0, base)  # every solution takes the same number of units
        for own in units.values():
            own.sort()
        took = flow({e: [c + shift for c, _ in own] for e, own in units.items()}, a_left, b_left)
        if took is None:
            return None
        count = dict(lo)
        for e, n in took.items():
            for c, i in units[e][:n]:
                pay += c
                count[i] = count.get(i, 0) + 1
        return pay - sum(price.get((j, v), 0.0) * n for j in rest for v, n in needs[j].items()), count

    def visit(lo: dict, hi: dict, price: dict) -> None:
        nonlocal best, best_took, nodes
        nodes += 1
        if nodes > node_limit or time.monotonic() - began > seconds:
            raise OutOfTime
        count, step = None, 0.05 if best == INF else max(0.01, best / max(1, sum(needs[0].values())) * 0.05)
        for turn in range(8):
            got = relaxed(lo, hi, price)
            if got is None:
                return
            bound, count = got
            if bound >= best - 1e-9:
                return
            over = defaultdict(int)
            for i, n in count.items():
                for j in rest:
                    over[j, cells[i][0][j]] += n
            gap = {(j, v): over[j, v] - n for j in rest for v, n in needs[j].items()}
            if not any(gap.values()):
                cost = sum(sum(cells[i][1][:n]) for i, n in count.items())
                if cost < best:
                    best, best_took = cost, dict(count)
                if cost <= bound + 1e-9:
                    return
                break
            if turn < 7:
                price = {k: price.get(k, 0.0) + step / (1 + turn) * g for k, g in gap.items()}
        wide = [i for i in live if lo.get(i, 0) < hi.get(i, len(cells[i][1]))]
        if not wide:
            return
        odd = [i for i in wide if any(gap[j, cells[i][0][j]] > 0 for j in rest) and count.get(i, 0) > lo.get(i, 0)]
        pick = max(odd or wide, key=lambda i: (count.get(i, 0) - lo.get(i, 0), i))
        x = count.get(pick, 0)
        if x > lo.get(pick, 0):
            visit(lo, {**hi, pick: x - 1}, price)
            visit({**lo, pick: x}, hi, price)
        else:
            visit({**lo, pick: x + 1}, hi, price)
            visit(lo, {**hi, pick: x}, price)

    status = "ok"
    try:
        visit({}, {}, {})
    except (OutOfTime, RecursionError):
        status = "timeout"
    if best_took is None:
        return ("timeout" if status == "timeout" else "infeasible"), INF, None
    took = [0] * len(cells)
    for i, n in best_took.items():
        took[i] = n
    return status, best, took


def enumerate_sets(records: list[tuple], needs: list[dict]) -> tuple[float, tuple] | None:
    """records: (values, distance). Every subset of the right size; for tests on tiny pools."""
    k, best = sum(needs[0].values()), None
    for own in combinations(range(len(records)), k):
        counts = [defaultdict(int) for _ in needs]
        for i in own:
            for j, v in enumerate(records[i][0]):
                counts[j][v] += 1
        if all({v: n for v, n in needs[j].items() if n} == dict(counts[j]) for j in range(len(needs))):
            cost = sum(records[i][1] for i in own)
            if best is None or cost < best[0]:
                best = (cost, own)
    return best


def greedy(records: list[tuple], needs: list[dict], swaps: int = 200) -> list[int] | None:
    """Nearest first where needs stay open, then exchanges of one for one that mend what is left open. May fail where a
    solution exists; what it returns meets the needs."""
    left = [dict(n) for n in needs]
    order = sorted(range(len(records)), key=lambda i: (records[i][1], i))
    took: list[int] = []
    for i in order:
        if all(left[j].get(v, 0) > 0 for j, v in enumerate(records[i][0])):
            took.append(i)
            for j, v in enumerate(records[i][0]):
                left[j][v] -= 1
    have = [Counter(records[i][0][j] for i in took) for j in range(len(needs))]

    def gap(j, v, more):
        return abs(have[j][v] + more - needs[j].get(v, 0))

    def swapped(a, i):
        """How far the counts are from the needs with the a-th taken record exchanged for record i, against now."""
        total = 0
        for j, (old, new) in enumerate(zip(records[took[a]][0], records[i][0])):
            if old != new:
                total += gap(j, old, -1) - gap(j, old, 0) + gap(j, new, 1) - gap(j, new, 0)
        return total

    k = sum(needs[0].values())
    spare = [i for i in order if i not in set(took)]
    while len(took) < k and spare:
        took.append(spare.pop(0))
        for own, v in zip(have, records[took[-1]][0]):
            own[v] += 1
    for _ in range(swaps + 1):
        if all(own[v] == n[v] for own, n in zip(have, needs) for v in n) and len(took) == k:
            return sorted(took)
        trial = min(((swapped(a, i), records[i][1], a, i) for a in range(len(took)) for i in spare[:200]), default=None)
        if trial is None or trial[0] >= 0:
            return None
        _, _, a, i = trial
        for own, old, new in zip(have, records[took[a]][0], records[i][0]):
            own[old] -= 1
            own[new] += 1
        spare.append(took[a])
        spare.remove(i)
        took = took[:a] + took[a + 1 :] + [i]
    return None
