"""The sequential searches with heaps, for sets that fit one task: a set per group, many groups in parallel.

They count what the published curves show (pairs seen, bounds and distances computed, calls per dimension).
"""

from __future__ import annotations

import heapq
from collections import Counter, defaultdict
from collections.abc import Iterator
from dataclasses import dataclass, field

#: Objects of one group; more belong to the block kernel.
MOST_OBJECTS = 20_000


@dataclass
class Item:
    """An object: size, summed depth and (level, w, count, summed distance below, parent) by node."""

    id: int
    n: int
    s: int
    nodes: dict[str, tuple[int, int, int, int]]
    side: int = 0
    parent: dict[str, str] = field(default_factory=dict)


def emd_exact(x: Item, y: Item, scale: int) -> float:
    small, big = (x, y) if len(x.nodes) <= len(y.nodes) else (y, x)
    shared = sum(w * min(c * big.n, big.nodes[v][2] * small.n) for v, (_, w, c, _) in small.nodes.items() if v in big.nodes)
    return (y.n * x.s + x.n * y.s - 2 * shared) / (x.n * y.n * scale)


def avg_exact(x: Item, y: Item, scale: int) -> float:
    shared = sum(w * c * y.nodes[v][2] for v, (_, w, c, _) in x.nodes.items() if v in y.nodes)
    return (y.n * x.s + x.n * y.s - 2 * shared) / (x.n * y.n * scale)


class GapStream:
    """Pairs of one-dimensional values, nearest first. Neighbours start in the heap; a pair that comes out is fused with
    earlier ones that touch it, since no longer gap can precede its parts."""

    def __init__(self, values: list[tuple[float, int]], hashed: bool = False) -> None:
        if hashed:  # equal values meet in a bucket first, only the distinct ones are sorted
            by: dict[float, list[int]] = defaultdict(list)
            for v, i in values:
                by[v].append(i)
            self.rows = [(v, i) for v in sorted(by) for i in sorted(by[v])]
        else:
            self.rows = sorted(values)
        self.heap = [(self.rows[p + 1][0] - self.rows[p][0], p, p + 1) for p in range(len(self.rows) - 1)]
        heapq.heapify(self.heap)
        self.queued = {(p, q) for _, p, q in self.heap}
        self.from_, self.to = defaultdict(list), defaultdict(list)
        self.calls = 0

    def __iter__(self) -> Iterator[tuple[float, int, int]]:
        while self.heap:
            gap, p, q = heapq.heappop(self.heap)
            self.calls += 1
            self.from_[p].append(q)
            self.to[q].append(p)
            for o, r in [(o, q) for o in self.to[p]] + [(p, r) for r in self.from_[q]]:
                if (o, r) not in self.queued:
                    self.queued.add((o, r))
                    heapq.heappush(self.heap, (self.rows[r][0] - self.rows[o][0], o, r))
            yield gap, self.rows[p][1], self.rows[q][1]


class Best:
    """The k least (distance, a, b)."""

    def __init__(self, k: int) -> None:
        self.k, self.heap = k, []

    def add(self, d: float, a: int, b: int) -> None:
        heapq.heappush(self.heap, (-d, -a, -b))
        if len(self.heap) > self.k:
            heapq.heappop(self.heap)

    @property
    def kth(self) -> float:
        return -self.heap[0][0] if self.k and len(self.heap) == self.k else float("inf") if self.k else -1.0

    def rows(self) -> list[tuple[float, int, int]]:
        return sorted((-d, -a, -b) for d, a, b in self.heap)


def dimensions(items: list[Item], variant: str, h: int, scale: int) -> tuple[list[str], dict[int, dict[str, float]]]:
    """Names of the dimensions and each object's values, the missing ones zero."""
    rows: dict[int, dict[str, float]] = {}
    for i, x in enumerate(items):
        if variant == "edge":
            rows[i] = {v: w * c / x.n / scale for v, (level, w, c, _) in x.nodes.items() if level <= h}
            continue
        own: Counter = Counter()
        for v, (level, _, c, _) in x.nodes.items():
            if variant == "l1_full" or level <= h:
                own[v] += c
                own[x.parent[v]] -= c
        own["root"] += x.n
        rows[i] = {v: c / x.n for v, c in own.items() if c}
    return sorted({v for r in rows.values() for v in r}), rows


def emd_threshold(items: list[Item], k: int, scale: int, variant: str = "l1_reduced", h: int = 1, factor: float = 1.0, least: float = 1.0, two_sided: bool = False, halved: bool = True, hashed: bool = False) -> tuple[list[tuple[float, int, int]], dict[str, int]]:
    """Round-robin over the dimensions; every new pair passes the bound on the dimensions, half L1 over all terms, EMD.

    ``factor`` scales the half L1 of the dimensions and the threshold, ``least`` that over all terms. ``halved=False`` is
    the published threshold, which stops too early.
    """
    names, rows = dimensions(items, variant, h, scale)
    _, all_terms = dimensions(items, "l1_full", h, scale)
    unit = 1.0 if variant == "edge" else factor / 2
    threshold_unit = unit if halved or variant == "edge" else 1.0
    streams = [GapStream([(rows[i].get(v, 0.0), i) for i in range(len(items))], hashed) for v in names]
    its = [iter(s) for s in streams]
    tau = [0.0] * len(names)
    best, seen = Best(k), set()
    counts = Counter(calls=0, new=0, bounds=0, full_l1=0, emd=0)
    live, j = len(names) > 0 and len(items) > 1 and k > 0, 0
    while live and threshold_unit * sum(tau) <= best.kth + 1e-12:
        step = next(its[j], None)
        if step is None:  # one exhausted dimension has shown every pair
            break
        tau[j], p, q = step
        counts["calls"] += 1
        x, y = items[p], items[q]
        key = (min(p, q), max(p, q))
        if key not in seen and not (two_sided and x.side == y.side):
            seen.add(key)
            counts["new"] += 1
            counts["bounds"] += 1
            d1 = unit * sum(abs(rows[p].get(v, 0.0) - rows[q].get(v, 0.0)) for v in rows[p].keys() | rows[q].keys())
            if d1 <= best.kth + 1e-12:
                counts["full_l1"] += 1
                d2 = least / 2 * sum(abs(all_terms[p].get(v, 0.0) - all_terms[q].get(v, 0.0)) for v in all_terms[p].keys() | all_terms[q].keys())
                if d2 <= best.kth + 1e-12:
                    counts["emd"] += 1
                    a, b = (x, y) if two_sided and x.side == 0 else (y, x) if two_sided else sorted((x, y), key=lambda o: o.id)
                    best.add(emd_exact(x, y, scale), a.id, b.id)
        j = (j + 1) % len(names)
    counts["most_calls"] = max([s.calls for s in streams], default=0)
    return best.rows(), dict(counts)


def emd_reduced_first(items: list[Item], k: int, scale: int, h: int = 1, two_sided: bool = False) -> tuple[list[tuple[float, int, int]], dict[str, int]]:
    """The baseline: EMD on the cut tree for every pair, then exact distances in that order."""
    _, rows = dimensions(items, "edge", h, scale)
    order = sorted((sum(abs(rows[p].get(v, 0.0) - rows[q].get(v, 0.0)) for v in rows[p].keys() | rows[q].keys()), p, q) for p in range(len(items)) for q in range(p + 1, len(items)) if not (two_sided and items[p].side == items[q].side))
    best, exact = Best(k), 0
    for d, p, q in order:
        if d > best.kth + 1e-12:
            break
        exact += 1
        a, b = sorted((items[p], items[q]), key=lambda x: x.side if two_sided else x.id)
        best.add(emd_exact(a, b, scale), a.id, b.id)
    return best.rows(), {"bounds": len(order), "emd": exact, "full_l1": 0, "calls": 0, "new": len(order), "most_calls": 0}


class Descent:
    """Lower bounds of the average distance by total cost, level by level."""

    def __init__(self, items: list[Item], scale: int) -> None:
        self.items, self.scale = items, scale
        self.groups: list[dict[str, set[str]]] = []
        for x in items:
            children: dict[str, set[str]] = defaultdict(set)
            below: Counter = Counter()
            for v, (_, _, c, _) in x.nodes.items():
                children[x.parent[v]].add(v)
                below[x.parent[v]] += c
            for v, c in [("root", x.n), *((v, t[2]) for v, t in x.nodes.items())]:
                if below[v] < c:
                    children[v].add("self")
            self.groups.append(children)

    def tuple_at(self, i: int, v: str) -> tuple[int, int]:
        x = self.items[i]
        return (x.n, x.s) if v == "root" else x.nodes[v][2:4]

    def case(self, i: int, j: int, v: str) -> tuple[str, int]:
        (n, w), (m, u) = self.tuple_at(i, v), self.tuple_at(j, v)
        g, h = self.groups[i][v], self.groups[j][v]
        if len(g) == len(h) == 1:
            return ("1a", 0) if g == h else ("1b", m * w + n * u)
        if len(g) == 1:
            return "3", w
        if len(h) == 1:
            return "3", u
        return "2", w + u

    def total(self, i: int, j: int, level: int, height: int) -> tuple[int, bool]:
        """(total, exact) with the across costs of all shared nodes above ``level`` exact."""
        x, y = self.items[i], self.items[j]
        shared = [(v, t) for v, t in x.nodes.items() if v in y.nodes]
        out, exact = y.n * x.s + x.n * y.s, True
        for v, (lv, w, c, d) in shared:
            if lv <= level:
                out -= 2 * w * c * y.nodes[v][2]
            if lv == level:
                case, bound = self.case(i, j, v)
                m, u = y.nodes[v][2:4]
                out += bound - (m * d + c * u)
                only_self = case == "1a" and self.groups[i][v] == {"self"}
                exact &= case == "1b" or only_self
        return out, exact


def avg_best_first(items: list[Item], k: int, scale: int, height: int, refine: str = "stepwise", order: str = "bfs", two_sided: bool = False) -> tuple[list[tuple[float, int, int]], dict[str, int]]:
    """Best pair first over the ordered list pairs; ``stepwise`` descends a level at a time, ``complete`` at once.

    With two sides a pair of one side only makes its successors.

    ``dfs`` goes to the deepest level of a popped pair before another pair is looked at, as long as its bound is below
    the kth distance. A pair's successors are made at its first pop only.
    """
    items = sorted(items, key=lambda x: (x.side, x.id))
    dsc = Descent(items, scale)
    lists: dict[tuple[str, str], list[int]] = defaultdict(list)
    for i, x in enumerate(items):
        g = dsc.groups[i]["root"]
        lists[("single", next(iter(g))) if len(g) == 1 else ("many", str(x.n))].append(i)
    mean = lambda i: items[i].s / items[i].n
    for name, members in lists.items():
        members.sort(key=lambda i: (mean(i), items[i].id) if name[0] == "single" else (items[i].s, items[i].id))
    names = sorted(lists)
    heap: list = []
    queued: set = set()

    def push(a: int, b: int, p: int, q: int) -> None:
        la, lb = lists[names[a]], lists[names[b]]
        if a == b and q <= p:
            q = p + 1
        if p < len(la) and q < len(lb) and (a, b, p, q) not in queued:
            queued.add((a, b, p, q))
            i, j = la[p], lb[q]
            case, total = dsc.case(i, j, "root")
            exact = case == "1b" or (case == "1a" and dsc.groups[i]["root"] == {"self"})
            heapq.heappush(heap, (total / (items[i].n * items[j].n * scale), min(i, j), max(i, j), exact, 0, (a, b, p, q)))

    for a in range(len(names)):
        for b in range(a, len(names)):
            push(a, b, 0, 0)
    best = Best(k)
    counts = Counter(pops=0, examined=0, complete=0)
    while heap and k:
        d, i, j, exact, level, place = heapq.heappop(heap)
        if d > best.kth:
            break
        counts["pops"] += 1
        if place is not None:
            a, b, p, q = place
            push(a, b, p + 1, q)
            push(a, b, p, q + 1)
            if two_sided and items[i].side == items[j].side:
                continue
            counts["examined"] += 1
        while not exact:
            if refine == "complete":
                d, exact = avg_exact(items[i], items[j], scale), True
            else:
                level += 1
                total, exact = dsc.total(i, j, level, height)
                d, exact = total / (items[i].n * items[j].n * scale), exact or level >= height
            if order == "bfs" or d > best.kth:
                break
        if exact:
            counts["complete"] += 1
            if level or refine == "complete":
                d = avg_exact(items[i], items[j], scale)
            best.add(d, items[i].id, items[j].id)
        else:
            heapq.heappush(heap, (d, i, j, exact, level, None))
    return best.rows(), dict(counts)


def mindist_lists(items: list[dict[str, int]], ids: list[int], parent: dict[str, tuple[str | None, int]], order: list[str], k: int, length: int, scale: int) -> list[tuple[float, int, int]]:
    """Bottom-up lists: at each node the nearest objects and the best pairs. ``order``: nodes, children first."""
    near: dict[str, dict[int, int]] = defaultdict(dict)
    pairs: dict[str, dict[tuple[int, int], int]] = defaultdict(dict)
    for obj, terms in zip(ids, items, strict=True):
        for t in terms:
            near[t][obj] = 0
    for v in order:
        kept = sorted(near[v].items(), key=lambda x: (x[1], x[0]))[:length]
        mine = pairs[v]
        for x, (a, da) in enumerate(kept):
            for b, db in kept[x + 1 :]:
                key = (min(a, b), max(a, b))
                mine[key] = min(mine.get(key, da + db), da + db)
        cut = sorted(mine.items(), key=lambda x: (x[1], x[0]))[:k]
        up, edge = parent[v]
        if up is None:
            return [(d / scale, a, b) for (a, b), d in cut]
        for obj, d in kept:
            near[up][obj] = min(near[up].get(obj, d + edge), d + edge)
        for key, d in cut:
            pairs[up][key] = min(pairs[up].get(key, d), d)
        del near[v], pairs[v]
    return []
