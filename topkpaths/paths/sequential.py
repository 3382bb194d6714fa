"""The methods one step at a time, in memory: worked examples, exact counters and lazy access. For tiny graphs only."""

from __future__ import annotations

import heapq
from collections import defaultdict

from .. import bounds

#: Edges up to which these run.
MAX_EDGES = 5000


class Small:
    """An undirected graph in memory: edges from the heaviest on, and sorted adjacency."""

    def __init__(self, edges, limit: int = MAX_EDGES):
        rows = sorted(((int(w), min(a, b), max(a, b)) for a, b, w in edges), key=lambda e: (-e[0], e[1], e[2]))
        if len(rows) > limit:
            raise ValueError(f"more than {limit} edges")
        self.edges = [(a, b, w, i) for i, (w, a, b) in enumerate(rows)]
        self.next = defaultdict(list)
        for a, b, w, i in self.edges:
            self.next[a].append((w, b, i))
            self.next[b].append((w, a, i))
        self.top = self.edges[0][2] if self.edges else 0

    def __len__(self) -> int:
        return len(self.edges)

    def edge(self, i: int) -> tuple[int, int, int, int]:
        return self.edges[i]

    def steps(self, node: int) -> list[tuple[int, int, int]]:
        """(w, node, place) of the edges at a node."""
        return self.next[node]


class Ranked:
    """The same over the arrays of a pulled graph: a node's steps become Python rows when they are asked for."""

    def __init__(self, arrays):
        self.arrays, self.top = arrays, int(arrays.w[0]) if len(arrays) else 0

    def __len__(self) -> int:
        return len(self.arrays)

    def edge(self, i: int) -> tuple[int, int, int, int]:
        return (*self.arrays.edges(i, i + 1)[0], i)

    def steps(self, node: int) -> list[tuple[int, int, int]]:
        return [(w, t, i) for w, i, t in self.arrays.steps(node)]


def canonical(nodes: tuple) -> tuple:
    return nodes if nodes[0] < nodes[-1] else nodes[::-1]


def rank_scan(edges, length: int, k: int = 1, exact_ties: bool = False) -> dict:
    """Reads one edge at a time and joins it with all edges read; stops at the threshold."""
    g = Small(edges)
    seen = defaultdict(list)
    best: list = []
    steps, joins, built = [], 0, 0
    for d, (a, b, w, _) in enumerate(g.edges, 1):
        seen[a].append((w, b))
        seen[b].append((w, a))
        found = set()
        for left in range(length):  # edges before the new one
            for x, y in ((a, b), (b, a)):
                fronts = [((x, y), w)]
                for _ in range(length - 1 - left):
                    fronts = [(n + (t,), v + u) for n, v in fronts for u, t in seen[n[-1]] if t not in n]
                    joins += len(fronts)
                for _ in range(left):
                    fronts = [((t,) + n, v + u) for n, v in fronts for u, t in seen[n[0]] if t not in n]
                    joins += len(fronts)
                found |= {(canonical(n), v) for n, v in fronts}
        built += len(found)
        best = sorted({*best, *found}, key=lambda r: (-r[1], r[0]))[:k]
        theta = bounds.rank_scan_bound(w, g.top, length)
        steps.append((d, length, float(theta), d, joins, built, 0, len(best)))
        if len(best) == k and (best[-1][1] > theta if exact_ties else best[-1][1] >= theta):
            break
    return {"paths": best, "edges_read": len(steps), "joins": joins, "built": built, "steps": steps}


def buffers(edges, length: int, k: int = 1, guard: str = "ends", lazy: bool = False, budget: int | None = None, ends: str = "both", trace: bool = True) -> dict:
    """Demand-driven ordered buffers: one release at a time. lazy: extensions come one by one, heaviest first.

    ends='one' (an ablation) grows each direction of a path at its last node only. Guards don't apply, and a path must
    wait for its lighter beginning, so the bound of length 2 falls more slowly. edges: rows, or a Ranked graph; trace: whether to note each step.
    """
    one = ends == "one"
    guard = "none" if one else guard
    g = edges if isinstance(edges, Ranked) else Small(edges)
    heap = {i: [] for i in range(2, length + 1)}  # (-w, nodes, first, last, peak, first eid, last eid)
    have = {i: set() for i in range(2, length + 1)}
    theta = {i: float(i * g.top) for i in range(2, length + 1)}
    count = defaultdict(int)
    pending: dict[int, list] = {i: [] for i in range(2, length + 1)}  # lazy: (-best next weight, path, cursors)
    read, steps, out = 0, [], []
    best_of: dict[int, int] = {}

    def allowed(w, e, far_w, far_e, peak):
        return {"none": True, "peak": w <= peak, "ends": w <= far_w, "strict": e > far_e}[guard]

    def add(level, nodes, w, first, last, peak, fe, le):
        count["joins"] += 1
        if not one and nodes[0] > nodes[-1]:
            nodes, first, last, fe, le = nodes[::-1], last, first, le, fe
        if nodes in have[level]:
            count["duplicates"] += 1
            return
        have[level].add(nodes)
        count["built"] += 1
        count["held"] += 1
        heapq.heappush(heap[level], (-w, nodes, first, last, peak, fe, le))

    def options(nodes, first, last, peak, fe, le):
        """Extensions of a path, heaviest appended edge first."""
        right = [(x, t, i, True) for x, t, i in g.steps(nodes[-1]) if t not in nodes and allowed(x, i, first, fe, peak)]
        left = [] if one else [(x, t, i, False) for x, t, i in g.steps(nodes[0]) if t not in nodes and allowed(x, i, last, le, peak)]
        return sorted(right + left, key=lambda o: (-o[0], o[2]))

    def grow(path, w, option, level):
        nodes, first, last, peak, fe, le = path
        x, t, i, right = option
        count["accesses"] += 1
        if right:
            add(level, nodes + (t,), w + x, first, x, max(peak, x), fe, i)
        else:
            add(level, (t,) + nodes, w + x, x, last, max(peak, x), i, le)

    def extend(path, w, level):
        rest = options(*path)
        if not lazy:
            for o in rest:
                grow(path, w, o, level)
        elif rest:
            heapq.heappush(pending[level], (-(w + rest[0][0]), path, w, rest, 0))

    def settle(level):
        """Lazy: makes pending extensions that could beat the buffer's top."""
        queue = pending[level]
        while queue and (not heap[level] or -queue[0][0] >= -heap[level][0][0]):
            _, path, w, rest, at = heapq.heappop(queue)
            grow(path, w, rest[at], level)
            if at + 1 < len(rest):
                heapq.heappush(queue, (-(w + rest[at + 1][0]), path, w, rest, at + 1))

    def full():
        return budget is not None and count["held"] >= budget

    def step_edge():
        nonlocal read
        if read >= len(g):
            theta[2] = bounds.NONE_LEFT
            return False
        a, b, w, i = g.edge(read)
        read += 1
        theta[2] = (w + g.top if one else bounds.after_read(w)) if read < len(g) else bounds.NONE_LEFT
        extend(((a, b), w, w, w, i, i), w, 2)
        if one:
            extend(((b, a), w, w, w, i, i), w, 2)
        return True

    def pull(level):
        """The next best path of a level, or None."""
        while True:
            settle(level)
            top = heap[level][0] if heap[level] else None
            if top is not None and -top[0] > theta[level]:
                heapq.heappop(heap[level])
                count["held"] -= 1
                best_of.setdefault(level, -top[0])
                return top
            if theta[level] == bounds.NONE_LEFT or full():
                return None
            if level == 2:
                step_edge()
            else:
                below = pull(level - 1)
                if below is None:
                    if full():
                        return None
                    theta[level] = bounds.NONE_LEFT
                else:
                    extend(below[1:], -below[0], level)
                    settle(level - 1)
                    left = -heap[level - 1][0][0] if heap[level - 1] else bounds.NONE_LEFT
                    high = max(left, theta[level - 1])
                    theta[level] = high + g.top if high != bounds.NONE_LEFT else bounds.NONE_LEFT
            if trace:
                steps.append((len(steps), level, None if theta[level] == bounds.NONE_LEFT else float(theta[level]), read, count["joins"], count["built"], count["duplicates"], count["held"]))

    while len(out) < k:
        got = pull(length) if length > 1 else None
        if got is None:
            break
        if (canonical(got[1]), -got[0]) not in out:
            out.append((canonical(got[1]), -got[0]))
    have.clear()  # pull refers to itself, so all this would wait for the garbage collector
    if length == 1:
        out = [((a, b), w) for a, b, w, _ in map(g.edge, range(min(k, len(g))))]
    return {"paths": out, "edges_read": read, **{c: count[c] for c in ("joins", "built", "duplicates", "accesses")}, "steps": steps, "held": count["held"], "buffers": heap, "best": best_of, "stopped": full() and len(out) < k}
