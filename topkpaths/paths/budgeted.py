"""Budgeted search: ordered buffers within a number of paths, then greedy completion, with a worst-case ratio."""

from __future__ import annotations

import heapq
from collections.abc import Callable

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .. import bounds
from ..graph.model import Graph
from . import expand, neighbours, sequential
from .neighbours import Neighbours
from .ordered_buffers import Search
from .result import PathResult

#: Paths of a frozen buffer that completion reads at a time; ends of waiting paths that are looked up together.
TOP_ROWS, LOOK_AHEAD = 2000, 256
#: Dead ends behind one path of the buffers, and in one component, after which it waits until the others have been tried.
PATIENCE, PART_PATIENCE = 4, 1000
#: Paths up to which a search over a pulled graph runs in the driver's memory.
MEMORY_PATHS = 1_000_000


def budgeted_search(g: Graph, length: int, budget: int, k: int = 1, guard: str = "ends", block: int = 64, bound: str = "split", engine: str = "auto") -> PathResult:
    """Exact if the budget suffices; else completes the longest buffer greedily. summary: exact, j, bound, rho.

    engine 'memory': the buffers of a small undirected graph stay in the driver, a path at a time; 'tables': buffers are
    tables; 'auto': memory where edges and budget are within PULL_EDGES and MEMORY_PATHS.
    """
    if engine == "auto":
        engine = "memory" if g.n_edges <= neighbours.PULL_EDGES and budget <= MEMORY_PATHS and not g.directed else "tables"
    if length > 1 and engine == "memory":
        return _in_memory(g, length, budget, k, guard, bound)
    run = Search(g, length, guard, "drain", "plain", block, budget)
    got = run.more(k)
    if not run.stopped:
        return PathResult(got.paths, got.summary | {"exact": True, "rho": 1.0, "bound": None, "j": length}, got.steps, g.labels)
    stored = {i: _rows_of(v.table().select("nodes", "w")) for i, v in run.levels.items() if v.rows}
    stored[1] = _rows_of(expand.canonical(expand.start_paths(g), g.directed).select("nodes", "w"))
    out = _finish(g, length, k, bound, {i: [] for i in range(1, length + 1)}, stored, _known_best(run), max(stored))
    return PathResult(out.paths, out.summary | {"held": run.held}, run.steps, g.labels)


def _in_memory(g: Graph, length: int, budget: int, k: int, guard: str, bound: str) -> PathResult:
    if g.n_edges > neighbours.PULL_EDGES:
        raise ValueError(f"more than {neighbours.PULL_EDGES} edges")
    arrays = neighbours.pulled(g)
    run = sequential.buffers(sequential.Ranked(arrays), length, k, guard, budget=budget, trace=False)
    if not run["stopped"]:
        summary = {"exact": True, "rho": 1.0, "bound": None, "j": length, "held": run["held"], "exhausted": len(run["paths"]) < k, "edges_read": run["edges_read"], "joins": run["joins"], "built": run["built"], "duplicates": run["duplicates"]}
        return PathResult(expand.answers(g.edges.sparkSession, run["paths"], length), summary, labels=g.labels)
    buffers = run.pop("buffers")
    filled = max((i for i, b in buffers.items() if b), default=1)
    heaps: dict[int, list] = {1: []}
    for i in range(2, length + 1):
        heaps[i] = [(e[0], e[1]) for e in buffers.pop(i)]
        heapq.heapify(heaps[i])
    best = {i: float(w) for i, w in run["best"].items()} | {1: float(g.max_w)}
    out = _finish(g, length, k, bound, heaps, {1: _edges_of(arrays)}, best, filled)
    return PathResult(out.paths, out.summary | {"held": run["held"]}, labels=g.labels)


def _rows_of(table: DataFrame) -> Callable:
    """Reads on in a frozen buffer: the next TOP_ROWS rows (-w, nodes) behind the last one read."""

    def read(last: tuple | None) -> list:
        t = table
        if last is not None:
            w, nodes = -last[0], F.array(*[F.lit(x) for x in last[1]])
            t = t.where((F.col("w") < w) | ((F.col("w") == w) & (F.col("nodes") > nodes)))
        return [(-r["w"], tuple(r["nodes"])) for r in t.orderBy(F.desc("w"), "nodes").limit(TOP_ROWS).collect()]

    return read


def _edges_of(arrays: neighbours.Pulled) -> Callable:
    """The same over the edges of a pulled graph, which stand in this order."""
    at = 0

    def read(last: tuple | None) -> list:
        nonlocal at
        at = 0 if last is None else at
        rows = arrays.edges(at, at + TOP_ROWS)
        at += len(rows)
        return [(-w, (min(a, b), max(a, b))) for a, b, w in rows]

    return read


def _finish(g: Graph, length: int, k: int, bound: str, heaps: dict, stored: dict[int, Callable], best: dict[int, float], filled: int) -> PathResult:
    j = max(2, filled)
    known = {i: w for i, w in best.items() if i < j}
    limit = bounds.split_bound(known, length, j, g.max_w) if bound == "split" else bounds.best_split_bound(known, length)
    found = _complete(g, length, k, heaps, stored)
    rho = bounds.rho(found[0][1] if found else None, limit)
    return PathResult(expand.answers(g.edges.sparkSession, found, length), {"exact": False, "j": j, "bound": limit, "rho": rho})


def _known_best(run: Search) -> dict[int, float]:
    """Optimal weights of the lengths whose best path stands above its bound (length 1 always)."""
    out = {1: float(run.g.max_w)}
    for i, v in run.levels.items():
        t = v.table()
        top = None if t is None else t.agg(F.max("w")).first()[0]
        if top is not None:
            out[i] = float(top)
    return out


def _complete(g: Graph, length: int, k: int, heaps: dict[int, list], stored: dict[int, Callable]) -> list:
    """Pops the best path of the longest buffer, extends it at both ends without a guard, steps back at dead ends.

    heaps: (-w, nodes) by length; stored: frozen buffers still to be read, by what reads on in them. The edges themselves are the last buffer to step back to,
    so a path is found if the graph has one. After the first dead end, paths around which too few nodes can be reached are not
    extended: a crowded corner with fewer nodes than the length has very many paths and no answer. For the same reason a path of the
    buffers waits after some dead ends behind it, and so does a component if the adjacency is pulled. None is dropped: what waits
    begins anew, with twice the patience, when the others are at their end.
    """
    near, stuck = Neighbours(g), False
    patience, part_patience, edges = PATIENCE, PART_PATIENCE, stored[1]
    base = max(i for i in heaps if heaps[i] or i in stored)
    root, ends, dead = (1, ()), 0, {}  # the last path of the buffers and the dead ends behind it; dead ends by component
    waiting: dict[int, list] = {}  # (length, path) by component; edges are read again
    later: list = []  # (length, path) of the buffers
    seen: dict[int, set] = {i: set() for i in heaps}
    found: list = []
    last: dict[int, tuple] = {}  # the last row read of a frozen buffer

    def fill(i: int) -> None:
        """Reads on in the frozen buffer until the heap's best path comes before all that is unread."""
        while i in stored and not (heaps[i] and i in last and heaps[i][0] <= last[i]):
            rows = stored[i](last.get(i))
            for r in rows:
                heapq.heappush(heaps[i], r)
            if len(rows) < TOP_ROWS:
                del stored[i]
            else:
                last[i] = rows[-1]

    while len(found) < k:
        level = next((i for i in range(length, 0, -1) if heaps[i] or i in stored), None)
        if level is None:
            if not waiting and not later:
                break
            if waiting:
                again, part_patience, stored[1] = [x for part in waiting.values() for x in part], 2 * part_patience, edges
                last.pop(1, None)
            else:
                again, later, patience = later, [], 2 * patience
            for i, path in again:
                heapq.heappush(heaps[i], path)
                seen[i].discard(path[1])
            ends, dead, waiting = 0, {}, {}
            continue
        fill(level)
        if not heaps[level]:
            continue
        if near.whole is None:
            near.prepare(n for _, n in heapq.nsmallest(LOOK_AHEAD, heaps[level]))
        w, nodes = heapq.heappop(heaps[level])
        if nodes in seen[level]:
            continue
        part = near.whole.component(nodes[0]) if stuck and near.whole is not None and level < length else None
        if part is not None and near.whole.sizes[part] <= length:
            continue
        if part in waiting:
            if level > 1:
                waiting[part].append((level, (w, nodes)))
            continue
        seen[level].add(nodes)
        if level == length:
            found.append((nodes, -w))
            continue
        ways = [] if stuck and not near.room(nodes, length - level) else [(x, (*nodes, t)) for x, _, t in near.after(nodes)] + [(x, (t, *nodes)) for x, _, t in near.before(nodes)]
        for x, path in ways:
            heapq.heappush(heaps[level + 1], (w - x, near.turned(path)))
        if level <= base:
            root, ends = (level, (w, nodes)), 0
        if ways:
            continue
        stuck, ends, dead[part] = True, ends + 1, dead.get(part, 0) + 1
        full = part is not None and dead[part] >= part_patience
        if (full or ends >= patience) and level > base:
            (waiting.setdefault(part, []) if full else later).append(root)
            for i in range(base + 1, length):
                heaps[i], seen[i] = [], set()
        elif full:
            waiting.setdefault(part, [])
    return found
