"""Canonical growth: each simple path is made exactly once, from its heaviest edge outwards.

Edges have a total order (eid). Taking away the later of a path's two end edges again and again ends at its first edge;
read backwards, a path grows at the right by edges later than its left end edge and at the left by edges later than its
right end edge. All later edges are no heavier than the heavier end edge h, so a path of i edges ends with at most
w + (length - i) * h; with a lower bound tau on the k-th answer everything below is cut inside the join.
"""

from __future__ import annotations

from pyspark.sql import functions as F

from ..graph.model import Graph
from ..runtime import keep
from . import expand
from .result import PathResult

#: Levels that one plan holds before the frontier is written.
LEVELS_PER_PLAN = 3


def beam(g: Graph, length: int, k: int, width: int = 200, agg: str = "sum") -> list:
    """The best of `width` paths kept per level: (nodes, w) rows, a lower bound for exact runs.

    A level holds at most max(width, 4 k) paths, so on large graphs these are broadcast and the edges are only scanned.
    """
    edges = g.edges.where(F.col("eid") < max(width, 4 * k))
    paths = expand.start_paths(g, agg, edges)
    for level in range(2, length + 1):
        grown = expand.deduplicated(expand.extend_both(paths, g, "none", agg, few=True), g.directed)
        paths = grown.orderBy(F.desc("w"), "nodes").limit(max(width, 4 * k))
        if level % LEVELS_PER_PLAN == 0:
            paths = keep(paths, "beam")
    return expand.top(paths, k, g.directed, agg).collect()  # k rows


def beam_search(g: Graph, length: int, k: int = 1, width: int = 200, agg: str = "sum") -> PathResult:
    rows = beam(g, length, k, width, agg)
    return PathResult(expand.answers(g.edges.sparkSession, rows, length, agg), {"exact": False, "width": width}, labels=g.labels)


def _band_limits(g: Graph, bands: int) -> list[int]:
    """eids that cut the edges into bands, each four times the one before."""
    if bands <= 1:
        return [0, g.n_edges]
    first = max(1, g.n_edges // sum(4**i for i in range(bands)))
    out = [0]
    for i in range(bands - 1):
        out.append(min(g.n_edges, out[-1] + first * 4**i))
    return [*dict.fromkeys([*out, g.n_edges])]


def canonical_growth(g: Graph, length: int, k: int = 1, agg: str = "sum", seed: int | str | None = "beam", bands: int = 1, width: int = 200, counters: bool = False) -> PathResult:
    """Exact top-k. seed: 'beam', a known lower bound on the k-th weight, or None; bands: slices of start edges.

    counters: also counts joins (paths made at any length, which are all different), by jobs of their own.
    """
    spark = g.edges.sparkSession
    best: list = []
    if seed == "beam" and length > 1 and g.n_edges:
        best = expand.better([(r[0], r[1]) for r in beam(g, length, k, width, agg)], [], k)
    tau = best[-1][1] if len(best) >= k else (seed if isinstance(seed, int) else None)
    rest = expand.AGGREGATES[agg][1]
    slack = 1 if agg == "product" else 0  # products are rounded
    limits = _band_limits(g, bands)
    steps, joins, read = [], 0, 0
    for lo, hi in zip(limits, limits[1:]):
        edges = g.edges.where((F.col("eid") >= lo) & (F.col("eid") < hi))
        paths = expand.start_paths(g, agg, edges)
        if tau is not None:
            paths = paths.where(rest(F.col("w"), F.col("last_w"), length - 1) >= tau - slack)
        for i in range(2, length + 1):
            paths = expand.extend_both(paths, g, "strict", agg)
            joins += paths.count() if counters else 0
            if tau is not None:
                paths = paths.where(rest(F.col("w"), F.greatest("first_w", "last_w"), length - i) >= tau - slack)
            if i % LEVELS_PER_PLAN == 0 and i < length:
                paths = keep(paths, "growth")
        best = expand.better(best, [(r[0], r[1]) for r in expand.top(paths, k, g.directed, agg).collect()], k)  # k rows
        tau = best[-1][1] if len(best) >= k else tau
        steps.append((len(steps), length, float(tau) if tau is not None else None, hi, joins, joins, 0, 0))
        read = hi
        if tau is not None and hi < g.n_edges and agg in ("sum", "mean"):
            unread = g.edges.where(F.col("eid") == hi).first()["w"]
            if length * unread < tau:
                break
    return PathResult(expand.answers(spark, best, length, agg), {"exact": True, "exhausted": len(best) < k, "bands": len(steps), "edges_read": read} | ({"joins": joins, "built": joins, "duplicates": 0} if counters else {}), steps, g.labels)
