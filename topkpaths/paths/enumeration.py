"""Exhaustive search: all simple paths of a length, by joins that drop cycles at once."""

from __future__ import annotations

from ..graph.model import Graph
from . import expand
from .result import PathResult


def enumerate_paths(g: Graph, length: int, k: int = 1, agg: str = "sum") -> PathResult:
    """Grows every path at its right end only, from both directions of each edge, and keeps one orientation."""
    spark = g.edges.sparkSession
    paths = expand.start_paths(g, agg)
    if not g.directed:
        paths = expand.both_ways(paths)
    for _ in range(length - 1):
        paths = expand.extend_right(paths, g, g.arcs(), "none", agg)
    if not g.directed:
        paths = paths.where("element_at(nodes, 1) < element_at(nodes, -1)")
    rows = expand.top(paths, k, g.directed, agg).collect()  # k rows
    return PathResult(expand.answers(spark, rows, length, agg), {"exact": True, "exhausted": len(rows) < k}, labels=g.labels)
