"""The facade: one call for every method, and a choice by size."""

from __future__ import annotations

from .graph.model import Graph
from .paths.budgeted import budgeted_search
from .paths.canonical_growth import beam_search, canonical_growth
from .paths.enumeration import enumerate_paths
from .paths.greedy import end_greedy
from .paths.ordered_buffers import ordered_buffers
from .paths.rank_join import edge_rank_scan
from .paths.reductions import lightest_paths
from .paths.result import PathResult
from .paths.subset_dp import avoidance_dp, pairwise_dp

METHODS = {
    "enumerate": enumerate_paths,
    "avoidance_dp": avoidance_dp,
    "pairwise_dp": pairwise_dp,
    "edge_rank_scan": edge_rank_scan,
    "ordered_buffers": ordered_buffers,
    "canonical_growth": canonical_growth,
    "budgeted": budgeted_search,
    "beam": beam_search,
    "greedy": end_greedy,
}


def heaviest_paths(g: Graph, length: int, k: int = 1, method: str = "auto", **options) -> PathResult:
    """The k heaviest simple paths with exactly `length` edges; fewer if there are fewer.

    'auto' is exact, unless a `budget` of paths is given: then it is the budgeted search, whose summary tells whether the
    budget sufficed.
    """
    if length < 1 or k < 1:
        raise ValueError("length and k are at least 1")
    if method == "auto":
        if "budget" in options:
            return budgeted_search(g, length, k=k, **options)
        return canonical_growth(g, length, k, **({"bands": 1 if g.small else 4} | options))
    return METHODS[method](g, length, k=k, **options)


__all__ = ["METHODS", "heaviest_paths", "lightest_paths"]
