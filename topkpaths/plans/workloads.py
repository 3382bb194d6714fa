"""Experiment workloads: time and counters by length and by k, gain of the guard, quality of the heuristics on long paths,
longest lengths, access counts and threshold decay.

Every row is one run. Seconds are wall-clock time and differ from run to run, so these queries have no SQL twin; the weights
of the exact methods are also given by queries of their own that have one, and tests hold weights and counters
against plain searches.
"""

from __future__ import annotations

from collections.abc import Iterable

from pyspark.sql import DataFrame, SparkSession

from .. import bounds
from ..api import heaviest_paths
from ..graph import builders as B
from ..graph.model import Graph
from ..paths.ordered_buffers import Search
from . import measures as M
from . import sqlgen as S

RUN = "graph string, method string, length int, k int, weight bigint, seconds double, edges_read bigint, joins bigint, built bigint, duplicates bigint, accesses bigint"
QUALITY = "graph string, length int, method string, weight bigint, bound bigint, rho double, optimum bigint, true_ratio double, seconds double"
DECAY = "graph string, method string, step long, level int, theta double, edges_read long, joins long, built long, duplicates long, held long"
#: name -> (method, options): the exact methods and the guards compared with each other.
EXACT = {
    "dp": ("avoidance_dp", {"form": "visited"}),
    "rank scan": ("edge_rank_scan", {"first": 512}),
    "buffers none": ("ordered_buffers", {"guard": "none"}),
    "buffers ends": ("ordered_buffers", {"guard": "ends"}),
    "buffers strict": ("ordered_buffers", {"guard": "strict"}),
    "buffers lazy": ("ordered_buffers", {"access": "lazy"}),
    "growth": ("canonical_growth", {}),
}
COUNTED = ("rank scan", "buffers none", "buffers ends", "buffers strict", "buffers lazy", "growth")


def _run(graph: str, g: Graph, label: str, length: int, k: int, **more) -> tuple:
    method, options = EXACT[label]
    r, sec = M.timed(lambda: heaviest_paths(g, length, k, method, **options, **more))
    rows = r.paths.orderBy("rank").collect()  # k rows
    last = rows[-1]["weight"] if rows else None
    return (graph, label, length, k, last, round(sec, 3), *[r.summary.get(c) for c in ("edges_read", "joins", "built", "duplicates", "accesses")])


def by_length(spark: SparkSession, graph: str, g: Graph, plan: dict[str, Iterable[int]]) -> DataFrame:
    """One answer, growing length; plan: method label -> lengths."""
    return spark.createDataFrame([_run(graph, g, label, n, 1) for label, lengths in plan.items() for n in lengths], RUN)


def by_k(spark: SparkSession, graph: str, g: Graph, length: int, plan: dict[str, Iterable[int]]) -> DataFrame:
    """Fixed length, growing number of answers; plan: method label -> ks. weight: that of the k-th answer."""
    return spark.createDataFrame([_run(graph, g, label, length, k) for label, ks in plan.items() for k in ks], RUN)


def access_counts(spark: SparkSession, graph: str, g: Graph, lengths: Iterable[int], labels: Iterable[str] = COUNTED) -> DataFrame:
    """All counters of every method; the counting is part of the seconds."""
    return spark.createDataFrame([_run(graph, g, label, n, 1, counters=True) for n in lengths for label in labels], RUN)


def threshold_decay(spark: SparkSession, graph: str, g: Graph, length: int, k: int = 1) -> DataFrame:
    """How the bounds fall from step to step."""
    rows = []
    for label in ("rank scan", "buffers ends", "buffers lazy"):
        method, options = EXACT[label]
        steps = heaviest_paths(g, length, k, method, **options, **({"block": 64} if label != "rank scan" else {})).steps
        rows += [(graph, label, *s) for s in steps]
    return spark.createDataFrame(rows, DECAY)


def long_paths(spark: SparkSession, graph: str, g: Graph, lengths: Iterable[int], budget: int, exact: int = 4) -> DataFrame:
    """Budgeted search and greedy against the best split of the optimal weights up to `exact`; up to there also against the optimum."""
    best, rows = M.optimal_weights(g, exact), []
    for n in lengths:
        limit = bounds.best_split_bound(best, n)
        for method, options in (("budgeted", {"budget": budget}), ("greedy", {})):
            r, sec = M.timed(lambda m=method, o=options: heaviest_paths(g, n, 1, m, **o))
            top = r.paths.first()
            weight = top and top["weight"]
            rho, true = bounds.rho(weight, limit), bounds.rho(weight, best.get(n))
            rows.append((graph, n, method, weight, int(limit), rho and round(rho, 4), best.get(n), true and round(true, 4), round(sec, 3)))
    return spark.createDataFrame(rows, QUALITY)


def longest(spark: SparkSession, graphs: dict[str, Graph], max_paths: int, upto: int, seconds: float) -> DataFrame:
    """(graph, method, longest, held, why): the longest length each guard solves within a number of paths held, and why it ended there."""
    rows = []
    for name, g in graphs.items():
        for label, options in (("buffers none", {"guard": "none"}), ("buffers ends", {"guard": "ends"}), ("buffers strict", {"guard": "strict"})):
            last, why = (1, 0), "longest tried"
            for n in range(2, upto + 1):
                run = Search(g, n, budget=max_paths, **options)
                _, sec = M.timed(lambda: run.more(1))
                if run.stopped:
                    why = "paths held"
                    break
                last = (n, run.held)
                if sec > seconds:
                    why = "time"
                    break
            rows.append((name, label, *last, why))
    return spark.createDataFrame(rows, "graph string, method string, longest int, held bigint, why string")


def _on(graph: str, make, *args):
    return lambda s, d: make(s, graph, B.stand_in(s, d, graph), *args)


def _best(graph: str, lengths: Iterable[int], labels: Iterable[str]):
    """(method, length, weight) of exact methods, and the SQL that gives the same; a length without a path has no row."""

    def run(s, d):
        g = B.stand_in(s, d, graph)
        rows = [(label, n, _run(graph, g, label, n, 1)[4]) for label in labels for n in lengths]
        return s.createDataFrame([r for r in rows if r[2] is not None], "method string, length int, weight bigint")

    each = " union all ".join(f"select {n}::int as length, weight from ({S.path_sql(graph, n, 1)})" for n in lengths)
    return run, f"select method, length, weight from (values {', '.join(f"('{x}')" for x in labels)}) m(method), ({each})"


_LONG = (10, 25, 40, 60, 80, 100)
QUERIES = {
    "e_time_by_length_topic": _on("topic", by_length, {"dp": (2, 3), "rank scan": (2, 3), "buffers none": (2, 3), "buffers ends": (2, 3), "growth": (2, 3, 4, 5)}),
    "e_time_by_length_words": _on("words", by_length, {"dp": (2,), "rank scan": (2, 3), "buffers none": (2, 3), "buffers ends": (2, 3), "buffers lazy": (2, 3), "growth": (2, 3)}),
    "e_time_by_length_baskets": _on("baskets", by_length, {"dp": (2, 3), "rank scan": (2, 3), "buffers none": (2, 3), "buffers ends": (2, 3), "growth": (2, 3, 4, 8, 12, 16, 20)}),
    "e_time_by_length_road": _on("road", by_length, {"dp": (2,), "rank scan": (2, 4), "buffers none": (2, 4), "buffers ends": (2, 4), "growth": (2, 4, 8, 12, 16)}),
    "e_time_by_k_topic": _on("topic", by_k, 3, {"rank scan": (1, 100), "buffers ends": (1, 100), "growth": (1, 10, 25, 50, 75, 100)}),
    "e_time_by_k_baskets": _on("baskets", by_k, 4, {"rank scan": (1, 10, 50, 100), "buffers ends": (1, 10, 50, 100), "growth": (1, 10, 50, 100)}),
    "e_time_by_k_road": _on("road", by_k, 10, {"growth": (1, 10, 25, 50, 75, 100)}),
    "e_guard_by_length_topic": _on("topic", by_length, {"buffers none": (2, 3), "buffers ends": (2, 3), "buffers strict": (2, 3)}),
    "e_guard_by_length_baskets": _on("baskets", by_length, {"buffers none": (2, 3, 4), "buffers ends": (2, 3, 4), "buffers strict": (2, 3, 4)}),
    "e_guard_by_length_road": _on("road", by_length, {"buffers none": (2, 3, 4), "buffers ends": (2, 3, 4), "buffers strict": (2, 3, 4)}),
    "e_dp_nation": _on("nation", by_length, {"dp": (2, 3, 4), "growth": (2, 3, 4)}),
    "e_long_paths_topic": _on("topic", long_paths, (3, 10, 25, 40, 63), 100_000, 3),
    "e_long_paths_words": _on("words", long_paths, (2, *_LONG), 100_000, 2),
    "e_long_paths_road": _on("road", long_paths, (4, *_LONG), 100_000, 4),
    "e_rho_by_length": lambda s, d: M.rho_table(s, B.stand_in(s, d, "topic"), (6, 10, 15, 25, 40, 63), (100_000,)),
    "e_rho_by_budget": lambda s, d: M.rho_table(s, B.stand_in(s, d, "topic"), (25,), (10, 100, 1000, 10_000, 100_000, 1_000_000)),
    "e_access_counts_topic": _on("topic", access_counts, (3,)),
    "e_access_counts_baskets": _on("baskets", access_counts, (2, 3)),
    "e_threshold_decay": _on("baskets", threshold_decay, 3),
    "e_read_paths_topic": lambda s, d: heaviest_paths(B.stand_in(s, d, "topic"), 5, 1).named(),
    "e_read_paths_words": lambda s, d: heaviest_paths(B.stand_in(s, d, "words"), 3, 1).named(),
    "e_longest_length": lambda s, d: longest(s, {n: B.stand_in(s, d, n) for n in ("topic", "baskets")}, 20_000, 4, 4.0),
}
ORACLES: dict = {}
for _g, _lengths, _labels in (("topic", (2, 3), ("rank scan", "buffers ends", "growth")), ("baskets", (2, 3), ("dp", "rank scan", "buffers none", "growth")), ("road", (2, 4), ("rank scan", "buffers ends", "buffers lazy", "growth"))):
    QUERIES[f"e_best_{_g}"], ORACLES[f"e_best_{_g}"] = _best(_g, _lengths, _labels)
