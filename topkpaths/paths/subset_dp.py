"""Dynamic programs over node sets: a state is an end node with the set of nodes to avoid, or visited so far."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ..graph.model import Graph
from ..runtime import keep
from . import expand
from .result import PathResult


def _best(paths: DataFrame, key: list[str], k: int) -> DataFrame:
    """The k best weights a state, ties included, so that the order of ties can be settled at the end."""
    rank = F.rank().over(Window.partitionBy(*key).orderBy(F.desc("w")))
    return paths.withColumn("rk", rank).where(F.col("rk") <= k).drop("rk")


def _finish(g: Graph, paths: DataFrame, length: int, k: int, states: int) -> PathResult:
    if not g.directed:  # both directions of each path were built
        paths = paths.where("element_at(nodes, 1) < element_at(nodes, -1)")
    rows = expand.top(paths, k, g.directed).collect()  # k rows
    return PathResult(expand.answers(g.edges.sparkSession, rows, length), {"exact": True, "states": states, "exhausted": len(rows) < k}, labels=g.labels)


def _twins(k: int, g: Graph) -> int:
    """Each undirected path is met from both ends, so twice as many rows are kept."""
    return k if g.directed else 2 * k


def avoidance_dp(g: Graph, length: int, k: int = 1, form: str = "avoid") -> PathResult:
    """The best path of l edges into an end node that avoids a set, from the best of l - 1 edges into its neighbours.

    form 'avoid': states are listed from the target down, then filled upwards; 'visited': the mirror image, bottom-up
    over (end, visited set).
    """
    return _avoid(g, length, k) if form == "avoid" else _visited(g, length, k)


def _avoid(g: Graph, length: int, k: int) -> PathResult:
    into = g.arcs(inward=True)  # head: the end node, tail: where the edge comes from
    nodes = g.edges.select(F.col("src").alias("end")).union(g.edges.select(F.col("dst"))).distinct()
    states = {length: keep(nodes.select("end", F.array().cast("array<bigint>").alias("avoid")), "states")}
    total = 0
    for i in range(length, 1, -1):  # down: which states are needed
        s, a = states[i].alias("s"), g.side(into).alias("a")
        on = (F.col("s.end") == F.col("a.head")) & ~F.array_contains("s.avoid", F.col("a.tail"))
        nxt = s.join(a, on).select(F.col("a.tail").alias("end"), F.array_sort(F.concat("s.avoid", F.array("s.end"))).alias("avoid")).distinct()
        states[i - 1] = keep(nxt, "states")
        total += states[i - 1].count()
    s, a = states[1].alias("s"), g.side(into).alias("a")
    free = (F.col("s.end") == F.col("a.head")) & ~F.array_contains("s.avoid", F.col("a.tail"))
    value = s.join(a, free).select("s.end", "s.avoid", F.array("a.tail", "s.end").alias("nodes"), F.col("a.w").alias("w"))
    wide = _twins(k, g)
    value = keep(_best(value, ["end", "avoid"], wide), "values")
    for i in range(2, length + 1):  # up: the best of each state
        s, a, v = states[i].alias("s"), g.side(into).alias("a"), value.alias("v")
        step = s.join(a, (F.col("s.end") == F.col("a.head")) & ~F.array_contains("s.avoid", F.col("a.tail"))).select(
            "s.end", "s.avoid", F.col("a.tail").alias("via"), F.array_sort(F.concat("s.avoid", F.array("s.end"))).alias("wider"), F.col("a.w").alias("aw")).alias("t")
        grown = step.join(v, (F.col("t.via") == F.col("v.end")) & (F.col("t.wider") == F.col("v.avoid"))).select("t.end", "t.avoid", F.concat("v.nodes", F.array("t.end")).alias("nodes"), (F.col("v.w") + F.col("t.aw")).alias("w"))
        value = keep(_best(grown, ["end", "avoid"], wide), "values")
    return _finish(g, value, length, k, total)


def _visited(g: Graph, length: int, k: int) -> PathResult:
    arcs, wide, total = g.arcs(), _twins(k, g), 0
    value = arcs.select(F.col("tail").alias("end"), F.array_sort(F.array("head", "tail")).alias("seen"), F.array("head", "tail").alias("nodes"), "w")
    for _ in range(2, length + 1):
        v, a = value.alias("v"), g.side(arcs).alias("a")
        on = (F.col("v.end") == F.col("a.head")) & ~F.array_contains("v.seen", F.col("a.tail"))
        grown = v.join(a, on).select(F.col("a.tail").alias("end"), F.array_sort(F.concat("v.seen", F.array("a.tail"))).alias("seen"), F.concat("v.nodes", F.array("a.tail")).alias("nodes"), (F.col("v.w") + F.col("a.w")).alias("w"))
        value = keep(_best(grown, ["end", "seen"], wide), "values")
        total += value.select("end", "seen").distinct().count()
    return _finish(g, value, length, k, total)


def pairwise_dp(g: Graph, length: int, k: int = 1, prune: bool = True) -> PathResult:
    """One best path per pair of end nodes and length. A heuristic: the path a longer one needs may be the second best.

    prune drops a path that even the heaviest edges could not lift to the k-th weight of a beam.
    """
    from .canonical_growth import beam

    tau = None
    if prune:
        seed = beam(g, length, k)
        tau = seed[-1]["w"] if len(seed) >= k else None
    paths = g.arcs().select(F.array("head", "tail").alias("nodes"), "w")
    for i in range(2, length + 1):
        p, a = paths.alias("p"), g.side(g.arcs()).alias("a")
        on = (F.element_at("p.nodes", -1) == F.col("a.head")) & ~F.array_contains("p.nodes", F.col("a.tail"))
        grown = p.join(a, on).select(F.concat("p.nodes", F.array("a.tail")).alias("nodes"), (F.col("p.w") + F.col("a.w")).alias("w"))
        if tau is not None:
            grown = grown.where(F.col("w") + (length - i) * g.max_w >= tau)
        best = grown.groupBy(F.element_at("nodes", 1).alias("a"), F.element_at("nodes", -1).alias("b")).agg(F.min(F.struct((-F.col("w")).alias("neg"), "nodes")).alias("m"))
        paths = keep(best.select("m.nodes", (-F.col("m.neg")).alias("w")), "pairs")
    if not g.directed:
        paths = expand.canonical(paths, False).distinct()
    rows = expand.top(paths, k, g.directed).collect()  # k rows
    return PathResult(expand.answers(g.edges.sparkSession, rows, length), {"exact": False}, labels=g.labels)
