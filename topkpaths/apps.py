"""Ready-made uses: item sequences, routes, chains of influence, stable chains in time."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .api import heaviest_paths
from .graph import builders as B
from .graph.model import Graph, encode, graph
from .paths import expand
from .paths.canonical_growth import canonical_growth
from .paths.layered import layered_paths
from .paths.reductions import lightest_paths
from .paths.result import PathResult
from .runtime import keep


def recommend_sequences(sessions: DataFrame, good: DataFrame, length: int, k: int = 1, min_weight: float = 0.1, **options) -> PathResult:
    """Sequences of good items that are often used together; good: (item)."""
    pairs = B.cooccurrence(sessions.join(good, "item", "left_semi"), "dice", min_weight)
    edges, ids = encode(keep(pairs, "pairs"), "a", "b")
    return heaviest_paths(graph(edges.select("src", "dst", "w"), labels=ids), length, k, **options)


def plan_routes(distances: DataFrame, length: int, k: int = 1) -> PathResult:
    """The shortest trips through length + 1 places; distances: (src, dst, dist)."""
    # of parallel ways the shorter: negated, the heaviest
    least = distances.groupBy(F.least("src", "dst").alias("src"), F.greatest("src", "dst").alias("dst")).agg(F.min("dist").alias("dist"))
    return lightest_paths(graph(least.select("src", "dst", F.col("dist").cast("double").alias("w"))), length, k)


def flow_chains(moves: DataFrame, length: int, k: int = 1, **options) -> PathResult:
    """Strong chains of influence; moves: (frm, to)."""
    edges, ids = encode(keep(B.flow(moves), "flow"), "a", "b")
    return heaviest_paths(graph(edges.select("src", "dst", "w"), labels=ids), length, k, **options)


def stable_chains(layers: DataFrame, k: int = 1, steps: int | None = None) -> PathResult:
    """Heavy chains through layers in time; layers: (layer, src, dst, w)."""
    return layered_paths(layers, k, "bfs", steps)


def heaviest_with_ends(g: Graph, halves: DataFrame, length: int, k: int) -> DataFrame:
    """(rank, nodes, length, weight) of the k paths with the largest sum of edge weights and of the two end nodes' scores; halves: (id, half), none negative.

    The k' heaviest paths by edges alone are found for growing k' until no path further down can reach the k-th sum.
    """
    most = halves.agg(F.max("half")).first()[0] or 0
    wanted = 4 * k
    while True:
        rows = canonical_growth(g, length, wanted).paths
        x, y = halves.toDF("x", "hx"), halves.toDF("y", "hy")
        ends = rows.select("nodes", "weight", F.element_at("nodes", 1).alias("x"), F.element_at("nodes", -1).alias("y"))
        best = ends.join(x, "x", "left").join(y, "y", "left").select("nodes", (F.col("weight") + F.coalesce("hx", F.lit(0)) + F.coalesce("hy", F.lit(0))).alias("w"))
        top = expand.top(best, k, True).collect()  # k rows
        found = rows.agg(F.count("*").alias("n"), F.min("weight").alias("low")).first()
        if found["n"] < wanted or (len(top) == k and found["low"] + 2 * most < top[-1]["w"]):
            return expand.answers(g.edges.sparkSession, top, length)
        wanted *= 4
