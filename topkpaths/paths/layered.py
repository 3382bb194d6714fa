"""Paths through layers in time: breadth-first, depth-first and threshold forms."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ..runtime import keep
from . import expand
from .result import PathResult


def layered_paths(edges: DataFrame, k: int = 1, method: str = "bfs", layers: int | None = None, first: int = 256) -> PathResult:
    """The k heaviest paths over the first `layers` steps; edges: (layer, src, dst, w), each into the next layer.

    bfs: the k best per node and layer (acyclic, so no set is needed). dfs: paths pruned by the best possible rest from their last node.
    ta: heaviest edges first, in growing prefixes, until no unread edge can matter.
    """
    spark = edges.sparkSession
    e = keep(edges.select("layer", "src", "dst", "w"), "layers")
    tops = {r["layer"]: r["m"] for r in e.groupBy("layer").agg(F.max("w").alias("m")).collect()}  # one row a layer
    n = layers or len(tops)
    run = {"bfs": _bfs, "dfs": _dfs, "ta": _ta}[method]
    rows, summary = run(e, n, k, tops, first)
    return PathResult(expand.answers(spark, rows, n), summary)


def _step(paths: DataFrame, e: DataFrame, layer: int) -> DataFrame:
    p, a = paths.alias("p"), e.where(F.col("layer") == layer).alias("a")
    return p.join(a, F.element_at("p.nodes", -1) == F.col("a.src")).select(F.concat("p.nodes", F.array("a.dst")).alias("nodes"), (F.col("p.w") + F.col("a.w")).alias("w"))


def _first(e: DataFrame) -> DataFrame:
    return e.where("layer = 0").select(F.array("src", "dst").alias("nodes"), "w")


def _bfs(e, n, k, tops, _):
    paths = _first(e)
    per_node = Window.partitionBy(F.element_at("nodes", -1)).orderBy(F.desc("w"), "nodes")
    for layer in range(1, n):
        paths = _step(paths, e, layer).withColumn("rk", F.row_number().over(per_node)).where(F.col("rk") <= k).drop("rk")
        if layer % 5 == 0:
            paths = keep(paths, "layer")
    return expand.top(paths, k, True).collect(), {"exact": True}  # k rows


def _rests(e, n):
    """Layer -> (node, rest): the heaviest way on from each node whose next edge is in that layer and that reaches the last."""
    out = {}
    for layer in range(n - 1, 0, -1):
        on = e.where(F.col("layer") == layer)
        if layer < n - 1:
            on = on.join(out[layer + 1].withColumnRenamed("node", "dst"), "dst").withColumn("w", F.col("w") + F.col("rest"))
        out[layer] = keep(on.groupBy(F.col("src").alias("node")).agg(F.max("w").alias("rest")), "rest")
    return out


def _dfs(e, n, k, tops, _):
    rests, paths = _rests(e, n), _first(e)
    for layer in range(n):
        paths = _step(paths, e, layer) if layer else paths
        most = F.col("w")
        if layer < n - 1:  # a path that cannot reach the last layer goes
            paths = paths.join(rests[layer + 1], F.element_at("nodes", -1) == F.col("node"))
            most = most + F.col("rest")
        # each of these leads to a path as heavy as its bound, so k of them leave no better one out, ties included
        paths = paths.orderBy(most.desc(), "nodes").limit(k).select("nodes", "w")
        if layer % 4 == 3:
            paths = keep(paths, "depth")
    return expand.top(paths, k, True).collect(), {"exact": True}  # k rows


def _ta(e, n, k, tops, first):
    ranked = keep(e.where(F.col("layer") < n).withColumn("rk", F.row_number().over(Window.partitionBy("layer").orderBy(F.desc("w"), "src", "dst"))), "ranked")
    most = ranked.agg(F.max("rk")).first()[0] or 0
    depth, rounds = first, 0
    while True:
        rounds += 1
        part = keep(ranked.where(F.col("rk") <= depth), "prefix")
        rows, _ = _bfs(part, n, k, tops, first)
        unread = {r["layer"]: r["m"] for r in ranked.where(F.col("rk") > depth).groupBy("layer").agg(F.max("w").alias("m")).collect()}
        limit = max((sum(tops.get(j, 0) for j in range(n)) - tops[i] + m for i, m in unread.items()), default=-1)
        if depth >= most or (len(rows) >= k and rows[-1]["w"] > limit):
            return rows, {"exact": True, "rounds": rounds, "depth": min(depth, most)}
        depth *= 4
