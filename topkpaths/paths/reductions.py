"""Lightest paths of a fixed length by turning the weights round."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import functions as F

from ..graph.model import Graph, graph
from .canonical_growth import canonical_growth
from .result import PathResult


def flip(g: Graph, how: str = "difference") -> Graph:
    """difference: heaviest - w, order-equivalent for a fixed length; reciprocal: 1 / w, which is not."""
    w = g.max_w - F.col("w") if how == "difference" else F.round(1e18 / F.greatest(F.col("w"), F.lit(1))).cast("long")
    return graph(g.edges.select("src", "dst", w.cast("long").alias("w")), g.directed, g.labels)


def lightest_paths(g: Graph, length: int, k: int = 1, method: Callable = canonical_growth, how: str = "difference", **options) -> PathResult:
    """The k lightest paths: any method on the flipped graph, weights given in the original units."""
    got = method(flip(g, how), length, k, **options)
    if how == "difference":
        got.paths = got.paths.withColumn("weight", F.lit(length * g.max_w) - F.col("weight"))
    return got
