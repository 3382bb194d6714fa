"""How hard a graph is: sizes, degrees, weight distributions, ranked adjacency."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from .model import Graph


def degrees(g: Graph) -> DataFrame:
    """(node, degree, strength, top)"""
    return g.arcs().groupBy(F.col("head").alias("node")).agg(F.count("*").alias("degree"), F.sum("w").alias("strength"), F.max("w").alias("top"))


def profile(spark: SparkSession, g: Graph, roots: Callable[[Graph], DataFrame]) -> DataFrame:
    """One row: nodes, edges, edges per node, mean degree, components, largest and least weight."""
    nodes = g.arcs().select("head").distinct().count()
    merged = roots(g).count()  # nodes that are not their component's root
    return spark.createDataFrame([(nodes, g.n_edges, round(g.n_edges / nodes, 4), round(2 * g.n_edges / nodes, 4), nodes - merged, g.max_w, g.min_w)], "nodes long, edges long, edges_per_node double, mean_degree double, components long, top long, low long")


def histogram(g: Graph, buckets: int) -> DataFrame:
    """(bucket, n): equal widths between the least and the largest weight."""
    place = F.floor((F.col("w") - g.min_w) * float(buckets) / (g.max_w - g.min_w + 1)).cast("int") + 1
    return g.edges.groupBy(F.least(F.lit(buckets), place).alias("bucket")).agg(F.count("*").alias("n"))


def percentiles(g: Graph, at=(0.1, 0.5, 0.9)) -> DataFrame:
    """(q, w)"""
    row = g.edges.agg(F.percentile("w", F.array(*map(F.lit, at))).alias("p"))
    return row.select(F.explode(F.arrays_zip(F.array(*map(F.lit, at)).alias("q"), F.col("p"))).alias("x")).select(F.col("x.q").alias("q"), F.round("x.p").cast("long").alias("w"))


def ranked_arcs(g: Graph) -> DataFrame:
    """Adjacency with the place of each edge at its node, heaviest first (lazy access)."""
    return g.arcs().select("head", "tail", "w", F.row_number().over(Window.partitionBy("head").orderBy(F.desc("w"), "tail")).cast("long").alias("rk"))
