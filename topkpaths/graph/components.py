"""Connected components of an edge table, as stars that point to the smallest node."""

from __future__ import annotations

from collections.abc import Callable

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: Edges that one task contracts at a time.
CONTRACT_EDGES = 500_000


def _contractor():
    import pyarrow as pa

    def run(batches):
        up: dict[int, int] = {}

        def root(x):
            r = x
            while up.get(r, r) != r:
                r = up[r]
            while up.get(x, x) != r:
                up[x], x = r, up.get(x, x)
            return r

        for batch in batches:
            for u, v in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist()):
                a, b = root(u), root(v)
                up.setdefault(a, a)
                up.setdefault(b, b)
                if a != b:
                    up[max(a, b)] = min(a, b)
        pairs = [(x, root(x)) for x in list(up)]
        pairs = [p for p in pairs if p[0] != p[1]]
        yield pa.RecordBatch.from_arrays([pa.array([p[0] for p in pairs], pa.int64()), pa.array([p[1] for p in pairs], pa.int64())], names=["u", "v"])

    return run


def _star_round(e: DataFrame) -> DataFrame:
    """Links larger neighbours, then smaller ones, to the smallest neighbour of each node."""
    both = e.union(e.select(F.col("v").alias("u"), F.col("u").alias("v")))
    low = both.groupBy("u").agg(F.least(F.min("v"), F.col("u")).alias("m"))
    large = both.join(low, "u").where("v > u").select(F.col("v").alias("u"), F.col("m").alias("v")).distinct()
    low = large.groupBy("u").agg(F.min("v").alias("m"))
    small = large.join(low, "u")
    return small.select("u", F.col("m").alias("v")).union(small.where("v <> m").select(F.col("v").alias("u"), F.col("m").alias("v"))).distinct()


def components(edges: DataFrame, keep: Callable[[DataFrame], DataFrame]) -> DataFrame:
    """(node, root) of every node that has an edge and is not its own root; edges: two BIGINT columns.

    keep materialises a table between rounds (checkpoint, or a written table).
    """
    a, b = edges.columns[:2]
    e = keep(edges.select(F.greatest(a, b).alias("u"), F.least(a, b).alias("v")).where("u <> v").distinct())
    while True:
        n = e.count()
        if n == 0:
            break
        parts = -(-n // CONTRACT_EDGES)
        e = keep((e.coalesce(1) if parts == 1 else e.repartition(parts)).mapInArrow(_contractor(), "u bigint, v bigint"))
        if n <= CONTRACT_EDGES:
            break  # one task has seen every edge
        loose = e.alias("x").join(e.alias("y"), F.col("x.v") == F.col("y.u"), "left_semi").limit(1).count() + e.groupBy("u").count().where("count > 1").limit(1).count()
        if not loose:
            break
        e = keep(_star_round(e))
    return e.select(F.col("u").alias("node"), F.col("v").alias("root"))
