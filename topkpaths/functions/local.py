"""User-defined functions: only where no built-in says it, or as a cross-check of one."""

from __future__ import annotations

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.functions import arrow_udf, pandas_udf, udf, udtf

from ..paths import sequential


@udf(T.ArrayType(T.LongType()))
def turned(nodes):
    """The canonical orientation of a path, row by row."""
    return None if nodes is None else nodes if nodes[0] < nodes[-1] else nodes[::-1]


@pandas_udf(T.DoubleType())
def ratio(found: pd.Series, bound: pd.Series) -> pd.Series:
    """Found weight over its bound."""
    return found / bound.where(bound != 0, np.nan)


@arrow_udf(T.DoubleType())
def ratio_arrow(found: pa.Array, bound: pa.Array) -> pa.Array:
    import pyarrow.compute as pc

    return pc.divide(pc.cast(found, pa.float64()), pc.cast(bound, pa.float64()))


@pandas_udf(T.DoubleType())
def heaviest_three(w: pd.Series) -> float:
    """Sum of the three largest values of a group."""
    return float(w.nlargest(3).sum())


@udtf(returnType=T.StructType([T.StructField("component", T.LongType()), T.StructField("rank", T.IntegerType()), T.StructField("path", T.StringType()), T.StructField("weight", T.LongType())]))
class LocalPaths:
    """heaviest_paths_local(TABLE(edges) PARTITION BY component, length, k): exact search inside one small component."""

    def __init__(self):
        self.edges, self.component, self.length, self.k = [], None, 1, 1

    def eval(self, row, length: int, k: int):
        self.component, self.length, self.k = row["component"], length, k
        self.edges.append((row["src"], row["dst"], row["w"]))

    def terminate(self):
        if self.edges:
            for i, (nodes, w) in enumerate(sequential.buffers(self.edges, self.length, self.k)["paths"], 1):
                yield self.component, i, ">".join(map(str, nodes)), w


def per_component(edges: DataFrame, length: int, k: int) -> DataFrame:
    """The k best paths of each component: one group a component. edges: component, src, dst, w; components must be small."""

    def search(table: pa.Table) -> pa.Table:
        rows = list(zip(*(table.column(c).to_pylist() for c in ("src", "dst", "w"))))
        found = sequential.buffers(rows, length, k)["paths"]
        return pa.table({"component": pa.array([table.column("component")[0].as_py()] * len(found), pa.int64()), "rank": pa.array(range(1, len(found) + 1), pa.int32()), "path": pa.array([">".join(map(str, n)) for n, _ in found], pa.string()), "weight": pa.array([w for _, w in found], pa.int64())})

    return edges.groupBy("component").applyInArrow(search, "component long, rank int, path string, weight long")


def best_of_groups(groups: DataFrame, key: str, length: int, k: int) -> DataFrame:
    """The k best over all components."""
    return groups.orderBy(F.desc("weight"), "path").limit(k).select("path", F.lit(length).alias("length"), "weight")


__all__ = ["LocalPaths", "best_of_groups", "heaviest_three", "per_component", "ratio", "ratio_arrow", "turned"]
