"""What a method returns."""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import DataFrame, SparkSession

from ..graph.model import decode

TRACE = "step long, level int, theta double, edges_read long, joins long, built long, duplicates long, held long"


@dataclass
class PathResult:
    """paths: rank, nodes, length, weight; trace: counters by step; summary: totals."""

    paths: DataFrame
    summary: dict
    steps: list = field(default_factory=list)
    labels: DataFrame | None = None

    def trace(self, spark: SparkSession) -> DataFrame:
        return spark.createDataFrame([tuple(s) for s in self.steps], TRACE)

    def named(self) -> DataFrame:
        """(rank, path, length, weight)"""
        return decode(self.paths, self.labels).select("rank", "path", "length", "weight")
