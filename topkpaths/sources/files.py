"""Edge lists and paths as files: arc files of road graphs, delimited text, bucketed and banded tables, DOT."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def write_arcs(edges: DataFrame, path: str) -> None:
    """One line an arc: 'a src dst weight'."""
    edges.select(F.concat_ws(" ", F.lit("a"), "src", "dst", "w").alias("value")).write.text(path)


def read_arcs(spark: SparkSession, path: str) -> DataFrame:
    """(src, dst, w) of an arc file; comments and headers are skipped. Read and split by the engine, so files may be huge."""
    part = F.split("value", r"\s+")
    return spark.read.text(path).where(F.col("value").startswith("a ")).select(F.get(part, F.lit(1)).cast("long").alias("src"), F.get(part, F.lit(2)).cast("long").alias("dst"), F.get(part, F.lit(3)).cast("long").alias("w"))


def write_dot(edges: DataFrame, path: str) -> None:
    edges.select(F.format_string("  %d -- %d [weight=%d];", "src", "dst", "w").alias("value")).write.text(path)


def read_edge_list(spark: SparkSession, path: str, sep: str = ",", weighted: bool = True) -> DataFrame:
    schema = "src long, dst long" + (", w double" if weighted else "")
    return spark.read.csv(path, schema=schema, sep=sep)


def write_banded(edges: DataFrame, path: str, bands: int = 8) -> None:
    """Parquet in weight bands: reading from the heaviest down opens only the bands it needs. edges: src, dst, w, eid."""
    size = edges.count()
    band = F.floor(F.col("eid") * F.lit(bands) / F.lit(max(1, size))).cast("int")
    edges.withColumn("band", band).repartitionByRange(bands, "band", "eid").sortWithinPartitions("eid").write.partitionBy("band").parquet(path)


def read_bands(spark: SparkSession, path: str, upto: int) -> DataFrame:
    return spark.read.parquet(path).where(F.col("band") <= upto)


def write_bucketed(arcs: DataFrame, table: str, buckets: int = 16) -> None:
    """Adjacency bucketed by its head: joins on the head need no further exchange of it."""
    arcs.write.bucketBy(buckets, "head").sortBy("head").mode("overwrite").saveAsTable(table)


def write_paths(paths: DataFrame, path: str, kind: str = "json") -> None:
    """Answers as json lines, csv (nodes joined) or orc."""
    out = paths if kind != "csv" else paths.withColumn("nodes", F.array_join(F.transform("nodes", lambda x: x.cast("string")), ">"))
    out.write.format(kind).save(path)
