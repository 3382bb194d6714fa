"""Spark helpers shared by the training-data operators."""

from __future__ import annotations

import tempfile
import uuid
import zlib

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import IntegralType

#: ASCII white space; words are runs of anything else.
WORD_PATTERN = r"[^\x20\x09-\x0D]+"


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share; a temporary one only where the session names none and runs on one machine."""
    found = spark.sparkContext.getConf().get("spark.checkpoint.dir") or spark.conf.get("spark.checkpoint.dir", None)
    if not found:
        found = spark.sparkContext.getCheckpointDir()
    if not found:
        master = spark.sparkContext.master
        if not master.startswith("local") or master.startswith("local-cluster"):
            raise ValueError("set spark.checkpoint.dir to a folder that driver and executors share")
        found = tempfile.mkdtemp(prefix="topkpaths-")
        spark.sparkContext.setCheckpointDir(found)
        found = spark.sparkContext.getCheckpointDir()
    return found.rstrip("/")


def fresh_path(spark: SparkSession, tag: str) -> str:
    return f"{shared_dir(spark)}/{tag}-{uuid.uuid4().hex}"


def spill(df: DataFrame, tag: str) -> DataFrame:
    """Writes a table to the shared folder and reads it back: cuts the lineage, survives lost executors."""
    spark = df.sparkSession
    path = fresh_path(spark, tag)
    df.write.parquet(path)
    out = spark.read.schema(df.schema).parquet(path)
    out.spilled_to = path
    return out


def release(*tables: DataFrame) -> None:
    """Deletes spilled tables that nothing reads any more; other tables are left alone."""
    for t in tables:
        path = getattr(t, "spilled_to", None)
        if path:
            hadoop = t.sparkSession._jvm.org.apache.hadoop.fs.Path(path)
            hadoop.getFileSystem(t.sparkSession._jsc.hadoopConfiguration()).delete(hadoop, True)


class Scratch:
    """Spilled tables of one run, deleted together once its last table is written."""

    def __init__(self):
        self.tables: list[DataFrame] = []

    def spill(self, df: DataFrame, tag: str) -> DataFrame:
        self.tables.append(spill(df, tag))
        return self.tables[-1]

    def clear(self) -> None:
        release(*self.tables)
        self.tables = []


def shuffle_width(spark: SparkSession) -> int:
    return max(1, int(spark.conf.get("spark.sql.shuffle.partitions")))


def place_of(df: DataFrame, name: str) -> int:
    """The place of a column among all; case doesn't count, as in Spark."""
    return [c.lower() for c in df.columns].index(name)


def number_of_id(df: DataFrame, name: str = "doc_id") -> Column:
    """The id as a long: itself if it is an integer, else a hash of its text; null stays null."""
    if isinstance(df.schema[name].dataType, IntegralType):
        return F.col(name).cast("long")
    return F.when(F.col(name).isNotNull(), F.xxhash64(F.col(name).cast("string")))


def crc_of_id(name: str = "doc_id") -> Column:
    """crc32 of the id as text; a null id counts as an empty text."""
    return F.crc32(F.coalesce(F.col(name).cast("string"), F.lit("")).cast("binary"))


def py_crc_of_id(value) -> int:
    return zlib.crc32(b"" if value is None else str(value).encode())


def by_value(module) -> None:
    """Ships a kernel module inside the tasks, so executors need not have the package on their path."""
    import sys

    from pyspark import cloudpickle

    cloudpickle.register_pickle_by_value(sys.modules[module] if isinstance(module, str) else module)
