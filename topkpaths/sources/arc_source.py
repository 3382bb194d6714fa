"""Arc files as a data source of their own, for batches and streams: spark.read.format("arcs") and spark.readStream.format("arcs").

Files are of lines 'a src dst weight'; other lines are skipped. A large file is read in byte ranges: a line belongs to the
range in which it begins. The stream takes each file of a folder once, in order of name; a file must be whole when it appears
(written elsewhere and moved in). Paths are of a file system that every executor sees as a folder; `files.read_arcs` reads any other.
"""

from __future__ import annotations

import glob
import os

from pyspark.sql import SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, DataSourceStreamReader, InputPartition

#: Bytes of a file that one task reads.
SPLIT_BYTES = 64 << 20


class Span(InputPartition):
    def __init__(self, path: str, start: int, end: int):
        self.path, self.start, self.end = path, start, end


def arc_files(path: str) -> list[str]:
    """The files of a folder (hidden and marker files left out), or the one file."""
    path = path.removeprefix("file:")
    return sorted(f for f in glob.glob(f"{path}/*") if os.path.isfile(f) and os.path.basename(f)[0] not in "._") if os.path.isdir(path) else [path]


def spans(paths: list[str], size: int) -> list[Span]:
    return [Span(p, at, at + size) for p in paths for at in range(0, os.path.getsize(p), size)]


def arcs_of(span: Span):
    with open(span.path, "rb") as f:
        if span.start:
            f.seek(span.start - 1)
            f.readline()  # the line that began in the range before
        while f.tell() < span.end:
            line = f.readline()
            if not line:
                return
            part = line.split()
            if len(part) >= 4 and part[0] == b"a":
                yield int(part[1]), int(part[2]), int(part[3])


class ArcReader(DataSourceReader):
    def __init__(self, options):
        self.path, self.size = options["path"], int(options.get("splitBytes", SPLIT_BYTES))

    def partitions(self):
        return spans(arc_files(self.path), self.size) or [Span(os.devnull, 0, 0)]

    def read(self, partition):
        return arcs_of(partition)


class ArcStream(DataSourceStreamReader):
    """Offset: the name of the last file taken."""

    def __init__(self, options):
        self.path, self.size = options["path"], int(options.get("splitBytes", SPLIT_BYTES))

    def initialOffset(self):
        return {"after": ""}

    def latestOffset(self):
        found = arc_files(self.path)
        return {"after": found[-1] if found else ""}

    def partitions(self, start, end):
        return spans([f for f in arc_files(self.path) if start["after"] < f <= end["after"]], self.size)

    def read(self, partition):
        return arcs_of(partition)


class Arcs(DataSource):
    @classmethod
    def name(cls):
        return "arcs"

    def schema(self):
        return "src bigint, dst bigint, w bigint"

    def reader(self, schema):
        return ArcReader(self.options)

    def streamReader(self, schema):
        return ArcStream(self.options)


def register(spark: SparkSession) -> None:
    """Makes the format known to a session; the classes travel with the tasks."""
    import sys

    from pyspark import cloudpickle

    cloudpickle.register_pickle_by_value(sys.modules[__name__])
    spark.dataSource.register(Arcs)
