"""Round trips through files, with SQL twins."""

from __future__ import annotations

from pyspark.sql import functions as F

from ..graph import builders as B
from ..plans import sqlgen as S
from ..runtime import scratch
from . import arc_source, files

_EDGES = "with " + S.GRAPHS["baskets"] + " select src, dst, w from edges"


def _edges(s, d):
    return B.stand_in(s, d, "baskets").edges


def _trip(kind):
    def run(s, d):
        path = scratch(s, kind)
        e = _edges(s, d).select("src", "dst", "w")
        e.write.format(kind).save(path)
        return s.read.schema(e.schema).format(kind).load(path)

    return run


def _arc_file(s, d):
    path = scratch(s, "arcs")
    files.write_arcs(_edges(s, d), path)
    return files.read_arcs(s, path)


def _arc_source(s, d):
    """The same arc files by the registered format, in ranges of 4 KB."""
    path = scratch(s, "arcs")
    files.write_arcs(_edges(s, d), path)
    arc_source.register(s)
    return s.read.format("arcs").option("splitBytes", 4096).load(path)


def _arc_stream(s, d):
    from ..streaming.live import drained

    path = scratch(s, "arcs")
    files.write_arcs(_edges(s, d), path)
    arc_source.register(s)
    return drained(s.readStream.format("arcs").load(path))


def _dot(s, d):
    path = scratch(s, "dot")
    files.write_dot(_edges(s, d), path)
    return s.read.text(path).select(F.regexp_extract("value", r"(\d+) --", 1).cast("long").alias("src"), F.regexp_extract("value", r"-- (\d+)", 1).cast("long").alias("dst"), F.regexp_extract("value", r"weight=(\d+)", 1).cast("long").alias("w"))


def _bands(s, d):
    path = scratch(s, "bands")
    files.write_banded(_edges(s, d), path, 8)
    return files.read_bands(s, path, 1).select("src", "dst", "w", "eid")


def _paths(s, d):
    from ..api import heaviest_paths

    path = scratch(s, "paths")
    files.write_paths(heaviest_paths(B.stand_in(s, d, "baskets"), 3, 5).paths, path, "json")
    return s.read.schema("rank int, nodes array<long>, length int, weight long").json(path).select("rank", F.array_join(F.transform("nodes", lambda x: x.cast("string")), ">").alias("path"), "length", "weight")


def _edge_list(s, d):
    path = scratch(s, "list")
    _edges(s, d).select("src", "dst", (F.col("w") / 1e9).alias("w")).write.csv(path)
    return files.read_edge_list(s, path).select("src", "dst", F.round(F.col("w") * 1e9).cast("long").alias("w"))


QUERIES = {
    "s_csv_roundtrip": _trip("csv"),
    "s_json_roundtrip": _trip("json"),
    "s_orc_roundtrip": _trip("orc"),
    "s_parquet_roundtrip": _trip("parquet"),
    "s_arc_file": _arc_file,
    "s_arc_source": _arc_source,
    "s_arc_stream": _arc_stream,
    "s_dot": _dot,
    "s_edge_list": _edge_list,
    "s_band_pruning": _bands,
    "s_paths_json": _paths,
}
ORACLES = dict.fromkeys(["s_csv_roundtrip", "s_json_roundtrip", "s_orc_roundtrip", "s_parquet_roundtrip", "s_arc_file", "s_arc_source", "s_arc_stream", "s_dot", "s_edge_list"], _EDGES)
ORACLES["s_band_pruning"] = "with " + S.GRAPHS["baskets"] + ", r as (select *, row_number() over (order by w desc, src, dst) - 1 as eid, count(*) over () as n from edges) select src, dst, w, eid from r where eid * 8 // n <= 1"
ORACLES["s_paths_json"] = S.path_sql("baskets", 3, 5)
