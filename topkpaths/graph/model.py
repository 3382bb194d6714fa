"""Weighted graphs as edge tables: validation, exact weights, ranks, adjacency and node dictionaries."""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ..runtime import keep

#: Units of a stored weight.
SCALE = 1_000_000_000
#: Edges up to which adjacency is broadcast (four longs each, both directions) and ranked by one window.
SMALL_EDGES = 200_000
#: Arcs of one head that are one key of a shuffled join; beyond it the head is dealt over several. On large graphs more, so that hubs are at most MAX_HUBS.
HUB_ARCS, MAX_HUBS = 50_000, 100_000
#: Labels up to which a dictionary is numbered by one window.
SMALL_LABELS = 200_000


def nano(weight: Column) -> Column:
    """Weights as integers, so that sums don't depend on their order."""
    return F.round(weight * float(SCALE)).cast("long")


def clean(edges: DataFrame, directed: bool = False) -> DataFrame:
    """(src, dst, w): no null or NaN weight, no loop, of parallel edges the heaviest; undirected edges with src < dst."""
    e = edges.where(F.col("src").isNotNull() & F.col("dst").isNotNull() & F.col("w").isNotNull() & (F.col("src") != F.col("dst")))
    if dict(edges.dtypes)["w"] == "double":
        e = e.where(~F.isnan("w")).withColumn("w", nano(F.col("w")))
    a, b = (F.col("src"), F.col("dst")) if directed else (F.least("src", "dst"), F.greatest("src", "dst"))
    return e.select(a.cast("long").alias("src"), b.cast("long").alias("dst"), F.col("w").cast("long").alias("w")).groupBy("src", "dst").agg(F.max("w").alias("w"))


def dropped(edges: DataFrame) -> DataFrame:
    """How many input rows `clean` refuses, by reason."""
    weight_bad = F.col("w").isNull() | (F.isnan("w") if dict(edges.dtypes)["w"] == "double" else F.lit(False))
    reason = F.when(weight_bad, "weight").when(F.col("src") == F.col("dst"), "loop").when(F.col("src").isNull() | F.col("dst").isNull(), "end")
    return edges.select(reason.alias("reason")).where("reason is not null").groupBy("reason").count()


def numbered(rows: DataFrame, order: list[Column], name: str, small: bool) -> DataFrame:
    """name: the place (from 0) in a total order. Large tables are range-sorted and get per-range offsets, never one window."""
    if small:
        return rows.withColumn(name, (F.row_number().over(Window.orderBy(*order)) - 1).cast("long"))
    sorted_ = rows.repartitionByRange(*order).sortWithinPartitions(*order).withColumn("at", F.monotonically_increasing_id())
    parts = keep(sorted_.select(*rows.columns, F.shiftright("at", 33).alias("part"), F.col("at").bitwiseAND((1 << 33) - 1).alias("place")), f"{name}-sorted")
    sizes = parts.groupBy("part").agg(F.count("*").alias("n"))  # one row a range
    offsets = sizes.select("part", F.coalesce(F.sum("n").over(Window.orderBy("part").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("base"))
    return parts.join(offsets, "part").select(*rows.columns, (F.col("base") + F.col("place")).alias(name))


def rank_edges(edges: DataFrame, small: bool) -> DataFrame:
    """eid: the place in (w desc, src, dst)."""
    return numbered(edges, [F.col("w").desc(), F.col("src"), F.col("dst")], "eid", small)


@dataclass
class Graph:
    """A ranked graph: edges (src, dst, w, eid), its size, and optionally (id, label) of nodes and (hub, parts) of nodes with many edges."""

    edges: DataFrame
    directed: bool
    n_edges: int
    max_w: int
    min_w: int
    labels: DataFrame | None = None
    hubs: DataFrame | None = None
    #: The adjacency, once it has been pulled to the driver.
    near: object = field(default=None, init=False, repr=False, compare=False)

    @property
    def small(self) -> bool:
        return self.n_edges <= SMALL_EDGES

    def arcs(self, inward: bool = False) -> DataFrame:
        """(head, tail, w, eid): steps from head to tail; inward: steps against the direction."""
        out = self.edges.select(F.col("src").alias("head"), F.col("dst").alias("tail"), "w", "eid")
        back = self.edges.select(F.col("dst").alias("head"), F.col("src").alias("tail"), "w", "eid")
        if self.directed:
            return back if inward else out
        return out.union(back)

    def side(self, arcs: DataFrame) -> DataFrame:
        """Adjacency for a join: broadcast behind the size check, else left to the planner."""
        return F.broadcast(arcs) if self.small else arcs

    def prefix(self, below: int, start: int = 0) -> Graph:
        """The edges with start <= eid < below."""
        e = self.edges.where((F.col("eid") >= start) & (F.col("eid") < below))
        return Graph(e, self.directed, min(below, self.n_edges) - start, self.max_w, self.min_w, self.labels, self.hubs)


def graph(edges: DataFrame, directed: bool = False, labels: DataFrame | None = None) -> Graph:
    """Validates, ranks and materialises an edge table (src, dst, w: BIGINT units or DOUBLE)."""
    plain = keep(clean(edges, directed), "edges")
    row = plain.agg(F.count("*").alias("n"), F.max("w").alias("hi"), F.min("w").alias("lo")).first()
    small = row["n"] <= SMALL_EDGES
    ranked = keep(rank_edges(plain, small), "edges-ranked")
    return Graph(ranked, directed, row["n"], row["hi"] or 0, row["lo"] or 0, labels, None if small else hubs_of(ranked, row["n"]))


def hubs_of(edges: DataFrame, n_edges: int) -> DataFrame | None:
    """(hub, parts) of nodes with too many edges for one key; at most MAX_HUBS rows, as the edges have 2 n ends. None if there are none."""
    most = max(HUB_ARCS, -(-2 * n_edges // MAX_HUBS))
    ends = edges.select(F.col("src").alias("hub")).union(edges.select(F.col("dst").alias("hub"))).groupBy("hub").agg(F.count("*").alias("n"))
    hubs = keep(ends.where(F.col("n") > most).select("hub", F.ceil(F.col("n") / most).cast("int").alias("parts")), "hubs")
    return None if hubs.isEmpty() else hubs


def encode(edges: DataFrame, a: str, b: str) -> tuple[DataFrame, DataFrame]:
    """Replaces labels by longs in sorted order: (edges with src, dst, dictionary of id, label)."""
    names = edges.select(F.col(a).alias("label")).union(edges.select(F.col(b).alias("label"))).where("label is not null").distinct()
    names = keep(names, "names")
    ids = keep(numbered(names, [F.col("label")], "id", names.count() <= SMALL_LABELS).select("label", (F.col("id") + 1).alias("id")), "labels")
    x, y = ids.select(F.col("label").alias(a), F.col("id").alias("src")), ids.select(F.col("label").alias(b), F.col("id").alias("dst"))
    return edges.join(x, a).join(y, b), ids


def decode(paths: DataFrame, labels: DataFrame | None, sep: str = ">") -> DataFrame:
    """Adds `path`: the node labels (or ids) joined by a mark. Few rows: the k answers."""
    if labels is None:
        return paths.withColumn("path", F.array_join(F.transform("nodes", lambda x: x.cast("string")), sep))
    at = paths.select("rank", F.posexplode("nodes").alias("pos", "id")).join(labels, "id")
    named = at.groupBy("rank").agg(F.array_join(F.transform(F.array_sort(F.collect_list(F.struct("pos", "label"))), lambda s: s["label"].cast("string")), sep).alias("path"))
    return paths.join(named, "rank")
