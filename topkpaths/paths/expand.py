"""Path tables and their extension by one edge: guards, cycle check, orientation, top-k."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..graph.model import SCALE, Graph
from ..runtime import keep

#: How edge weights make a path weight: (step, best possible rest of n edges no heavier than h).
AGGREGATES = {
    "sum": (lambda w, x: w + x, lambda w, h, n: w + h * n),
    "mean": (lambda w, x: w + x, lambda w, h, n: w + h * n),  # of a fixed length: ranked as the sum
    "min": (lambda w, x: F.least(w, x), lambda w, h, n: F.least(w, h)),
    "max": (lambda w, x: F.greatest(w, x), lambda w, h, n: F.greatest(w, h)),
    "product": (lambda w, x: w * x / float(SCALE), lambda w, h, n: w * F.pow(h / float(SCALE), F.lit(n))),
}
COLUMNS = ["nodes", "w", "first_w", "last_w", "peak_w", "first_eid", "last_eid"]


def start_paths(g: Graph, agg: str = "sum", edges: DataFrame | None = None) -> DataFrame:
    """Paths of one edge, each edge once (from src to dst)."""
    e = g.edges if edges is None else edges
    w = F.col("w").cast("double") if agg == "product" else F.col("w")
    return e.select(F.array("src", "dst").alias("nodes"), w.alias("w"), F.col("w").alias("first_w"), F.col("w").alias("last_w"), F.col("w").alias("peak_w"), F.col("eid").alias("first_eid"), F.col("eid").alias("last_eid"))


def both_ways(paths: DataFrame) -> DataFrame:
    """Each path and its reverse, in one pass over the paths."""
    same = F.struct(*COLUMNS)
    back = F.struct(F.reverse("nodes").alias("nodes"), "w", F.col("last_w").alias("first_w"), F.col("first_w").alias("last_w"), "peak_w", F.col("last_eid").alias("first_eid"), F.col("first_eid").alias("last_eid"))
    return paths.select(F.inline(F.array(same, back)))


def _guard(kind: str, w: Column, eid: Column, far_w: Column, far_eid: Column, peak: Column) -> Column | None:
    """What may be appended, given the edge at the other end."""
    return {"none": None, "peak": w <= peak, "ends": w <= far_w, "strict": eid > far_eid}[kind]


def _sides(paths: DataFrame, arcs: DataFrame, g: Graph, few: bool, end: int) -> tuple[DataFrame, DataFrame, Column]:
    """Both sides of the path join and its key: the node at that end of the path (1 or -1), which is the head of the arc.

    Where the join is shuffled, the arcs of a hub are dealt over several keys by their tail, and a path that ends in one meets each of them.
    """
    key = F.element_at("p.nodes", end) == F.col("a.head")
    if few and not g.small:
        return F.broadcast(paths).alias("p"), arcs.alias("a"), key
    if g.small or g.hubs is None:
        return paths.alias("p"), g.side(arcs).alias("a"), key
    hubs = F.broadcast(g.hubs)
    p = paths.join(hubs, F.element_at("nodes", end) == F.col("hub"), "left").select(*COLUMNS, F.explode(F.sequence(F.lit(0), F.coalesce("parts", F.lit(1)) - 1)).alias("part"))
    a = arcs.join(hubs, F.col("head") == F.col("hub"), "left").select("head", "tail", "w", "eid", F.coalesce(F.pmod(F.xxhash64("tail"), F.col("parts")).cast("int"), F.lit(0)).alias("part"))
    return p.alias("p"), a.alias("a"), key & (F.col("p.part") == F.col("a.part"))


def extend_right(paths: DataFrame, g: Graph, arcs: DataFrame, guard: str = "none", agg: str = "sum", extra=None, few: bool = False) -> DataFrame:
    """Appends an edge behind the last node; extra(path, arc weight, arc eid) may add a condition to the join.

    few: the paths are of a bounded number, so they are broadcast and the adjacency is only scanned.
    """
    p, a, key = _sides(paths, arcs, g, few, -1)
    on = key & ~F.array_contains("p.nodes", F.col("a.tail"))
    rule = _guard(guard, F.col("a.w"), F.col("a.eid"), F.col("p.first_w"), F.col("p.first_eid"), F.col("p.peak_w"))
    for cond in (rule, extra and extra(F.col("a.w"), F.col("a.eid"))):
        on = on if cond is None else on & cond
    step = AGGREGATES[agg][0]
    return p.join(a, on).select(
        F.concat("p.nodes", F.array("a.tail")).alias("nodes"), step(F.col("p.w"), F.col("a.w")).alias("w"), "p.first_w", F.col("a.w").alias("last_w"),
        F.greatest("p.peak_w", "a.w").alias("peak_w"), "p.first_eid", F.col("a.eid").alias("last_eid"))


def extend_left(paths: DataFrame, g: Graph, arcs: DataFrame, guard: str = "none", agg: str = "sum", extra=None, few: bool = False) -> DataFrame:
    """Puts an edge before the first node; arcs lead against the direction of the graph."""
    p, a, key = _sides(paths, arcs, g, few, 1)
    on = key & ~F.array_contains("p.nodes", F.col("a.tail"))
    rule = _guard(guard, F.col("a.w"), F.col("a.eid"), F.col("p.last_w"), F.col("p.last_eid"), F.col("p.peak_w"))
    for cond in (rule, extra and extra(F.col("a.w"), F.col("a.eid"))):
        on = on if cond is None else on & cond
    step = AGGREGATES[agg][0]
    return p.join(a, on).select(
        F.concat(F.array("a.tail"), "p.nodes").alias("nodes"), step(F.col("p.w"), F.col("a.w")).alias("w"), F.col("a.w").alias("first_w"), "p.last_w",
        F.greatest("p.peak_w", "a.w").alias("peak_w"), F.col("a.eid").alias("first_eid"), "p.last_eid")


def extend_both(paths: DataFrame, g: Graph, guard: str = "none", agg: str = "sum", extra=None, few: bool = False) -> DataFrame:
    """Extends at both ends. Undirected: a path's left end is its reverse's right end, so one join does both."""
    if not g.directed:
        return extend_right(both_ways(paths), g, g.arcs(), guard, agg, extra, few)
    return extend_right(paths, g, g.arcs(), guard, agg, extra, few).union(extend_left(paths, g, g.arcs(inward=True), guard, agg, extra, few))


def oriented(nodes: Column, directed: bool) -> Column:
    """A path and its reverse are one: the smaller end comes first."""
    return nodes if directed else F.when(F.element_at(nodes, 1) < F.element_at(nodes, -1), nodes).otherwise(F.reverse(nodes))


def canonical(paths: DataFrame, directed: bool) -> DataFrame:
    return paths.withColumn("nodes", oriented(F.col("nodes"), directed))


def deduplicated(paths: DataFrame, directed: bool, agg: str = "sum") -> DataFrame:
    """Each path once, in canonical orientation, with the end columns of that orientation."""
    if directed:
        return paths.dropDuplicates(["nodes"])
    turn = F.element_at("nodes", 1) > F.element_at("nodes", -1)
    flip = lambda a, b: F.when(turn, F.col(b)).otherwise(F.col(a))
    return paths.select(
        oriented(F.col("nodes"), False).alias("nodes"), "w", flip("first_w", "last_w").alias("first_w"), flip("last_w", "first_w").alias("last_w"), "peak_w",
        flip("first_eid", "last_eid").alias("first_eid"), flip("last_eid", "first_eid").alias("last_eid")).dropDuplicates(["nodes"])


def ranked_weight(agg: str) -> Column:
    """Products are ranked by nine decimals, so that the order of factors doesn't matter."""
    return F.round("w").cast("long") if agg == "product" else F.col("w")


def top(paths: DataFrame, k: int, directed: bool, agg: str = "sum") -> DataFrame:
    """The k best: (nodes, w), by weight and then by nodes. A limit over a sort: k rows a task."""
    return canonical(paths, directed).select("nodes", ranked_weight(agg).alias("w")).orderBy(F.desc("w"), "nodes").limit(k)


def answers(spark, rows, length: int, agg: str = "sum") -> DataFrame:
    """The result table of at most k rows: rank, nodes, length, weight."""
    out = [(i + 1, list(map(int, r[0])), length, int(r[1])) for i, r in enumerate(rows)]
    df = spark.createDataFrame(out, "rank int, nodes array<bigint>, length int, weight bigint")
    return df.withColumn("weight", F.round(F.col("weight") / length).cast("long")) if agg == "mean" else df


def better(a, b, k: int, seen: bool = True):
    """Merges two lists of (nodes, w) rows: the k best, each once."""
    rows = {tuple(r[0]): int(r[1]) for r in [*a, *b]}
    return sorted(rows.items(), key=lambda r: (-r[1], r[0]))[:k]


__all__ = ["AGGREGATES", "COLUMNS", "answers", "better", "both_ways", "canonical", "deduplicated", "extend_both", "extend_left", "extend_right", "keep", "oriented", "ranked_weight", "start_paths", "top"]
