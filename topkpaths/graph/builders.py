"""Graphs from ordinary tables: co-occurrence, flows, distances, neighbours, links; and the stand-in graphs."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ..runtime import keep
from .model import Graph, encode, graph, nano
from .pair_blocks import dice_pairs


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


#: Items of a session that are paired in one place; a longer session is dealt into parts.
SESSION_PART = 512


def session_pairs(s: DataFrame, part: int = SESSION_PART) -> DataFrame:
    """(a, b), a < b, of each session; s: different rows (session, item).

    A session of more than `part` items is dealt into parts by the item's hash, and each two parts meet in a block of
    their own: no key holds more than the pairs of two parts, and no pair is met twice.
    """
    long_ones = s.groupBy("session").agg(F.ceil(F.count("*") / F.lit(part)).cast("int").alias("parts")).where("parts > 1")
    dealt = s.join(long_ones, "session", "left").select("session", "item", F.coalesce("parts", F.lit(1)).alias("parts"))
    dealt = dealt.withColumn("own", F.when(F.col("parts") == 1, 0).otherwise(F.pmod(F.xxhash64("item"), F.col("parts")).cast("int")))
    x = dealt.select("session", F.col("own").alias("lo"), F.explode(F.sequence("own", F.col("parts") - 1)).alias("hi"), F.col("item").alias("a"))
    y = dealt.select("session", F.explode(F.sequence(F.lit(0), F.col("own"))).alias("lo"), F.col("own").alias("hi"), F.col("item").alias("b"))
    met = x.join(y, ["session", "lo", "hi"]).where((F.col("lo") < F.col("hi")) | (F.col("a") < F.col("b")))
    return met.select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b"))


def pair_counts(sessions: DataFrame, min_item: int = 1, min_support: int = 1) -> DataFrame:
    """(a, b, both, na, nb) of items a < b that share sessions; sessions: (session, item)."""
    s = sessions.where("session is not null and item is not null").distinct()
    freq = s.groupBy("item").agg(F.count("*").alias("n"))
    if min_item > 1:
        freq = freq.where(F.col("n") >= min_item)
        s = s.join(freq.select("item"), "item", "left_semi")
    both = session_pairs(s).groupBy("a", "b").agg(F.count("*").alias("both")).where(F.col("both") >= min_support)
    return both.join(freq.select(F.col("item").alias("a"), F.col("n").alias("na")), "a").join(freq.select(F.col("item").alias("b"), F.col("n").alias("nb")), "b")


#: Measures of how strongly two items belong together.
MEASURES: dict[str, Column] = {
    "dice": lambda: 2.0 * F.col("both") / (F.col("na") + F.col("nb")),
    "jaccard": lambda: F.col("both") * 1.0 / (F.col("na") + F.col("nb") - F.col("both")),
    "condprob": lambda: F.col("both") * 1.0 / F.least("na", "nb"),
    "count": lambda: F.col("both") * 1.0,
}


def cooccurrence(sessions: DataFrame, measure: str = "dice", min_weight: float = 0.1, min_item: int = 1, min_support: int = 1) -> DataFrame:
    """(a, b, w in nano-units): the cut-off stands before any path search."""
    weight = MEASURES[measure]()
    return pair_counts(sessions, min_item, min_support).where(weight >= min_weight).select("a", "b", nano(weight).alias("w"))


def flow(moves: DataFrame) -> DataFrame:
    """(a, b, w): mean of the two directed shares; moves: (frm, to), loops don't count."""
    c = moves.where("frm <> to").groupBy("frm", "to").agg(F.count("*").alias("n"))
    out = c.groupBy("frm").agg(F.sum("n").alias("total"))
    share = c.join(out, "frm").select("frm", "to", (F.col("n") / F.col("total")).alias("f"))
    up = share.where("frm < to").select(F.col("frm").alias("a"), F.col("to").alias("b"), F.col("f").alias("f1"))
    down = share.where("frm > to").select(F.col("to").alias("a"), F.col("frm").alias("b"), F.col("f").alias("f2"))
    both = up.join(down, ["a", "b"], "full_outer")
    return both.select("a", "b", nano((F.coalesce("f1", F.lit(0.0)) + F.coalesce("f2", F.lit(0.0))) / 2).alias("w"))


def flipped(distances: DataFrame) -> DataFrame:
    """(src, dst, w): 1 - distance / largest distance."""
    top = distances.agg(F.max("dist").alias("top"))
    return distances.crossJoin(F.broadcast(top)).select("src", "dst", nano(1 - F.col("dist") / F.col("top")).alias("w"))  # one row


#: Vectors in one block of the nearest-neighbour search.
KNN_BLOCK = 2_048


def _nearest(k: int):
    """Kernel over (own ids and vectors, other ids and vectors) of two blocks: each own row's k nearest among the others."""
    import numpy as np
    import pyarrow as pa

    def matrix(cell):
        flat = cell.values
        return flat.flatten().to_numpy(zero_copy_only=False).astype("float64").reshape(len(flat), -1)

    def run(batches):
        for batch in batches:
            for i in range(batch.num_rows):
                ids, own, others, there = (batch.column(c)[i] for c in range(4))
                a, b = ids.values.to_numpy(), others.values.to_numpy()
                va, vb = matrix(own), matrix(there)
                with np.errstate(invalid="ignore", divide="ignore"):
                    d = np.round(1 - (va @ vb.T) / (np.linalg.norm(va, axis=1)[:, None] * np.linalg.norm(vb, axis=1)[None, :]), 9)
                d[np.isnan(d)] = np.inf
                d[a[:, None] == b[None, :]] = np.inf
                by_id = np.argsort(b, kind="stable")
                pick = by_id[np.argsort(d[:, by_id], axis=1, kind="stable")[:, :k]]
                best = np.take_along_axis(d, pick, 1)
                found = np.isfinite(best).ravel()
                yield pa.RecordBatch.from_arrays([pa.array(np.repeat(a, pick.shape[1])[found]), pa.array(b[pick].ravel()[found]), pa.array(best.ravel()[found])], names=["a", "b", "dist"])

    return run


def knn(vectors: DataFrame, k: int = 2, block: int = KNN_BLOCK) -> DataFrame:
    """(src, dst, dist): the k nearest by cosine distance; vectors: (id, v), of one dimension. Null and zero vectors have no neighbours.

    Exact. Vectors are packed into blocks of a bounded size; each two blocks meet as one row, whose task multiplies them
    and gives k rows a vector, so that a vector's ranking holds k rows a block.
    """
    rows = keep(vectors.where("id is not null and v is not null").select(F.col("id").cast("long").alias("id"), F.transform("v", lambda x: x.cast("double")).alias("v")), "vectors")
    blocks = max(1, -(-rows.count() // block))
    packed = rows.groupBy(F.pmod(F.xxhash64("id"), F.lit(blocks)).alias("no")).agg(F.collect_list("id").alias("ids"), F.collect_list("v").alias("vs"))  # some `block` rows
    packed = keep(packed, "blocks")
    own = packed.select(F.explode(F.sequence(F.lit(0).cast("long"), F.lit(blocks - 1).cast("long"))).alias("no"), F.col("ids").alias("a"), F.col("vs").alias("va"))
    met = own.join(packed, "no").select("a", "va", F.col("ids").alias("b"), F.col("vs").alias("vb"))
    d = met.mapInArrow(_nearest(k), "a long, b long, dist double")
    near = d.withColumn("rk", F.row_number().over(Window.partitionBy("a").orderBy("dist", "b"))).where(F.col("rk") <= k)
    return near.select(F.least("a", "b").alias("src"), F.greatest("a", "b").alias("dst"), "dist").distinct()


def links(pages: DataFrame) -> DataFrame:
    """(page_id, href): the link targets of each page."""
    return pages.select("page_id", F.explode(F.regexp_extract_all("html", F.lit(r'href="([^"]*)"'), F.lit(1))).alias("href"))


def node_filter(edges: DataFrame, good: DataFrame, key: str) -> DataFrame:
    """Edges between good nodes only."""
    return edges.join(good.select(F.col(key).alias("src")), "src", "left_semi").join(good.select(F.col(key).alias("dst")), "dst", "left_semi")


def induced(g: Graph, nodes: DataFrame, key: str = "id") -> Graph:
    return graph(node_filter(g.edges.select("src", "dst", "w"), nodes, key), g.directed, g.labels)


def mean_node_score(edges: DataFrame, scores: DataFrame) -> DataFrame:
    """Edge weight times both node scores (scores: id, r in 0..1)."""
    a, b = scores.select(F.col("id").alias("src"), F.col("r").alias("ra")), scores.select(F.col("id").alias("dst"), F.col("r").alias("rb"))
    return edges.join(a, "src").join(b, "dst").select("src", "dst", F.round(F.col("w") * F.col("ra") * F.col("rb")).cast("long").alias("w"))


# --- stand-in graphs -------------------------------------------------------------------------------------------

_LINE_ORDER = ["l_linenumber", "l_partkey", "l_suppkey", "l_quantity", "l_extendedprice"]


def topic_moves(spark: SparkSession, sf_dir: str, column: str = "p_name") -> DataFrame:
    """A line item followed by the next one of its order: (frm, to) part names, or another column of the parts."""
    line, part = load(spark, sf_dir, "lineitem"), load(spark, sf_dir, "part")
    rows = line.join(part.select(F.col("p_partkey").alias("l_partkey"), column), "l_partkey")
    w = Window.partitionBy("l_orderkey").orderBy(*_LINE_ORDER)
    return rows.select(F.col(column).alias("frm"), F.lead(column).over(w).alias("to")).where("to is not null")


def topic_edges(spark: SparkSession, sf_dir: str) -> DataFrame:
    return flow(topic_moves(spark, sf_dir))


def type_edges(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The flow between the six part types: a complete graph of six nodes, like the six-node example."""
    return flow(topic_moves(spark, sf_dir, "p_type"))


def market_edges(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Customers of a nation by region and by market segment: regions are stars of nations, and segments meet all of them."""
    cust, nation, region = load(spark, sf_dir, "customer"), load(spark, sf_dir, "nation"), load(spark, sf_dir, "region")
    c = cust.join(F.broadcast(nation), F.col("c_nationkey") == F.col("n_nationkey")).join(F.broadcast(region), F.col("n_regionkey") == F.col("r_regionkey"))  # 25 and 5 rows
    pairs = c.select(F.inline(F.array(F.struct(F.col("n_name").alias("a"), F.col("r_name").alias("b")), F.struct(F.col("n_name").alias("a"), F.col("c_mktsegment").alias("b")))))
    return pairs.groupBy("a", "b").agg(F.count("*").alias("w"))


def nation_edges(spark: SparkSession, sf_dir: str) -> DataFrame:
    line, orders = load(spark, sf_dir, "lineitem"), load(spark, sf_dir, "orders")
    cust, supp = load(spark, sf_dir, "customer"), load(spark, sf_dir, "supplier")
    moves = line.join(orders, F.col("l_orderkey") == F.col("o_orderkey")).join(cust, F.col("o_custkey") == F.col("c_custkey")).join(supp, F.col("l_suppkey") == F.col("s_suppkey"))
    return flow(moves.select(F.col("c_nationkey").cast("long").alias("frm"), F.col("s_nationkey").cast("long").alias("to")))


def basket_sessions(spark: SparkSession, sf_dir: str) -> DataFrame:
    return load(spark, sf_dir, "lineitem").select(F.col("l_orderkey").alias("session"), F.col("l_partkey").alias("item"))


def basket_edges(spark: SparkSession, sf_dir: str, measure: str = "dice", min_weight: float = 0.07, min_support: int = 1) -> DataFrame:
    return cooccurrence(basket_sessions(spark, sf_dir), measure, min_weight, min_support=min_support)


def word_lines(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Different lines of the documents, and of each its different words of more than three letters."""
    line = load(spark, sf_dir, "documents").select(F.explode(F.split("text", "\n")).alias("line")).where("line <> ''").distinct()
    found = F.array_distinct(F.regexp_extract_all(F.lower("line"), F.lit(r"(\p{L}+)"), F.lit(1)))
    return keep(line, "lines").select("line", F.filter(found, lambda x: F.length(x) > 3).alias("items"))


def word_edges(spark: SparkSession, sf_dir: str, max_items: int | None = None) -> DataFrame:
    """Words that share lines; beyond max_items words, all pairs are joined."""
    lines, cut, min_item, min_support = word_lines(spark, sf_dir), 0.1, 5, 3
    pairs = dice_pairs(lines.select("items"), cut, min_item, min_support, max_items)
    if pairs is None:  # a line is long: sessions are joined by a hash of it
        return cooccurrence(lines.select(F.xxhash64("line").alias("session"), F.explode("items").alias("item")), "dice", cut, min_item, min_support)
    weight = MEASURES["dice"]()
    return pairs.where(weight >= cut).select("a", "b", nano(weight).alias("w"))


def event_items(spark: SparkSession, sf_dir: str) -> DataFrame:
    e = load(spark, sf_dir, "events")
    return e.select("event_id", "user_id", F.col("ts").cast("timestamp").alias("ts"), F.get_json_object("props", "$.k").cast("long").alias("k"), "value", "event_type")


def event_sessions(events: DataFrame, gap_hours: int = 6) -> DataFrame:
    """(session, item): a user's events up to a gap."""
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    start = (F.unix_micros("ts") - F.unix_micros(F.lag("ts").over(w)) >= gap_hours * 3_600_000_000).cast("int")
    marked = events.withColumn("start", F.coalesce(start, F.lit(1)))
    numbered = marked.withColumn("no", F.sum("start").over(w.rowsBetween(Window.unboundedPreceding, Window.currentRow)))
    return numbered.select(F.struct("user_id", "no").alias("session"), F.col("k").alias("item"))


def event_edges(spark: SparkSession, sf_dir: str) -> DataFrame:
    return cooccurrence(event_sessions(event_items(spark, sf_dir)), "dice", 0.0)


def road_distances(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(src, dst, dist): the next order of a customer, and of a day and priority; of parallel edges the shorter."""
    o = load(spark, sf_dir, "orders").select("o_orderkey", "o_custkey", "o_orderpriority", F.to_date("o_orderdate").alias("d"), "o_totalprice")
    nxt = F.struct("o_orderkey", "d", "o_totalprice")
    by_customer = Window.partitionBy("o_custkey").orderBy("d", "o_orderkey")
    by_day = Window.partitionBy("d", "o_orderpriority").orderBy("o_custkey", "o_orderkey")
    steps = o.select("*", F.lead(nxt).over(by_customer).alias("n")).union(o.select("*", F.lead(nxt).over(by_day).alias("n"))).where("n is not null")
    dist = 1 + F.abs(F.datediff("n.d", "d")) + F.abs(F.col("n.o_totalprice") - F.col("o_totalprice")) / 1000
    return steps.select(F.least("o_orderkey", "n.o_orderkey").alias("src"), F.greatest("o_orderkey", "n.o_orderkey").alias("dst"), dist.alias("dist")).groupBy("src", "dst").agg(F.min("dist").alias("dist"))


def road_edges(spark: SparkSession, sf_dir: str) -> DataFrame:
    return flipped(road_distances(spark, sf_dir))


def vector_edges(spark: SparkSession, sf_dir: str) -> DataFrame:
    v = load(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("id"), F.col("embedding").alias("v"))
    return flipped(knn(v, 2))


def layer_edges(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(layer, src, dst, w): nodes (day, k); neighbouring days' items by shared users (Dice)."""
    e = event_items(spark, sf_dir).select(F.to_date("ts").alias("day"), "user_id", "k").distinct()
    first = e.agg(F.min("day").alias("first"))
    e = e.crossJoin(F.broadcast(first)).select(F.datediff("day", "first").cast("long").alias("layer"), "user_id", "k")  # one row
    n = e.groupBy("layer", "k").agg(F.count("*").alias("n"))
    x = e.select("layer", "user_id", F.col("k").alias("a"))
    y = e.select((F.col("layer") - 1).alias("layer"), "user_id", F.col("k").alias("b"))
    both = x.join(y, ["layer", "user_id"]).groupBy("layer", "a", "b").agg(F.count("*").alias("both"))
    na, nb = n.select("layer", F.col("k").alias("a"), F.col("n").alias("na")), n.select((F.col("layer") - 1).alias("layer"), F.col("k").alias("b"), F.col("n").alias("nb"))
    w = 2.0 * F.col("both") / (F.col("na") + F.col("nb"))
    joined = both.join(na, ["layer", "a"]).join(nb, ["layer", "b"])
    return joined.select("layer", (F.col("layer") * 1000 + F.col("a")).alias("src"), ((F.col("layer") + 1) * 1000 + F.col("b")).alias("dst"), nano(w).alias("w"))


#: The six-node example, in hundredths.
SIX_NODES = ((1, 2, 93), (2, 3, 93), (1, 3, 87), (2, 4, 77), (1, 6, 76), (2, 5, 73), (3, 4, 73), (1, 4, 73), (5, 6, 72), (3, 5, 70), (1, 5, 70), (2, 6, 70), (4, 5, 69), (3, 6, 66), (4, 6, 58))


def six_nodes(spark: SparkSession) -> Graph:
    return literal(spark, [(a, b, w / 100) for a, b, w in SIX_NODES])


def chain_and_star(n: int) -> list[tuple[int, int, float]]:
    """A heavy chain of three edges whose last is very light, and a light star of n rays."""
    return [(1, 2, 1.0), (2, 3, 1.0), (3, 4, 0.001), (11, 12, 0.03), (12, 13, 0.03), *[(13, 100 + i, 0.02) for i in range(n)]]


def adverse_star(n: int) -> list[tuple[int, int, float]]:
    """Three heavy edges in a row; the last one's node has n - 1 light rays."""
    return [(11, 12, 1.0), (12, 13, 1.0), (13, 101, 1.0), *[(13, 100 + i, 0.01) for i in range(2, n + 1)]]


def literal(spark: SparkSession, rows, directed: bool = False) -> Graph:
    return graph(spark.createDataFrame([(int(a), int(b), float(w)) for a, b, w in rows], "src long, dst long, w double"), directed)


def stand_in(spark: SparkSession, sf_dir: str, name: str, directed: bool = False) -> Graph:
    """topic, types, market, nation, baskets, words, sessions, road or vectors as a ranked graph with labels."""
    if name in (labelled := {"topic": topic_edges, "types": type_edges, "market": market_edges, "words": word_edges}):
        edges, ids = encode(keep(labelled[name](spark, sf_dir), "pairs"), "a", "b")
        return graph(edges.select("src", "dst", "w"), directed, ids)
    if name in ("nation", "baskets", "sessions"):
        make = {"nation": nation_edges, "baskets": basket_edges, "sessions": event_edges}[name]
        return graph(make(spark, sf_dir).select(F.col("a").alias("src"), F.col("b").alias("dst"), "w"), directed)
    return graph({"road": road_edges, "vectors": vector_edges}[name](spark, sf_dir), directed)
