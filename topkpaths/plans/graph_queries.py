"""Queries over the graphs themselves, with their SQL twins."""

from __future__ import annotations

from pyspark.sql import functions as F

from ..graph import builders as B
from ..graph import stats
from ..graph.components import components
from ..graph.model import clean, dropped
from ..runtime import keep
from . import sqlgen as S

_EDGES = "select a, b, w from pairs"


def _stand(name):
    return lambda spark, d: B.stand_in(spark, d, name)


def g_components(spark, d):
    g = B.stand_in(spark, d, "baskets")
    nodes = g.edges.select(F.col("src").alias("node")).union(g.edges.select("dst")).distinct()
    root = components(g.edges.select("src", "dst"), keep)
    return nodes.join(root, "node", "left").select("node", F.coalesce("root", "node").alias("root")).groupBy("root").agg(F.count("*").alias("nodes"))


def g_node_filter(spark, d):
    good = B.load(spark, d, "part").where("p_size > 25").select("p_partkey")
    e = B.basket_edges(spark, d).select(F.col("a").alias("src"), F.col("b").alias("dst"), "w")
    return B.node_filter(e, good, "p_partkey").select("src", "dst", "w")


def g_dropped(spark, d):
    o = B.load(spark, d, "orders").select(F.col("o_custkey").alias("src"), F.when(F.col("o_orderkey") % 7 != 0, F.pmod("o_orderkey", F.lit(150))).alias("dst"), F.when(F.col("o_orderkey") % 5 != 0, F.col("o_totalprice")).alias("w"))
    return dropped(o)


def g_clean(spark, d):
    o = B.load(spark, d, "orders").select(F.col("o_custkey").alias("src"), F.pmod("o_orderkey", F.lit(150)).alias("dst"), F.round("o_totalprice").cast("long").alias("w"))
    return clean(o)


def g_conversation_words(spark, d):
    c = B.load(spark, d, "conversations").select(F.col("conv_id").alias("session"), F.explode(F.regexp_extract_all(F.lower("text"), F.lit(r"(\p{L}+)"), F.lit(1))).alias("item")).where("length(item) > 5")
    return B.cooccurrence(c, "dice", 0.3, min_item=3, min_support=3)


def g_quality_words(spark, d):
    """Node filter by document labels: words of documents labelled good."""
    good = B.load(spark, d, "labels").where("quality = 1").select("doc_id")
    docs = B.load(spark, d, "documents").join(good, "doc_id", "left_semi")
    return docs.select("doc_id", F.explode(F.array_distinct(F.regexp_extract_all(F.lower("text"), F.lit(r"(\p{L}+)"), F.lit(1)))).alias("word")).where("length(word) > 3").groupBy("word").agg(F.count("*").alias("docs")).where("docs >= 3")


QUERIES = {
    "g_topic_edges": lambda s, d: B.topic_edges(s, d),
    "g_nation_flow": lambda s, d: B.nation_edges(s, d),
    "g_part_dice": lambda s, d: B.basket_edges(s, d, "dice", 0.07),
    "g_part_jaccard": lambda s, d: B.basket_edges(s, d, "jaccard", 0.04),
    "g_part_condprob": lambda s, d: B.basket_edges(s, d, "condprob", 0.08),
    "g_part_count": lambda s, d: B.basket_edges(s, d, "count", 2.0),
    "g_word_dice": lambda s, d: B.word_edges(s, d),
    "g_session_dice": lambda s, d: B.event_edges(s, d),
    "g_road_distances": lambda s, d: B.road_distances(s, d).select("src", "dst", F.round("dist", 6).alias("dist")),
    "g_road_flipped": lambda s, d: B.road_edges(s, d),
    "g_vector_knn": lambda s, d: B.vector_edges(s, d),
    "g_layered": lambda s, d: B.layer_edges(s, d),
    "g_links": lambda s, d: B.links(B.load(s, d, "pages")).groupBy("href").agg(F.count("*").alias("n")),
    "g_conversation_words": g_conversation_words,
    "g_quality_words": g_quality_words,
    "g_degree": lambda s, d: stats.degrees(_stand("baskets")(s, d)),
    "g_strength": lambda s, d: stats.degrees(_stand("topic")(s, d)),
    "g_stats": lambda s, d: stats.profile(s, _stand("topic")(s, d), _components_of(s, d)),
    "g_weight_histogram": lambda s, d: stats.histogram(_stand("topic")(s, d), 20),
    "g_weight_percentiles": lambda s, d: stats.percentiles(_stand("road")(s, d)),
    "g_components": g_components,
    "g_node_filter": g_node_filter,
    "g_clean": g_clean,
    "g_dropped": g_dropped,
    "g_arcs": lambda s, d: stats.ranked_arcs(_stand("baskets")(s, d)),
    "g_edge_rank": lambda s, d: _stand("topic")(s, d).edges.select("src", "dst", "w", "eid"),
    "g_edge_rank_ranges": lambda s, d: _ranged(s, d),
    "g_induced": lambda s, d: B.induced(_stand("nation")(s, d), B.load(s, d, "nation").join(B.load(s, d, "region").where("r_name = 'ASIA'"), F.col("n_regionkey") == F.col("r_regionkey")).select(F.col("n_nationkey").alias("id"))).edges.select("src", "dst", "w"),
}


def _components_of(s, d):
    return lambda g: components(g.edges.select("src", "dst"), keep)


def _ranged(s, d):
    """Ranks by range partitions and offsets, as large tables get them."""
    from ..graph.model import rank_edges

    return rank_edges(keep(clean(B.road_edges(s, d)), "edges"), small=False)


ORACLES = {
    "g_topic_edges": f"with {S._flow(S.TOPIC_MOVES)} {_EDGES}",
    "g_nation_flow": f"with {S._flow(S.NATION_MOVES)} {_EDGES}",
    "g_part_dice": S.cooccur_sql("dice", 0.07),
    "g_part_jaccard": S.cooccur_sql("jaccard", 0.04),
    "g_part_condprob": S.cooccur_sql("condprob", 0.08),
    "g_part_count": S.cooccur_sql("count", 2.0),
    "g_word_dice": f"with {S.GRAPHS['words']} {_EDGES}",
    "g_session_dice": f"with {S.GRAPHS['sessions']} {_EDGES}",
    "g_road_distances": f"with {S.ROAD} select src, dst, round(dist, 6) as dist from ro",
    "g_road_flipped": f"with {S.GRAPHS['road']} select src, dst, w from edges",
    "g_vector_knn": f"with {S.GRAPHS['vectors']} select src, dst, w from edges",
    "g_layered": f"with {S.LAYERS} select layer, src, dst, w from layers",
    "g_links": "select href, count(*) as n from (select unnest(regexp_extract_all(html, 'href=\"([^\"]*)\"', 1)) as href from pages) group by href",
    "g_conversation_words": "with " + S._cooccur(r"select * from (select conv_id as session, unnest(regexp_extract_all(lower(text), '\p{L}+')) as item from conversations) where length(item) > 5", S._WEIGHT["dice"], 0.3, 3, 3) + " " + _EDGES,
    "g_quality_words": r"select word, count(*) as docs from (select doc_id, unnest(list_distinct(regexp_extract_all(lower(text), '\p{L}+'))) as word from documents where doc_id in (select doc_id from labels where quality = 1)) where length(word) > 3 group by word having count(*) >= 3",
    "g_degree": f"with {S.GRAPHS['baskets']} select node, count(*) as degree, sum(w)::bigint as strength, max(w) as top from (select src as node, w from edges union all select dst, w from edges) group by node",
    "g_strength": f"with {S.GRAPHS['topic']} select node, count(*) as degree, sum(w)::bigint as strength, max(w) as top from (select src as node, w from edges union all select dst, w from edges) group by node",
    "g_stats": f"with recursive {S.GRAPHS['topic']}, a as (select src as x, dst as y from edges union select dst, src from edges), r(x, y) as (select x, y from a union select r.x, a.y from r join a on r.y = a.x) select (select count(distinct x) from a) as nodes, count(*) as edges, round(count(*) / (select count(distinct x) from a), 4) as edges_per_node, round(2 * count(*) / (select count(distinct x) from a), 4) as mean_degree, (select count(distinct m) from (select x, min(y) as m from r group by x)) as components, max(w) as top, min(w) as low from edges",
    "g_weight_histogram": f"with {S.GRAPHS['topic']} select least(20, floor((w - lo) * 20.0 / (hi - lo + 1))::int + 1) as bucket, count(*) as n from edges, (select min(w) as lo, max(w) as hi from edges) group by 1",
    "g_weight_percentiles": f"with {S.GRAPHS['road']} select q, round(v)::bigint as w from (select unnest([0.1, 0.5, 0.9]) as q, unnest(quantile_cont(w, [0.1, 0.5, 0.9])) as v from edges)",
    "g_components": f"with recursive {S.GRAPHS['baskets']}, a as (select src as x, dst as y from edges union all select dst, src from edges), r(x, y) as (select x, y from a union select r.x, a.y from r join a on r.y = a.x), m as (select x, least(x, min(y)) as root from r group by x) select root, count(*) as nodes from m group by root",
    "g_node_filter": f"with {S.GRAPHS['baskets']} select src, dst, w from edges where src in (select p_partkey from part where p_size > 25) and dst in (select p_partkey from part where p_size > 25)",
    "g_clean": "select least(s, t) as src, greatest(s, t) as dst, max(w) as w from (select o_custkey as s, o_orderkey % 150 as t, round(o_totalprice)::bigint as w from orders) where s <> t group by all",
    "g_dropped": "select reason, count(*) as count from (select case when o_orderkey % 5 = 0 then 'weight' when o_orderkey % 7 <> 0 and o_custkey = o_orderkey % 150 then 'loop' when o_orderkey % 7 = 0 then 'end' end as reason from orders) where reason is not null group by reason",
    "g_arcs": f"with {S.GRAPHS['baskets']}, a as (select src as head, dst as tail, w from edges union all select dst, src, w from edges) select head, tail, w, row_number() over (partition by head order by w desc, tail) as rk from a",
    "g_edge_rank": f"with {S.GRAPHS['topic']} select src, dst, w, row_number() over (order by w desc, src, dst) - 1 as eid from edges",
    "g_edge_rank_ranges": f"with {S.GRAPHS['road']} select src, dst, w, row_number() over (order by w desc, src, dst) - 1 as eid from edges",
    "g_induced": f"with {S.GRAPHS['nation']}, inside as (select n_nationkey from nation join region on n_regionkey = r_regionkey where r_name = 'ASIA') select src, dst, w from edges where src in (from inside) and dst in (from inside)",
}
