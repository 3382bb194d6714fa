"""Path queries: every method and variant on the stand-in graphs, with exhaustive SQL twins where they fit."""

from __future__ import annotations

from pyspark.sql import functions as F

from .. import apps
from ..api import heaviest_paths
from ..graph import builders as B
from ..graph.model import encode, graph
from ..runtime import keep
from ..paths import sequential
from ..paths.expand import answers
from ..paths.layered import layered_paths
from ..paths.ordered_buffers import Search
from ..paths.rank_join import Input, rank_join
from ..paths.reductions import lightest_paths
from ..paths.result import TRACE, PathResult
from . import measures as M
from . import sqlgen as S

QUERIES: dict = {}
ORACLES: dict = {}


def _graph(spark, d, name, directed=False):
    return B.six_nodes(spark) if name == "six" else B.stand_in(spark, d, name, directed)


def _add(key, name, length, k, method, sql=None, **options):
    QUERIES[key] = lambda s, d: heaviest_paths(_graph(s, d, name), length, k, method, **options).named()
    if sql is not False:
        ORACLES[key] = sql or S.path_sql(name, length, k)


# exhaustive search
_add("p_enumerate_d1_l2", "topic", 2, 10, "enumerate")
_add("p_enumerate_d2p_l4", "baskets", 4, 10, "enumerate")
_add("p_enumerate_x1_l4", "types", 4, 10, "enumerate")
_add("p_enumerate_d3v_l3", "vectors", 3, 10, "enumerate")
# dynamic programs
_add("p_dp_avoid_d1n_l3", "nation", 3, 5, "avoidance_dp")
_add("p_dp_avoid_d2p_l3", "baskets", 3, 5, "avoidance_dp")
_add("p_dp_visited_d1n_l3", "nation", 3, 5, "avoidance_dp", form="visited")
_add("p_dp_visited_d2p_l4", "baskets", 4, 1, "avoidance_dp", form="visited")
_add("p_dp_topk", "six", 4, 20, "avoidance_dp")
# rank scan
_add("p_rank_scan_x1_l4", "six", 4, 3, "edge_rank_scan", first=4)
_add("p_rank_scan_d2p_l3", "baskets", 3, 10, "edge_rank_scan", first=128)
_add("p_rank_scan_d3_l4", "road", 4, 3, "edge_rank_scan", first=1024)
_add("p_rank_scan_partials", "baskets", 3, 10, "edge_rank_scan", first=256, keep_partials=True)
for _k in (1, 10, 100):
    _add(f"p_rank_scan_k{_k}", "baskets", 4, _k, "edge_rank_scan", first=512)
# ordered buffers
_add("p_buffers_d1_l3", "topic", 3, 3, "ordered_buffers", block=16)
_add("p_buffers_d2p_l4", "baskets", 4, 10, "ordered_buffers", block=256)
_add("p_buffers_d2w_l2", "words", 2, 10, "ordered_buffers")
_add("p_buffers_d3_l6", "road", 6, 3, "ordered_buffers", block=4096)
for _g in ("none", "peak", "ends", "strict"):
    _add(f"p_buffers_guard_{_g}", "baskets", 3, 10, "ordered_buffers", guard=_g, block=256)
_add("p_buffers_release_slice", "six", 4, 3, "ordered_buffers", release=20, block=4)
_add("p_buffers_release_drain", "nation", 3, 10, "ordered_buffers", block=32)
_add("p_buffers_peak_bound", "baskets", 4, 5, "ordered_buffers", bound="peak", block=256)
# canonical growth
_add("p_growth_d1_l3", "topic", 3, 10, "canonical_growth")
_add("p_growth_d2p_l6", "baskets", 6, 10, "canonical_growth")
_add("p_growth_d2w_l2", "words", 2, 25, "canonical_growth")
_add("p_growth_d2e_l2", "sessions", 2, 10, "canonical_growth")
_add("p_growth_d3_l6", "road", 6, 10, "canonical_growth")
_add("p_growth_d3_l10", "road", 10, 1, "canonical_growth")
_add("p_growth_d3v_l5", "vectors", 5, 10, "canonical_growth")
_add("p_growth_k100", "baskets", 4, 100, "canonical_growth")
_add("p_growth_bands", "road", 4, 10, "canonical_growth", bands=4)
_add("p_growth_unseeded", "nation", 3, 10, "canonical_growth", seed=None)
_add("p_length_one", "topic", 1, 10, "canonical_growth")
_add("p_too_few", "baskets", 10, 1000, "canonical_growth")
_add("p_auto", "nation", 2, 10, "auto")
# aggregates
_add("p_min", "baskets", 3, 10, "canonical_growth", S.path_sql("baskets", 3, 10, step="least(p.w, arcs.w)"), agg="min")
_add("p_max", "baskets", 3, 10, "canonical_growth", S.path_sql("baskets", 3, 10, step="greatest(p.w, arcs.w)"), agg="max")
_add("p_product", "baskets", 3, 10, "canonical_growth", S.path_sql("baskets", 3, 10, start="w::double", step="p.w * arcs.w / 1000000000.0", final="round(w)"), agg="product")
_add("p_mean", "nation", 3, 10, "canonical_growth", S.path_sql("nation", 3, 10).replace("v::bigint as weight", "round(v / 3.0)::bigint as weight"), agg="mean")
_STEP = {"min": "least(p.w, arcs.w)", "max": "greatest(p.w, arcs.w)"}
for _a in ("min", "max"):
    _add(f"p_buffers_{_a}", "baskets", 3, 10, "ordered_buffers", S.path_sql("baskets", 3, 10, step=_STEP[_a]), agg=_a)
    _add(f"p_rank_scan_{_a}", "baskets", 3, 10, "edge_rank_scan", S.path_sql("baskets", 3, 10, step=_STEP[_a]), agg=_a, first=256)
_PRODUCT = S.path_sql("baskets", 3, 10, start="w::double", step="p.w * arcs.w / 1000000000.0", final="round(w)")
_add("p_buffers_product", "baskets", 3, 10, "ordered_buffers", _PRODUCT, agg="product")
_add("p_rank_scan_product", "baskets", 3, 10, "edge_rank_scan", _PRODUCT, agg="product", first=256)
# lazy access
_add("p_lazy_d1_l3", "topic", 3, 10, "ordered_buffers", access="lazy", block=64)
_add("p_lazy_d2p_l4", "baskets", 4, 10, "ordered_buffers", access="lazy", block=256)
_add("p_lazy_d2w_l2", "words", 2, 25, "ordered_buffers", access="lazy", block=256)
_add("p_lazy_d3_l6", "road", 6, 3, "ordered_buffers", access="lazy", block=4096)
# heuristics and baselines
_add("h_budget_exact", "baskets", 4, 5, "budgeted", budget=1_000_000, block=1024)
_add("h_budget_small", "baskets", 6, 1, "budgeted", False, budget=500)
_add("h_beam", "topic", 6, 3, "beam", False)
_add("h_greedy", "topic", 6, 1, "greedy", False)
_add("h_greedy_stalls", "baskets", 10, 1, "greedy", False)
_add("h_pairwise_dp", "nation", 3, 3, "pairwise_dp", False)


def _directed(method, **options):
    def run(s, d):
        moves = B.topic_moves(s, d).where("frm <> to").groupBy("frm", "to").agg(F.count("*").alias("n"))
        edges, ids = encode(keep(moves, "moves"), "frm", "to")
        return heaviest_paths(graph(edges.select("src", "dst", F.col("n").alias("w")), directed=True, labels=ids), 2, 10, method, **options).named()

    return run


_DIRECTED = f"""moves as ({S.TOPIC_MOVES}), pairs as (select frm as a, "to" as b, count(*) as w from moves where frm <> "to" group by all),
labels as (select row_number() over (order by label) as id, label from (select a as label from pairs union select b from pairs)),
edges as (select x.id as src, y.id as dst, w from pairs join labels x on x.label = a join labels y on y.label = b)"""
QUERIES["p_growth_directed"] = _directed("canonical_growth")
QUERIES["p_enumerate_directed"] = _directed("enumerate")
QUERIES["p_buffers_directed"] = _directed("ordered_buffers", guard="strict")
QUERIES["p_dp_directed"] = _directed("avoidance_dp")
QUERIES["p_lazy_directed"] = _directed("ordered_buffers", access="lazy")
QUERIES["h_greedy_directed"] = _directed("greedy")
QUERIES["h_budget_directed"] = _directed("budgeted", budget=100_000)
for _key in ("p_lazy_directed", "h_budget_directed", "p_growth_directed", "p_enumerate_directed", "p_buffers_directed", "p_dp_directed"):
    ORACLES[_key] = S.path_sql("topic", 2, 10, directed=True, edges=_DIRECTED)


def _lightest(length):
    return lambda s, d: lightest_paths(graph(B.road_distances(s, d).select("src", "dst", F.round(F.col("dist") * 1e6).cast("long").alias("w"))), length, 5).named()


_DISTANCES = S.ROAD + ", edges as (select src, dst, round(dist * 1000000)::bigint as w from ro)"
for _n in (4, 8):
    QUERIES[f"p_lightest_d3_l{_n}"] = _lightest(_n)
    ORACLES[f"p_lightest_d3_l{_n}"] = S.path_sql("road", _n, 5, lightest=True, edges=_DISTANCES)


def _scores(s, d):
    return B.load(s, d, "part").select(F.col("p_partkey").alias("id"), (F.col("p_size") / 50.0).alias("r"))


def p_node_score_mul(s, d):
    e = B.basket_edges(s, d).select(F.col("a").alias("src"), F.col("b").alias("dst"), "w")
    return heaviest_paths(graph(B.mean_node_score(e, _scores(s, d))), 3, 10).named()


def p_node_score_add(s, d):
    """Node scores added: an edge carries half of both ends' scores; the outer halves of a path's ends come on top.

    The halves missing at the ends are bounded by the largest score, so growth keeps every path that can still be among the answers.
    """
    score = B.load(s, d, "part").select(F.col("p_partkey").alias("id"), (F.col("p_size") * 500_000).cast("long").alias("half"))
    a, b = score.toDF("a", "ha"), score.toDF("b", "hb")
    edges = B.basket_edges(s, d).join(a, "a").join(b, "b").select(F.col("a").alias("src"), F.col("b").alias("dst"), (F.col("w") + F.col("ha") + F.col("hb")).alias("w"))
    return apps.heaviest_with_ends(graph(edges), score, 3, 10).select("rank", F.array_join(F.transform("nodes", lambda x: x.cast("string")), ">").alias("path"), "length", "weight")


QUERIES |= {"p_node_score_mul": p_node_score_mul, "p_node_score_add": p_node_score_add}
_SCORED = S.GRAPHS["baskets"].replace("edges as (select a as src, b as dst, w from pairs)", "edges as (select a as src, b as dst, round(w * (x.p_size / 50.0::double) * (y.p_size / 50.0::double))::bigint as w from pairs join part x on x.p_partkey = a join part y on y.p_partkey = b)")
ORACLES["p_node_score_mul"] = S.path_sql("baskets", 3, 10, edges=_SCORED)
ORACLES["p_node_score_add"] = S.path_sql("baskets", 3, 10, final="w + (select sum(p_size * 1000000)::bigint from part where list_contains(n, p_partkey))")


def _layered(run, k):
    """Over every layer of the table, from the first day to the last."""
    return lambda s, d: run(B.layer_edges(s, d), k).paths.select("rank", F.array_join(F.transform("nodes", lambda x: x.cast("string")), ">").alias("path"), "length", "weight")


def _layered_sql(k):
    """The k best chains into each node, layer by layer."""
    return f"""with recursive {S.LAYERS}, best(layer, n, v) as (select layer + 1, [src, dst], w from layers where layer = 0 union all
select layer, n, v from (select l.layer + 1 as layer, list_append(b.n, l.dst) as n, b.v + l.w as v, row_number() over (partition by l.dst order by b.v + l.w desc, list_append(b.n, l.dst)) as rk
from best b join layers l on l.layer = b.layer and l.src = b.n[-1]) where rk <= {k}),
top as (select n, v from best where layer = (select max(layer) + 1 from layers) order by v desc, n limit {k})
select (row_number() over (order by v desc, n))::int as rank, array_to_string(n, '>') as path, (len(n) - 1)::int as length, v::bigint as weight from top"""


for _m in ("bfs", "dfs", "ta"):
    QUERIES[f"p_layered_{_m}"] = _layered(lambda e, k, m=_m: layered_paths(e, k, m), 5)
    ORACLES[f"p_layered_{_m}"] = _layered_sql(5)


def _sql(form):
    def run(s, d):
        return S.heaviest_paths_sql(s, B.stand_in(s, d, "baskets"), 3, 10, form).select(F.array_join(F.transform("nodes", lambda x: x.cast("string")), ">").alias("path"), F.col("w").alias("weight"))

    return run


QUERIES |= {"p_sql_selfjoin": _sql("self_join"), "p_sql_recursive": _sql("recursive")}
for _key in ("p_sql_selfjoin", "p_sql_recursive"):
    ORACLES[_key] = f"select path, weight from ({S.path_sql('baskets', 3, 10)})"


def _pulled(g):
    """The edges of a graph for the one-step-at-a-time forms, which refuse more than MAX_EDGES."""
    return [tuple(r) for r in g.edges.orderBy("eid").limit(sequential.MAX_EDGES + 1).select("src", "dst", "w").collect()]


def p_buffers_lazy(s, d):
    """Lazy extension, one step at a time, on the six part types."""
    g = B.stand_in(s, d, "types")
    return PathResult(answers(s, sequential.buffers(_pulled(g), 4, 5, lazy=True)["paths"], 4), {"exact": True}, labels=g.labels).named()


QUERIES["p_buffers_lazy"] = p_buffers_lazy
ORACLES["p_buffers_lazy"] = S.path_sql("types", 4, 5)


def p_more_answers(s, d):
    """Ten answers, then ten more from the same state."""
    run = Search(B.stand_in(s, d, "baskets"), 3, block=256)
    run.more(10)
    return run.more(20).named()


QUERIES["p_more_answers"] = p_more_answers
ORACLES["p_more_answers"] = S.path_sql("baskets", 3, 20)


# general rank join
def _joined(s, d, three=False, **options):
    line = B.load(s, d, "lineitem").select("l_orderkey", "l_partkey", "l_linenumber", "l_extendedprice")
    orders = B.load(s, d, "orders").select("o_orderkey", "o_totalprice")
    part = B.load(s, d, "part").select("p_partkey", "p_retailprice")
    inputs = [Input(line, "l_extendedprice", ["l_orderkey", "l_linenumber"]), Input(orders, "o_totalprice", ["o_orderkey"])]
    on = [F.col("l_orderkey") == F.col("o_orderkey")]
    if three:
        inputs.append(Input(part, "p_retailprice", ["p_partkey"]))
        on.append(F.col("l_partkey") == F.col("p_partkey"))
    best, _ = rank_join(inputs, on, ["l_orderkey", "l_partkey"], 10, **options)
    return best.select("l_orderkey", "l_partkey", "score")


QUERIES |= {
    "rj_two_way": lambda s, d: _joined(s, d, probe="full"),
    "rj_three_way": lambda s, d: _joined(s, d, True, first=2048),
    "rj_adaptive": lambda s, d: _joined(s, d, True, pull="adaptive", first=2048),
    "rj_min_score": lambda s, d: _joined(s, d, f="min", first=1024),
}
_RJ = "select l_orderkey, l_partkey, round({}, 6) as score from lineitem join orders on l_orderkey = o_orderkey join part on l_partkey = p_partkey order by score desc, l_orderkey, l_partkey limit 10"
ORACLES |= {
    "rj_two_way": _RJ.format("l_extendedprice + o_totalprice"),
    "rj_three_way": _RJ.format("l_extendedprice + o_totalprice + p_retailprice"),
    "rj_adaptive": _RJ.format("l_extendedprice + o_totalprice + p_retailprice"),
    "rj_min_score": _RJ.format("least(l_extendedprice, o_totalprice)"),
}


# applications
def a_sequences(s, d):
    good = B.load(s, d, "part").where("p_size > 10").select(F.col("p_partkey").alias("item"))
    return apps.recommend_sequences(B.basket_sessions(s, d), good, 3, 5, 0.07).named()


_GOOD = f"{S._cooccur('select l_orderkey as session, l_partkey as item from lineitem where l_partkey in (select p_partkey from part where p_size > 10)', S._WEIGHT['dice'], 0.07)}, {S._PLAIN}"
QUERIES |= {
    "app_sequences": a_sequences,
    "app_routes": lambda s, d: apps.plan_routes(B.road_distances(s, d).select("src", "dst", F.round("dist", 6).alias("dist")), 5, 3).named(),
    "app_flow_chains": lambda s, d: apps.flow_chains(B.topic_moves(s, d), 3, 5).named(),
    "app_stable_chains": _layered(apps.stable_chains, 3),
}
ORACLES |= {
    "app_sequences": S.path_sql("baskets", 3, 5, edges=_GOOD),
    "app_routes": S.path_sql("road", 5, 3, lightest=True, edges=S.ROAD + ", edges as (select src, dst, round(round(dist, 6) * 1000000000.0)::bigint as w from ro)"),
    "app_flow_chains": S.path_sql("topic", 3, 5),
    "app_stable_chains": _layered_sql(3),
}


# measures
def _counters(rows):
    return lambda s, d: s.createDataFrame(rows(s, d), "graph string, method string, length int, edges_read long, joins long, built long, duplicates long")


def _counted(s, d):
    out = []
    for name, lengths in (("types", range(2, 6)), ("market", (2, 3))):
        edges = _pulled(B.stand_in(s, d, name))
        for n in lengths:
            r = sequential.rank_scan(edges, n)
            out.append((name, "rank scan", n, r["edges_read"], r["joins"], r["built"], 0))
            for guard in ("none", "peak", "ends", "strict"):
                b = sequential.buffers(edges, n, guard=guard)
                out.append((name, f"buffers {guard}", n, b["edges_read"], b["joins"], b["built"], b["duplicates"]))
            y = sequential.buffers(edges, n, ends="one")
            out.append((name, "buffers one end", n, y["edges_read"], y["joins"], y["built"], y["duplicates"]))
            z = sequential.buffers(edges, n, lazy=True)
            out.append((name, "buffers lazy", n, z["edges_read"], z["joins"], z["built"], z["duplicates"]))
    return out


def m_threshold_trace(s, d):
    edges = _pulled(B.stand_in(s, d, "types"))
    rows = sequential.rank_scan(edges, 4)["steps"] + sequential.buffers(edges, 4)["steps"]
    return s.createDataFrame([tuple(r) for r in rows], TRACE)


def m_guard_gain(s, d):
    """Extensions made, duplicates and seconds without and with the guard."""
    out = []
    for name, n in (("baskets", 3), ("nation", 3)):
        g = B.stand_in(s, d, name)
        for guard in ("none", "ends", "strict"):
            r, sec = M.timed(lambda: heaviest_paths(g, n, 1, "ordered_buffers", guard=guard, block=64))
            out.append((name, n, guard, r.summary["joins"], r.summary["duplicates"], round(sec, 3)))
    return s.createDataFrame(out, "graph string, length int, guard string, joins long, duplicates long, seconds double")


def _top_baskets(s, d, length=4, k=5):
    return heaviest_paths(B.stand_in(s, d, "baskets"), length, k).paths


QUERIES |= {
    "m_access_counts": _counters(_counted),
    "m_threshold_trace": m_threshold_trace,
    "m_guard_gain": m_guard_gain,
    "m_coherence": lambda s, d: M.coherence(_top_baskets(s, d), B.load(s, d, "part").select(F.col("p_partkey").alias("id"), F.col("p_brand").alias("group"))),
    "m_overlap": lambda s, d: M.overlap(_top_baskets(s, d)),
    "m_surprise": lambda s, d: M.surprise(_top_baskets(s, d), B.load(s, d, "part").where("p_size > 25").select(F.col("p_partkey").alias("id"))),
    "m_path_labels": lambda s, d: heaviest_paths(B.stand_in(s, d, "topic"), 2, 5).named(),
    "m_quality_by_length": lambda s, d: M.quality_table(s, B.stand_in(s, d, "baskets"), (4,), 500),
    "m_longest_length": lambda s, d: M.longest_length(s, B.stand_in(s, d, "baskets"), 1500, 3),
    "m_spark_costs": lambda s, d: M.cost_table(s, B.stand_in(s, d, "baskets"), 3, ("enumerate", "canonical_growth", "greedy")),
    "h_upper_bound": lambda s, d: M.bound_table(s, B.stand_in(s, d, "baskets"), 4, range(5, 13)),
    "h_rho_by_length": lambda s, d: M.rho_table(s, B.stand_in(s, d, "topic"), (6, 15, 25), (20_000,)),
    "h_rho_by_budget": lambda s, d: M.rho_table(s, B.stand_in(s, d, "topic"), (25,), (10, 100, 1000, 10_000)),
}
_TOP5 = S.path_sql("baskets", 4, 5).replace("array_to_string(n, '>') as path", "n")
ORACLES |= {
    "m_coherence": f"""with t as ({_TOP5}), g as (select rank, p_brand as "group", count(*) as c from (select rank, unnest(n) as id from t) join part on p_partkey = id group by all),
r as (select rank, "group", round(c / sum(c) over (partition by rank), 4) as share, row_number() over (partition by rank order by c desc, "group") as rk from g) select rank, "group", share from r where rk = 1""",
    "m_overlap": f"with t as ({_TOP5}) select x.rank as a, y.rank as b, len(list_intersect(x.n, y.n))::int as shared from t x join t y on x.rank < y.rank",
    "m_surprise": f"with t as ({_TOP5}) select rank, round(avg(case when p_size > 25 then 0.0 else 1.0 end), 4) as share from (select rank, unnest(n) as id from t) join part on p_partkey = id group by rank",
    "m_path_labels": S.path_sql("topic", 2, 5),
    "h_upper_bound": "with b as (" + " union all ".join(f"select {i} as l, (select max(weight) from ({S.path_sql('baskets', i, 1)})) as w" for i in range(1, 5)) + ") select n::int as length, ((n // 4) * (select w from b where l = 4) + coalesce((select w from b where l = n % 4), 0))::bigint as bound from (select unnest(range(5, 13)) as n)",
}
