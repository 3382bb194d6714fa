"""Queries that run the user-defined functions, with SQL twins."""

from __future__ import annotations

from pyspark.sql import functions as F

from ..graph import builders as B
from ..graph.components import components
from ..plans import sqlgen as S
from ..runtime import keep
from . import local


def _with_components(s, d):
    g = B.stand_in(s, d, "baskets")
    root = components(g.edges.select("src", "dst"), keep)
    return g.edges.join(root, F.col("src") == F.col("node"), "left").select(F.coalesce("root", "src").alias("component"), "src", "dst", "w")


def fn_udf(s, d):
    e = B.load(s, d, "orders").select("o_orderkey", F.array("o_custkey", F.col("o_orderkey") % 100).alias("n"))
    return e.select("o_orderkey", F.array_join(local.turned("n").cast("array<string>"), ">").alias("path"))


def fn_udtf(s, d):
    """The k best of each component through a table function."""
    _with_components(s, d).createOrReplaceTempView("topk_component_edges")
    s.udtf.register("heaviest_paths_local", local.LocalPaths)
    return s.sql("SELECT component, rank, path, weight FROM heaviest_paths_local(TABLE(topk_component_edges) PARTITION BY (component), 3, 2)")


_PER = f"""with recursive {S.GRAPHS['baskets']}, arcs as (select src as a, dst as b, w from edges union all select dst, src, w from edges),
r(x, y) as (select a, b from arcs union select r.x, arcs.b from r join arcs on r.y = arcs.a), m as (select x, least(x, min(y)) as component from r group by x),
p(n, len, w) as (select [a, b], 1, w from arcs union all select list_append(n, arcs.b), len + 1, p.w + arcs.w from p join arcs on p.n[len(p.n)] = arcs.a where p.len < 3 and not list_contains(p.n, arcs.b)),
f as (select m.component, n, w, row_number() over (partition by m.component order by w desc, n) as rank from p join m on m.x = p.n[1] where p.len = 3 and n[1] < n[4])
select component, rank::int as rank, array_to_string(n, '>') as path, w::bigint as weight from f where rank <= 2"""

QUERIES = {
    "fn_udf": fn_udf,
    "fn_pandas_udf": lambda s, d: B.load(s, d, "orders").select("o_orderkey", F.round(local.ratio("o_totalprice", F.lit(300007.0)), 6).alias("r")),
    "fn_arrow_udf": lambda s, d: B.load(s, d, "orders").select("o_orderkey", F.round(local.ratio_arrow("o_totalprice", F.lit(300007.0)), 6).alias("r")),
    "fn_udaf": lambda s, d: B.load(s, d, "orders").groupBy("o_custkey").agg(F.round(local.heaviest_three("o_totalprice"), 2).alias("best")),
    "fn_udtf_paths": fn_udtf,
    "fn_grouped_map": lambda s, d: local.per_component(_with_components(s, d), 3, 2),
}
_RATIO = "select o_orderkey, round(o_totalprice / 300007.0::double, 6) as r from orders"
ORACLES = {
    "fn_udf": "select o_orderkey, least(o_custkey, o_orderkey % 100) || '>' || greatest(o_custkey, o_orderkey % 100) as path from orders",
    "fn_pandas_udf": _RATIO,
    "fn_arrow_udf": _RATIO,
    "fn_udaf": "select o_custkey, round(sum(o_totalprice), 2) as best from (select *, row_number() over (partition by o_custkey order by o_totalprice desc) as rk from orders) where rk <= 3 group by o_custkey",
    "fn_udtf_paths": _PER,
    "fn_grouped_map": _PER,
}
