"""SQL text for path queries: the plain l-way self-join (Spark), and recursive queries (Spark and DuckDB)."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from ..graph.model import Graph


def self_join_sql(arcs: str, length: int, k: int) -> str:
    """The query an optimiser gets without any of the methods: a chain of joins, a sort, a limit."""
    a = [f"a{i}" for i in range(1, length + 1)]
    nodes = ["a1.head", *[f"{x}.tail" for x in a]]
    joins = " ".join(f"JOIN {arcs} {y} ON {x}.tail = {y}.head" for x, y in zip(a, a[1:]))
    apart = [f"{nodes[i]} <> {nodes[j]}" for j in range(2, length + 1) for i in range(j - 1)]
    cond = " AND ".join([*apart, f"{nodes[0]} < {nodes[-1]}"])
    return f"SELECT array({', '.join(nodes)}) AS nodes, {' + '.join(f'{x}.w' for x in a)} AS w FROM {arcs} a1 {joins} WHERE {cond} ORDER BY w DESC, nodes LIMIT {k}"


def recursive_sql(arcs: str, length: int, k: int) -> str:
    return f"""WITH RECURSIVE p(nodes, len, w) AS (
  SELECT array(head, tail), 1, w FROM {arcs}
  UNION ALL
  SELECT concat(p.nodes, array(a.tail)), p.len + 1, p.w + a.w FROM p JOIN {arcs} a ON element_at(p.nodes, -1) = a.head
  WHERE p.len < {length} AND NOT array_contains(p.nodes, a.tail))
SELECT nodes, w FROM p WHERE len = {length} AND element_at(nodes, 1) < element_at(nodes, -1) ORDER BY w DESC, nodes LIMIT {k}"""


def heaviest_paths_sql(spark: SparkSession, g: Graph, length: int, k: int, form: str = "self_join") -> DataFrame:
    """(nodes, w) by SQL text alone."""
    g.arcs().createOrReplaceTempView("topk_arcs")
    return spark.sql((self_join_sql if form == "self_join" else recursive_sql)("topk_arcs", length, k))


# --- DuckDB twins ----------------------------------------------------------------------------------------------

_NANO = "round({} * 1000000000.0)::bigint"


def _encoded(pairs: str) -> str:
    return f"""{pairs},
labels as (select row_number() over (order by label) as id, label from (select a as label from pairs union select b from pairs)),
edges as (select x.id as src, y.id as dst, w from pairs join labels x on x.label = a join labels y on y.label = b)"""


def _flow(moves: str) -> str:
    return f"""moves as ({moves}),
cnt as (select frm, "to", count(*) as n from moves where frm <> "to" group by all),
tot as (select frm, sum(n)::bigint as total from cnt group by frm),
share as (select frm, "to", n / total as f from cnt join tot using (frm)),
pairs as (select coalesce(u.frm, d."to") as a, coalesce(u."to", d.frm) as b, {_NANO.format("((coalesce(u.f, 0) + coalesce(d.f, 0)) / 2)")} as w
  from (select * from share where frm < "to") u full join (select * from share where frm > "to") d on u.frm = d."to" and u."to" = d.frm)"""


def _cooccur(sessions: str, weight: str, cut: float, min_item: int = 1, min_support: int = 1) -> str:
    return f"""s0 as (select distinct session, item from ({sessions}) where session is not null and item is not null),
fr as (select item, count(*) as n from s0 group by item having count(*) >= {min_item}),
s1 as (select s0.* from s0 join fr using (item)),
bo as (select x.item as a, y.item as b, count(*) as c from s1 x join s1 y on x.session = y.session and x.item < y.item group by all having count(*) >= {min_support}),
wt as (select a, b, {weight} as v from bo join fr fa on fa.item = a join fr fb on fb.item = b),
pairs as (select a, b, {_NANO.format("v")} as w from wt where v >= {cut})"""


_WEIGHT = {"dice": "2.0::double * c / (fa.n + fb.n)", "jaccard": "c * 1.0::double / (fa.n + fb.n - c)", "condprob": "c * 1.0::double / least(fa.n, fb.n)", "count": "c * 1.0::double"}
TOPIC_MOVES = "select frm, \"to\" from (select p_name as frm, lead(p_name) over (partition by l_orderkey order by l_linenumber, l_partkey, l_suppkey, l_quantity, l_extendedprice) as \"to\" from lineitem join part on l_partkey = p_partkey) where \"to\" is not null"
NATION_MOVES = "select c_nationkey::bigint as frm, s_nationkey::bigint as \"to\" from lineitem join orders on l_orderkey = o_orderkey join customer on o_custkey = c_custkey join supplier on l_suppkey = s_suppkey"
BASKETS = "select l_orderkey as session, l_partkey as item from lineitem"
WORDS = r"select line as session, unnest(list_distinct(regexp_extract_all(lower(line), '\p{L}+'))) as item from (select distinct unnest(string_split(text, chr(10))) as line from documents) where line <> ''"
EVENT_SESSIONS = """select (user_id, no) as session, k as item from (select *, sum(start) over (partition by user_id order by ts, event_id rows unbounded preceding) as no from (
  select *, case when epoch_us(ts) - lag(epoch_us(ts)) over (partition by user_id order by ts, event_id) < 21600000000 then 0 else 1 end as start from (select *, (props->>'$.k')::bigint as k from events)))"""
_PLAIN = "edges as (select a as src, b as dst, w from pairs)"
ROAD = """o as (select o_orderkey as k, o_custkey as c, o_orderpriority as p, o_orderdate::date as d, o_totalprice as t from orders),
st as (select k, d, t, lead((k, d, t)) over (partition by c order by d, k) as n from o union all select k, d, t, lead((k, d, t)) over (partition by d, p order by c, k) as n from o),
ro as (select least(k, n[1]) as src, greatest(k, n[1]) as dst, min(1 + abs(n[2] - d) + abs(n[3] - t) / 1000) as dist from st where n is not null group by all)"""
VECTORS = """v as (select vec_id as id, [x::double for x in embedding] as e from embeddings),
vn as (select id, e, sqrt(list_sum([x * x for x in e])) as nr from v),
di as (select a.id as a, b.id as b, round(1 - list_sum([z[1] * z[2] for z in list_zip(a.e, b.e)]) / (a.nr * b.nr), 9) as dist from vn a join vn b on a.id <> b.id),
nn as (select a, b, dist from (select *, row_number() over (partition by a order by dist, b) as rk from di) where rk <= 2),
ro as (select distinct least(a, b) as src, greatest(a, b) as dst, dist from nn)"""
FLIPPED = "edges as (select src, dst, round((1 - dist / (select max(dist) from ro)) * 1000000000.0)::bigint as w from ro)"
LAYERS = """ev as (select distinct ts::date as d, user_id, (props->>'$.k')::bigint as k from events),
ly as (select (d - (select min(d) from ev))::bigint as layer, user_id, k from ev),
ln as (select layer, k, count(*) as n from ly group by all),
lb as (select x.layer, x.k as a, y.k as b, count(*) as c from ly x join ly y on y.layer = x.layer + 1 and x.user_id = y.user_id group by all),
layers as (select lb.layer, lb.layer * 1000 + a as src, (lb.layer + 1) * 1000 + b as dst, round(2.0::double * c / (na.n + nb.n) * 1000000000.0)::bigint as w
  from lb join ln na on na.layer = lb.layer and na.k = a join ln nb on nb.layer = lb.layer + 1 and nb.k = b)"""

#: CTEs that end in edges(src, dst, w); those with labels also make labels(id, label).
GRAPHS = {
    "topic": _encoded(_flow(TOPIC_MOVES)),
    "types": _encoded(_flow(TOPIC_MOVES.replace("p_name", "p_type"))),
    "nation": _flow(NATION_MOVES) + ",\n" + _PLAIN,
    "baskets": _cooccur(BASKETS, _WEIGHT["dice"], 0.07) + ",\n" + _PLAIN,
    "words": _encoded(_cooccur(f"select * from ({WORDS}) where length(item) > 3", _WEIGHT["dice"], 0.1, 5, 3)),
    "sessions": _cooccur(EVENT_SESSIONS, _WEIGHT["dice"], 0.0) + ",\n" + _PLAIN,
    "road": ROAD + ",\n" + FLIPPED,
    "vectors": VECTORS + ",\n" + FLIPPED,
    "six": "edges as (select * from (values " + ", ".join(f"({a}::bigint, {b}::bigint, {w}0000000::bigint)" for a, b, w in ((1, 2, 93), (2, 3, 93), (1, 3, 87), (2, 4, 77), (1, 6, 76), (2, 5, 73), (3, 4, 73), (1, 4, 73), (5, 6, 72), (3, 5, 70), (1, 5, 70), (2, 6, 70), (4, 5, 69), (3, 6, 66), (4, 6, 58))) + ") t(src, dst, w))",
}
LABELLED = ("topic", "types", "words")


def cooccur_sql(measure: str, cut: float) -> str:
    return f"with {_cooccur(BASKETS, _WEIGHT[measure], cut)} select a, b, w from pairs"


def path_sql(name: str, length: int, k: int, step: str = "p.w + arcs.w", start: str = "w", final: str = "w", directed: bool = False, extra: str = "", lightest: bool = False, edges: str | None = None) -> str:
    """The k best simple paths of a graph by exhaustive recursion, in DuckDB's dialect."""
    ctes = GRAPHS[name] if edges is None else edges
    arcs = "select src as a, dst as b, w from edges" + ("" if directed else " union all select dst, src, w from edges")
    label = "(select string_agg(l.label, '>' order by t.i) from (select unnest(n) as id, generate_subscripts(n, 1) as i) t join labels l using (id))" if name in LABELLED else "array_to_string(n, '>')"
    once = "" if directed else " and n[1] < n[len(n)]"
    order = f"{final} {'asc' if lightest else 'desc'}, n"
    return f"""with recursive {ctes},
arcs as ({arcs}),
p(n, len, w) as (select [a, b], 1, {start} from arcs
  union all select list_append(n, arcs.b), len + 1, {step} from p join arcs on p.n[len(p.n)] = arcs.a where p.len < {length} and not list_contains(p.n, arcs.b)),
best as (select n, {final} as v from p where len = {length}{once}{extra} order by {order} limit {k})
select (row_number() over (order by v {'asc' if lightest else 'desc'}, n))::int as rank, {label} as path, {length} as length, v::bigint as weight from best"""
