"""The relational operators around the path methods, one query each, with SQL twins."""

from __future__ import annotations

from pyspark.sql import functions as F
from pyspark.sql.window import Window as W

from ..graph.builders import load

QUERIES: dict = {}
ORACLES: dict = {}


def op(name: str, sql: str | None):
    """Registers a query (spark, load) under a name."""

    def add(f):
        QUERIES[name] = lambda spark, d: f(lambda t: load(spark, d, t))
        if sql:
            ORACLES[name] = sql
        return f

    return add


# scans: a full read of each table, reduced to what shows every row was read
_KEYS = {"region": "r_regionkey", "nation": "n_nationkey", "customer": "c_custkey", "supplier": "s_suppkey", "part": "p_partkey", "orders": "o_orderkey", "lineitem": "l_orderkey", "events": "event_id", "documents": "doc_id", "embeddings": "vec_id", "pages": "page_id", "benchmark": "item_id", "labels": "doc_id", "conversations": "conv_id"}
for _t, _k in _KEYS.items():
    op(f"s_scan_{_t}", f"select count(*) as n, min({_k}) as low, max({_k}) as high, sum({_k})::bigint as total from {_t}")(
        lambda t, a=_t, k=_k: t(a).agg(F.count("*").alias("n"), F.min(k).alias("low"), F.max(k).alias("high"), F.sum(k).alias("total")))


# projection and filter
@op("f_weight_cut", "select l_orderkey, l_linenumber, l_extendedprice from lineitem where l_extendedprice >= 50000 and l_discount < 0.02")
def _(t):
    return t("lineitem").where("l_extendedprice >= 50000 and l_discount < 0.02").select("l_orderkey", "l_linenumber", "l_extendedprice")


@op("f_between_in_like", "select p_partkey, p_name from part where p_size between 10 and 20 and p_type in (select min(p_type) from part union select max(p_type) from part) and p_name like '%ring%' and regexp_matches(p_name, '^(s|l|o)')")
def _(t):
    ends = t("part").agg(F.min("p_type").alias("a"), F.max("p_type").alias("b")).select(F.explode(F.array("a", "b")).alias("p_type"))
    return t("part").where("p_size between 10 and 20 and p_name like '%ring%' and p_name rlike '^(s|l|o)'").join(ends, "p_type", "left_semi").select("p_partkey", "p_name")


@op("f_nulls", "select count(*) as n, count(v) as known, sum(coalesce(v, 0))::bigint as filled, count(*) filter (where v is null) as missing from (select nullif(o_orderkey % 7, 3) as v from orders)")
def _(t):
    v = t("orders").select(F.nullif(F.col("o_orderkey") % 7, F.lit(3)).alias("v"))
    return v.agg(F.count("*").alias("n"), F.count("v").alias("known"), F.sum(F.coalesce("v", F.lit(0))).alias("filled"), F.count_if(F.col("v").isNull()).alias("missing"))


@op("f_case_band", "select case when l_quantity < 10 then 'light' when l_quantity < 30 then 'middle' else 'heavy' end as band, count(*) as n from lineitem group by 1")
def _(t):
    band = F.when(F.col("l_quantity") < 10, "light").when(F.col("l_quantity") < 30, "middle").otherwise("heavy")
    return t("lineitem").groupBy(band.alias("band")).agg(F.count("*").alias("n"))


@op("f_distinct", "select distinct p_brand, p_type from part")
def _(t):
    return t("part").select("p_brand", "p_type").distinct()


# joins
_LO = "select o_orderkey, o_custkey, l_linenumber from orders join lineitem on o_orderkey = l_orderkey"


def _lines_of_orders(t, hint):
    return t("orders").join(t("lineitem").hint(hint), F.col("o_orderkey") == F.col("l_orderkey")).select("o_orderkey", "o_custkey", "l_linenumber")


op("j_inner_hash", _LO)(lambda t: _lines_of_orders(t, "shuffle_hash"))
op("j_sort_merge", _LO)(lambda t: _lines_of_orders(t, "merge"))


@op("j_broadcast", "select n_name, r_name from nation join region on n_regionkey = r_regionkey")
def _(t):
    return t("nation").join(F.broadcast(t("region")), F.col("n_regionkey") == F.col("r_regionkey")).select("n_name", "r_name")  # 5 rows


@op("j_theta", "select a.n_nationkey as a, b.n_nationkey as b from nation a join nation b on a.n_regionkey < b.n_regionkey and a.n_name > b.n_name")
def _(t):
    a, b = t("nation").alias("a"), t("nation").alias("b")
    return a.join(b, (F.col("a.n_regionkey") < F.col("b.n_regionkey")) & (F.col("a.n_name") > F.col("b.n_name"))).select(F.col("a.n_nationkey").alias("a"), F.col("b.n_nationkey").alias("b"))


@op("j_range_band", "select p_partkey, s_suppkey from part join supplier on p_retailprice between s_acctbal - 5 and s_acctbal + 5")
def _(t):
    # an interval of width 10 touches at most two bands of 10: an equi-join on the band, then the exact test
    s = t("supplier").select("s_suppkey", "s_acctbal", F.explode(F.sequence(F.floor((F.col("s_acctbal") - 5) / 10), F.floor((F.col("s_acctbal") + 5) / 10))).alias("band"))
    p = t("part").select("p_partkey", "p_retailprice", F.floor(F.col("p_retailprice") / 10).alias("band"))
    return p.join(s, "band").where("p_retailprice between s_acctbal - 5 and s_acctbal + 5").select("p_partkey", "s_suppkey")


@op("j_interval_session", """with s as (select user_id, min(ts) as a, min(ts) + interval 2 day as b from events group by user_id) select s.user_id, count(*) as n, round(sum(e.value), 4) as total from s join events e on e.user_id = s.user_id and e.ts >= s.a and e.ts < s.b group by s.user_id""")
def _(t):
    e = t("events")
    s = e.groupBy("user_id").agg(F.min("ts").alias("a")).withColumn("b", F.expr("a + interval 2 days"))
    return e.join(s, "user_id").where("ts >= a and ts < b").groupBy("user_id").agg(F.count("*").alias("n"), F.round(F.sum("value"), 4).alias("total"))


@op("j_asof_order_event", "select event_id, o as last_order from events asof left join (select o_custkey, o_orderdate, max(o_orderkey) as o from orders group by all) on o_custkey = user_id and o_orderdate <= ts")
def _(t):
    # both inputs in one order a user; the last order seen is carried forward
    e = t("events").select(F.col("user_id").alias("u"), "ts", F.lit(1).alias("kind"), "event_id", F.lit(None).cast("long").alias("o"))
    o = t("orders").select(F.col("o_custkey").alias("u"), F.col("o_orderdate").alias("ts"), F.lit(0).alias("kind"), F.lit(None).cast("long").alias("event_id"), F.col("o_orderkey").alias("o"))
    line = W.partitionBy("u").orderBy("ts", "kind", F.col("o").asc_nulls_last()).rowsBetween(W.unboundedPreceding, W.currentRow)
    return e.union(o).withColumn("last_order", F.last("o", ignorenulls=True).over(line)).where("kind = 1").select("event_id", "last_order")


op("j_semi", "select c_custkey from customer where exists (select 1 from orders where o_custkey = c_custkey and o_totalprice > 300000)")(
    lambda t: t("customer").join(t("orders").where("o_totalprice > 300000"), F.col("c_custkey") == F.col("o_custkey"), "left_semi").select("c_custkey"))
op("j_anti", "select c_custkey from customer where not exists (select 1 from supplier where s_suppkey = c_custkey and s_nationkey <> c_nationkey)")(
    lambda t: t("customer").join(t("supplier"), (F.col("c_custkey") == F.col("s_suppkey")) & (F.col("c_nationkey") != F.col("s_nationkey")), "left_anti").select("c_custkey"))
op("j_left", "select c_custkey, count(o_orderkey) as n from customer left join orders on c_custkey = o_custkey group by c_custkey")(
    lambda t: t("customer").join(t("orders"), F.col("c_custkey") == F.col("o_custkey"), "left").groupBy("c_custkey").agg(F.count("o_orderkey").alias("n")))
op("j_right", "select s_suppkey, count(l_orderkey) as n from lineitem right join supplier on l_suppkey = s_suppkey group by s_suppkey")(
    lambda t: t("lineitem").join(t("supplier"), F.col("l_suppkey") == F.col("s_suppkey"), "right").groupBy("s_suppkey").agg(F.count("l_orderkey").alias("n")))
op("j_full", "select c_custkey as x, s_suppkey as y from customer full join supplier on c_custkey = s_suppkey and c_nationkey = s_nationkey")(
    lambda t: t("customer").join(t("supplier"), (F.col("c_custkey") == F.col("s_suppkey")) & (F.col("c_nationkey") == F.col("s_nationkey")), "full_outer").select(F.col("c_custkey").alias("x"), F.col("s_suppkey").alias("y")))


@op("j_cross_missing", "select a.n_nationkey as a, b.n_nationkey as b, count(s_suppkey) as lines from nation a join nation b on a.n_nationkey < b.n_nationkey left join (select c_nationkey, s_nationkey, s_suppkey from customer join orders on o_custkey = c_custkey join lineitem on l_orderkey = o_orderkey join supplier on l_suppkey = s_suppkey) on c_nationkey = a.n_nationkey and s_nationkey = b.n_nationkey group by all")
def _(t):
    n = t("nation").select("n_nationkey")  # 25 rows
    pairs = n.toDF("a").crossJoin(n.toDF("b")).where("a < b")
    met = t("lineitem").join(t("orders"), F.col("l_orderkey") == F.col("o_orderkey")).join(t("customer"), F.col("o_custkey") == F.col("c_custkey")).join(t("supplier"), F.col("l_suppkey") == F.col("s_suppkey"))
    met = met.groupBy(F.col("c_nationkey").alias("a"), F.col("s_nationkey").alias("b")).agg(F.count("*").alias("lines"))
    return pairs.join(met, ["a", "b"], "left").select("a", "b", F.coalesce("lines", F.lit(0)).alias("lines"))


@op("j_self", "select a.o_orderkey as x, b.o_orderkey as y from orders a join orders b on a.o_custkey = b.o_custkey and a.o_orderkey < b.o_orderkey where a.o_orderpriority = b.o_orderpriority")
def _(t):
    a, b = t("orders").alias("a"), t("orders").alias("b")
    return a.join(b, (F.col("a.o_custkey") == F.col("b.o_custkey")) & (F.col("a.o_orderpriority") == F.col("b.o_orderpriority")) & (F.col("a.o_orderkey") < F.col("b.o_orderkey"))).select(F.col("a.o_orderkey").alias("x"), F.col("b.o_orderkey").alias("y"))


@op("j_lateral_top_arcs", "select c_custkey, o_orderkey from (select c_custkey, o_orderkey, row_number() over (partition by c_custkey order by o_totalprice desc, o_orderkey) as rk from customer join orders on o_custkey = c_custkey) where rk <= 2")
def _(t):
    # the two dearest orders of each customer: a window instead of a subquery a row
    rk = F.row_number().over(W.partitionBy("o_custkey").orderBy(F.desc("o_totalprice"), "o_orderkey"))
    top = t("orders").withColumn("rk", rk).where("rk <= 2")
    return t("customer").join(top, F.col("c_custkey") == F.col("o_custkey")).select("c_custkey", "o_orderkey")


@op("j_lateral_join", "select c_custkey, o_orderkey from customer, lateral (select o_orderkey from orders where o_custkey = c_custkey order by o_totalprice desc, o_orderkey limit 2)")
def _(t):
    mine = t("orders").where(F.col("o_custkey") == F.col("c_custkey").outer()).orderBy(F.desc("o_totalprice"), "o_orderkey").limit(2).select("o_orderkey")
    return t("customer").lateralJoin(mine).select("c_custkey", "o_orderkey")


@op("j_null_safe", "select count(*) as n from (select nullif(c_nationkey, 3) as k from customer) a join (select nullif(s_nationkey, 3) as k from supplier) b on a.k is not distinct from b.k")
def _(t):
    a, b = t("customer").select(F.nullif("c_nationkey", F.lit(3)).alias("k")), t("supplier").select(F.nullif("s_nationkey", F.lit(3)).alias("j"))
    return a.join(b, F.col("k").eqNullSafe(F.col("j"))).agg(F.count("*").alias("n"))


# aggregates
op("a_group", "select l_returnflag, l_linestatus, count(*) as n, round(sum(l_extendedprice), 2) as total, round(avg(l_discount), 6) as mean from lineitem group by all")(
    lambda t: t("lineitem").groupBy("l_returnflag", "l_linestatus").agg(F.count("*").alias("n"), F.round(F.sum("l_extendedprice"), 2).alias("total"), F.round(F.avg("l_discount"), 6).alias("mean")))
op("a_distinct", "select l_returnflag, count(distinct l_partkey) as parts, count(distinct l_suppkey) as suppliers from lineitem group by l_returnflag")(
    lambda t: t("lineitem").groupBy("l_returnflag").agg(F.count_distinct("l_partkey").alias("parts"), F.count_distinct("l_suppkey").alias("suppliers")))
op("a_approx_distinct", None)(lambda t: t("lineitem").groupBy("l_returnflag").agg(F.approx_count_distinct("l_partkey", 0.02).alias("parts")))
op("a_rollup", "select p_brand, p_type, count(*) as n, sum(p_size)::bigint as size from part group by rollup (p_brand, p_type)")(
    lambda t: t("part").rollup("p_brand", "p_type").agg(F.count("*").alias("n"), F.sum("p_size").alias("size")))
op("a_cube", "select n_regionkey, c_mktsegment, count(*) as n from customer join nation on c_nationkey = n_nationkey group by cube (n_regionkey, c_mktsegment)")(
    lambda t: t("customer").join(F.broadcast(t("nation")), F.col("c_nationkey") == F.col("n_nationkey")).cube("n_regionkey", "c_mktsegment").agg(F.count("*").alias("n")))
op("a_grouping_sets", "select o_orderstatus, o_orderpriority, grouping(o_orderstatus)::int as g, count(*) as n from orders group by grouping sets ((o_orderstatus), (o_orderpriority), ())")(
    lambda t: t("orders").groupingSets([[F.col("o_orderstatus")], [F.col("o_orderpriority")], []], "o_orderstatus", "o_orderpriority").agg(F.grouping("o_orderstatus").cast("int").alias("g"), F.count("*").alias("n")))
op("a_pivot", "select l_returnflag, count(*) filter (where l_linestatus = 'O') as o, count(*) filter (where l_linestatus = 'F') as f from lineitem group by l_returnflag")(
    lambda t: t("lineitem").groupBy("l_returnflag").pivot("l_linestatus", ["O", "F"]).count().select("l_returnflag", F.coalesce("O", F.lit(0)).alias("o"), F.coalesce("F", F.lit(0)).alias("f")))
op("a_unpivot", "select s_suppkey, 'nation' as name, s_nationkey::double as v from supplier union all select s_suppkey, 'balance', s_acctbal from supplier")(
    lambda t: t("supplier").select("s_suppkey", F.col("s_nationkey").cast("double").alias("nation"), F.col("s_acctbal").alias("balance")).unpivot("s_suppkey", ["nation", "balance"], "name", "v"))
op("a_filter_clause", "select o_orderstatus, count(*) filter (where o_totalprice > 200000) as dear, round(sum(o_totalprice) filter (where o_orderpriority like '1%'), 2) as urgent from orders group by o_orderstatus")(
    lambda t: t("orders").groupBy("o_orderstatus").agg(F.count_if(F.col("o_totalprice") > 200000).alias("dear"), F.round(F.sum(F.when(F.col("o_orderpriority").like("1%"), F.col("o_totalprice"))), 2).alias("urgent")))
op("a_percentile", "select l_returnflag, round(quantile_cont(l_extendedprice, 0.5), 4) as mid, round(quantile_cont(l_extendedprice, 0.9), 4) as high from lineitem group by l_returnflag")(
    lambda t: t("lineitem").groupBy("l_returnflag").agg(F.round(F.percentile("l_extendedprice", 0.5), 4).alias("mid"), F.round(F.percentile("l_extendedprice", 0.9), 4).alias("high")))
op("a_approx_percentile", None)(lambda t: t("lineitem").groupBy("l_returnflag").agg(F.percentile_approx("l_extendedprice", 0.5, 1000).alias("mid")))
op("a_collect", "select p_brand, string_agg(distinct p_name, ',' order by p_name) as names from part group by p_brand")(
    lambda t: t("part").groupBy("p_brand").agg(F.array_join(F.array_sort(F.collect_set("p_name")), ",").alias("names")))
op("a_max_by_k", "select o_custkey, string_agg(o_orderkey::varchar, ',' order by o_totalprice desc, o_orderkey) as best from (select *, row_number() over (partition by o_custkey order by o_totalprice desc, o_orderkey) as rk from orders) where rk <= 3 group by o_custkey")(
    lambda t: t("orders").withColumn("rk", F.row_number().over(W.partitionBy("o_custkey").orderBy(F.desc("o_totalprice"), "o_orderkey"))).where("rk <= 3").groupBy("o_custkey").agg(F.array_join(F.transform(F.array_sort(F.collect_list(F.struct("rk", "o_orderkey"))), lambda s: s["o_orderkey"].cast("string")), ",").alias("best")))
op("a_moments", "select l_returnflag, round(stddev_samp(l_quantity), 6) as sd, round(var_pop(l_discount), 8) as var, round(corr(l_quantity, l_extendedprice), 6) as r from lineitem group by l_returnflag")(
    lambda t: t("lineitem").groupBy("l_returnflag").agg(F.round(F.stddev_samp("l_quantity"), 6).alias("sd"), F.round(F.var_pop("l_discount"), 8).alias("var"), F.round(F.corr("l_quantity", "l_extendedprice"), 6).alias("r")))
op("a_having", "select o_custkey, count(*) as n from orders group by o_custkey having count(*) > 15")(
    lambda t: t("orders").groupBy("o_custkey").agg(F.count("*").alias("n")).where("n > 15"))

# windows
def _lw():
    return W.partitionBy("l_orderkey").orderBy("l_linenumber", "l_partkey", "l_suppkey", "l_quantity", "l_extendedprice")


def _pw():
    return W.partitionBy("p_brand").orderBy("p_size")


_LWS = "over (partition by l_orderkey order by l_linenumber, l_partkey, l_suppkey, l_quantity, l_extendedprice)"
op("w_row_number", f"select l_orderkey, l_partkey, row_number() {_LWS} as rn from lineitem")(
    lambda t: t("lineitem").select("l_orderkey", "l_partkey", F.row_number().over(_lw()).alias("rn")))
op("w_rank_dense", "select p_partkey, rank() over w as r, dense_rank() over w as dr from part window w as (partition by p_brand order by p_size)")(
    lambda t: t("part").select("p_partkey", F.rank().over(_pw()).alias("r"), F.dense_rank().over(_pw()).alias("dr")))
op("w_ntile", "select p_partkey, ntile(4) over (partition by p_brand order by p_size, p_partkey)::int as q from part")(
    lambda t: t("part").select("p_partkey", F.ntile(4).over(W.partitionBy("p_brand").orderBy("p_size", "p_partkey")).alias("q")))
op("w_percent_rank", "select p_partkey, round(percent_rank() over w, 6) as pr, round(cume_dist() over w, 6) as cd from part window w as (partition by p_brand order by p_size)")(
    lambda t: t("part").select("p_partkey", F.round(F.percent_rank().over(_pw()), 6).alias("pr"), F.round(F.cume_dist().over(_pw()), 6).alias("cd")))
op("w_lag_lead", f"select l_orderkey, l_partkey, lag(l_partkey) {_LWS} as before, lead(l_partkey, 1, -1) {_LWS} as after from lineitem")(
    lambda t: t("lineitem").select("l_orderkey", "l_partkey", F.lag("l_partkey").over(_lw()).alias("before"), F.lead("l_partkey", 1, -1).over(_lw()).alias("after")))
op("w_first_last", "select o_orderkey, first_value(o_orderkey) over w as a, last_value(o_orderkey) over w as z, nth_value(o_orderkey, 2) over w as b from orders window w as (partition by o_custkey order by o_orderdate, o_orderkey rows between unbounded preceding and unbounded following)")(
    lambda t: t("orders").select("o_orderkey", *[f.over(W.partitionBy("o_custkey").orderBy("o_orderdate", "o_orderkey").rowsBetween(W.unboundedPreceding, W.unboundedFollowing)).alias(n) for f, n in ((F.first("o_orderkey"), "a"), (F.last("o_orderkey"), "z"), (F.nth_value("o_orderkey", 2), "b"))]))
op("w_running_sum", "select o_orderkey, round(sum(o_totalprice) over (partition by o_custkey order by o_orderdate, o_orderkey rows unbounded preceding), 2) as run from orders")(
    lambda t: t("orders").select("o_orderkey", F.round(F.sum("o_totalprice").over(W.partitionBy("o_custkey").orderBy("o_orderdate", "o_orderkey").rowsBetween(W.unboundedPreceding, W.currentRow)), 2).alias("run")))
op("w_range_frame", "select p_partkey, count(*) over (partition by p_brand order by p_size range between 5 preceding and 5 following) as near from part")(
    lambda t: t("part").select("p_partkey", F.count("*").over(W.partitionBy("p_brand").orderBy("p_size").rangeBetween(-5, 5)).alias("near")))
op("w_interval_frame", "select event_id, count(*) over (partition by user_id order by ts range between interval 1 day preceding and current row) as day from events")(
    lambda t: t("events").selectExpr("event_id", "count(*) over (partition by user_id order by ts range between interval 1 day preceding and current row) as day"))
op("w_topk_per_node", "select l_suppkey, l_orderkey, l_linenumber from (select *, row_number() over (partition by l_suppkey order by l_extendedprice desc, l_orderkey, l_linenumber, l_partkey) as rk from lineitem) where rk <= 3")(
    lambda t: t("lineitem").withColumn("rk", F.row_number().over(W.partitionBy("l_suppkey").orderBy(F.desc("l_extendedprice"), "l_orderkey", "l_linenumber", "l_partkey"))).where("rk <= 3").select("l_suppkey", "l_orderkey", "l_linenumber"))

# sorts and sets
op("o_sort_limit", "select o_orderkey, o_totalprice from orders order by o_totalprice desc, o_orderkey limit 25")(
    lambda t: t("orders").select("o_orderkey", "o_totalprice").orderBy(F.desc("o_totalprice"), "o_orderkey").limit(25))
op("o_offset", "select o_orderkey from orders order by o_totalprice desc, o_orderkey limit 10 offset 20")(
    lambda t: t("orders").orderBy(F.desc("o_totalprice"), "o_orderkey").offset(20).limit(10).select("o_orderkey"))
op("o_nulls_last", "select k from (select nullif(c_custkey % 50, 7) as k, c_custkey from customer) order by k desc nulls last, c_custkey limit 40")(
    lambda t: t("customer").select(F.nullif(F.col("c_custkey") % 50, F.lit(7)).alias("k"), "c_custkey").orderBy(F.col("k").desc_nulls_last(), "c_custkey").limit(40).select("k"))
op("o_topk", "select c_mktsegment, c_custkey from (select *, rank() over (partition by c_mktsegment order by c_acctbal desc) as r from customer) where r <= 5")(
    lambda t: t("customer").withColumn("r", F.rank().over(W.partitionBy("c_mktsegment").orderBy(F.desc("c_acctbal")))).where("r <= 5").select("c_mktsegment", "c_custkey"))
_A, _B = "select c_custkey as k from customer", "select s_suppkey as k from supplier"
for _n, _f in {"union_all": lambda a, b: a.unionAll(b), "union": lambda a, b: a.union(b).distinct(), "intersect": lambda a, b: a.intersect(b), "intersect_all": lambda a, b: a.intersectAll(b), "except": lambda a, b: a.subtract(b), "except_all": lambda a, b: a.exceptAll(b)}.items():
    op(f"u_{_n}", f"{_A} {_n.replace('_', ' ')} {_B}")(lambda t, f=_f: f(t("customer").select(F.col("c_custkey").alias("k")), t("supplier").select(F.col("s_suppkey").alias("k"))))


# sampling: every row has its fate by its key, so a run can be repeated
@op("o_sample_stable", None)
def _(t):
    return t("orders").where(F.pmod(F.xxhash64(F.lit("sample"), "o_orderkey"), F.lit(10)) == 0).select("o_orderkey")


op("o_sample", None)(lambda t: t("orders").sample(fraction=0.1, seed=7).select("o_orderkey"))
op("o_sample_by", None)(lambda t: t("orders").sampleBy("o_orderstatus", {"O": 0.1, "F": 0.05, "P": 1.0}, seed=7).select("o_orderkey", "o_orderstatus"))

# sketches against exact values: how far off they are, so that a reader sees it
op("a_sketch_kll", None)(lambda t: t("lineitem").groupBy("l_returnflag").agg(F.expr("kll_sketch_get_quantile_double(kll_sketch_agg_double(l_extendedprice), 0.5D)").alias("mid"), F.percentile("l_extendedprice", 0.5).alias("exact")))
op("a_sketch_hll", None)(lambda t: t("lineitem").groupBy("l_returnflag").agg(F.hll_sketch_estimate(F.hll_sketch_agg("l_partkey", 12)).alias("parts"), F.count_distinct("l_partkey").alias("exact")))


@op("a_sketch_count_min", None)
def _(t):
    """Counts of parts from a count-min table of 4 x 4,096 cells: never below the truth."""
    cell = lambda i: F.pmod(F.xxhash64(F.lit(i), "l_partkey"), F.lit(4096)).alias("cell")
    rows = [t("lineitem").groupBy(F.lit(i).alias("line"), cell(i)).agg(F.count("*").alias("n")) for i in range(4)]
    table = rows[0].union(rows[1]).union(rows[2]).union(rows[3])
    parts = t("lineitem").groupBy("l_partkey").agg(F.count("*").alias("exact"))
    asked = parts.select("l_partkey", "exact", F.inline(F.array(*[F.struct(F.lit(i).alias("line"), cell(i)) for i in range(4)])))
    return asked.join(table, ["line", "cell"]).groupBy("l_partkey", "exact").agg(F.min("n").alias("estimate"))


@op("j_bloom", "select l_orderkey, l_linenumber from lineitem where exists (select 1 from orders where o_orderkey = l_orderkey and o_totalprice > 300000)")
def _(t):
    """A bit table of the small side (2^20 bits as 64-bit words, or-ed by word) drops rows before the exact semi join."""
    bits = 20
    at = lambda c, i: F.pmod(F.xxhash64(F.lit(i), c), F.lit(1 << bits))
    dear = t("orders").where("o_totalprice > 300000").select("o_orderkey")
    ones = dear.select(F.explode(F.array(*[at("o_orderkey", i) for i in range(3)])).alias("bit"))
    words = ones.groupBy((F.col("bit") / 64).cast("int").alias("word")).agg(F.bit_or(F.expr("shiftleft(1L, cast(bit % 64 as int))")).alias("mask"))
    table = words.agg(F.map_from_entries(F.collect_list(F.struct("word", "mask"))).alias("table"))  # one row of at most 2^14 words
    has = [F.coalesce(F.expr(f"shiftright(table[cast(b{i} / 64 as int)], cast(b{i} % 64 as int))").bitwiseAND(F.lit(1)), F.lit(0)) == 1 for i in range(3)]
    line = t("lineitem").select("l_orderkey", "l_linenumber", *[at("l_orderkey", i).alias(f"b{i}") for i in range(3)]).crossJoin(F.broadcast(table))
    return line.where(has[0] & has[1] & has[2]).join(dear, F.col("l_orderkey") == F.col("o_orderkey"), "left_semi").select("l_orderkey", "l_linenumber")
