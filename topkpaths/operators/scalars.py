"""Scalar functions on the given tables, with SQL twins."""

from __future__ import annotations

from pyspark.sql import functions as F

from .relational import op as _op
from . import relational

QUERIES: dict = {}
ORACLES: dict = {}


def op(name, sql):
    def add(f):
        _op(name, sql)(f)
        QUERIES[name] = relational.QUERIES.pop(name)
        if sql:
            ORACLES[name] = relational.ORACLES.pop(name)
        return f

    return add


op("x_string", "select p_partkey, upper(p_name) as u, length(p_name) as n, substr(p_name, 2, 4) as s, replace(p_name, ' ', '_') as r, lpad(p_brand, 12, '*') as l, trim(p_type) as t, split_part(p_name, ' ', 1) as w, levenshtein(p_name, p_type)::int as d from part")(
    lambda t: t("part").select("p_partkey", F.upper("p_name").alias("u"), F.length("p_name").cast("long").alias("n"), F.substring("p_name", 2, 4).alias("s"), F.replace("p_name", F.lit(" "), F.lit("_")).alias("r"), F.lpad("p_brand", 12, "*").alias("l"), F.trim("p_type").alias("t"), F.split_part("p_name", F.lit(" "), F.lit(1)).alias("w"), F.levenshtein("p_name", "p_type").alias("d")))
op("x_regex", r"select doc_id, len(regexp_extract_all(text, '[A-Z][a-z]+'))::int as names, regexp_extract(text, '([a-z]+)\.', 1) as last_word, length(regexp_replace(text, '[aeiou]', '', 'g'))::int as bare from documents")(
    lambda t: t("documents").select("doc_id", F.size(F.regexp_extract_all("text", F.lit("([A-Z][a-z]+)"), F.lit(1))).alias("names"), F.regexp_extract("text", r"([a-z]+)\.", 1).alias("last_word"), F.length(F.regexp_replace("text", "[aeiou]", "")).alias("bare")))
op("x_url", "select page_id, regexp_extract(url, '^([a-z]+)://', 1) as scheme, regexp_extract(url, '://([^/?#]*)', 1) as host, regexp_extract(url, '://[^/?#]*([^?#]*)', 1) as path from pages")(
    lambda t: t("pages").select("page_id", F.parse_url("url", F.lit("PROTOCOL")).alias("scheme"), F.parse_url("url", F.lit("HOST")).alias("host"), F.parse_url("url", F.lit("PATH")).alias("path")))
op("x_date", "select o_orderkey, year(o_orderdate)::int as y, month(o_orderdate)::int as m, date_trunc('month', o_orderdate)::date as f, (last_day(o_orderdate))::date as l, date_diff('day', date '1992-01-01', o_orderdate::date)::int as n from orders")(
    lambda t: t("orders").select("o_orderkey", F.year("o_orderdate").alias("y"), F.month("o_orderdate").alias("m"), F.to_date(F.date_trunc("month", "o_orderdate")).alias("f"), F.last_day("o_orderdate").alias("l"), F.datediff(F.to_date("o_orderdate"), F.lit("1992-01-01").cast("date")).alias("n")))
op("x_interval", "select event_id, (ts + interval 90 minute)::timestamp as later, date_diff('minute', date_trunc('day', ts), date_trunc('minute', ts))::bigint as minute from events")(
    lambda t: t("events").select("event_id", F.expr("ts + interval 90 minutes").alias("later"), F.expr("hour(ts) * 60L + minute(ts)").cast("long").alias("minute")))
op("x_math", "select l_orderkey, l_linenumber, l_partkey, round(ln(l_extendedprice), 6) as a, round(exp(l_discount), 6) as b, round(sqrt(l_quantity), 6) as c, round(pow(l_tax, 2), 6) as d, greatest(l_discount, l_tax) as g, least(l_discount, l_tax) as s, (l_partkey % 17)::bigint as m from lineitem")(
    lambda t: t("lineitem").select("l_orderkey", "l_linenumber", "l_partkey", F.round(F.ln("l_extendedprice"), 6).alias("a"), F.round(F.exp("l_discount"), 6).alias("b"), F.round(F.sqrt("l_quantity"), 6).alias("c"), F.round(F.pow("l_tax", F.lit(2)), 6).alias("d"), F.greatest("l_discount", "l_tax").alias("g"), F.least("l_discount", "l_tax").alias("s"), (F.col("l_partkey") % 17).alias("m")))
_NODES = "select o_custkey, list(o_orderkey order by o_orderdate, o_orderkey) as n from orders group by o_custkey"


def _nodes(t):
    """Each customer's orders in time: a path-like array."""
    s = F.array_sort(F.collect_list(F.struct("o_orderdate", "o_orderkey")))
    return t("orders").groupBy("o_custkey").agg(F.transform(s, lambda x: x["o_orderkey"]).alias("n"))


op("x_array", f"select o_custkey, len(n)::int as size, n[1] as a, n[len(n)] as z, array_to_string(list_reverse(n), '>') as back, array_to_string(n[2:4], '>') as mid, list_contains(n, n[1] + 1) as has, array_to_string(list_sort(n), '>') as sorted from ({_NODES})")(
    lambda t: _nodes(t).select("o_custkey", F.size("n").alias("size"), F.element_at("n", 1).alias("a"), F.element_at("n", -1).alias("z"), F.array_join(F.reverse(F.col("n").cast("array<string>")), ">").alias("back"), F.array_join(F.slice("n", 2, 3).cast("array<string>"), ">").alias("mid"), F.array_contains("n", F.element_at("n", 1) + 1).alias("has"), F.array_join(F.array_sort("n").cast("array<string>"), ">").alias("sorted")))
op("x_higher_order", f"select o_custkey, list_sum([x % 10 for x in n])::bigint as total, len([x for x in n if x % 2 = 0])::int as even, coalesce(list_bool_or([x > 100 for x in n]), false) as big from ({_NODES})")(
    lambda t: _nodes(t).select("o_custkey", F.aggregate("n", F.lit(0).cast("long"), lambda s, x: s + x % 10).alias("total"), F.size(F.filter("n", lambda x: x % 2 == 0)).alias("even"), F.exists("n", lambda x: x > 100).alias("big")))
op("x_explode", "select vec_id, i::int as i, round(v::double, 6) as v from (select vec_id, unnest(embedding) as v, generate_subscripts(embedding, 1) - 1 as i from embeddings) where i < 3")(
    lambda t: t("embeddings").select("vec_id", F.posexplode("embedding").alias("i", "v")).where("i < 3").select("vec_id", "i", F.round(F.col("v").cast("double"), 6).alias("v")))
op("x_map", "select n_regionkey, count(*)::int as size, max(case when n_name = (select min(n_name) from nation) then n_nationkey end) as found from nation group by n_regionkey")(
    lambda t: t("nation").groupBy("n_regionkey").agg(F.map_from_entries(F.collect_list(F.struct("n_name", "n_nationkey"))).alias("m")).crossJoin(t("nation").agg(F.min("n_name").alias("first"))).select("n_regionkey", F.size("m").alias("size"), F.expr("try_element_at(m, first)").alias("found")))
op("x_json", "select event_id, (props->>'$.k')::bigint as k from events")(
    lambda t: t("events").select("event_id", F.from_json("props", "k long")["k"].alias("k")))
op("x_variant", "select event_id, (props->>'$.k')::bigint as k from events where (props->>'$.k')::bigint > 50")(
    lambda t: t("events").select("event_id", F.variant_get(F.parse_json("props"), "$.k", "long").alias("k")).where("k > 50"))
op("x_md5", "select doc_id, md5(coalesce(text, '')) as h, sha256(coalesce(text, '')) as s from documents")(
    lambda t: t("documents").select("doc_id", F.md5(F.coalesce("text", F.lit("")).cast("binary")).alias("h"), F.sha2(F.coalesce("text", F.lit("")).cast("binary"), 256).alias("s")))
op("x_hash", None)(lambda t: t("orders").select("o_orderkey", F.xxhash64("o_orderkey", "o_custkey").alias("h")))
op("x_sketch", None)(lambda t: t("lineitem").groupBy("l_returnflag").agg(F.hll_sketch_estimate(F.hll_sketch_agg("l_partkey", 12)).alias("parts")))
