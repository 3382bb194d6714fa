"""Chat formatting: logged conversations that are a prefix of a longer one are dropped, the rest is rendered.

A chat log often holds every state of a conversation. Each turn's fingerprint covers its number, role and text; a running
sum of fingerprints gives every prefix of every conversation a (turns, lanes) key. A conversation whose full key is also
a proper prefix of another goes; of conversations with the same full key the smallest id stays. Keys are compared after
pre-aggregation, so a first turn shared by a third of all logs is one row a task. Running sums are made in two levels
(inside stretches of turn numbers, then over stretches), so a single huge conversation is spread too. It is rendered in
stretches as well: one row for each STRETCH turn numbers, whose texts joined in the order of `chunk` are the whole chat.

Edge cases: null role or text counts as empty; equal turns of one conversation count each time; turns with one number form
one step and stand in the order of their rendered text; a null turn counts as 0; a null conv_id is one conversation of its own; turns are compared by their logged numbers, counted from the
conversation's first; an empty table gives no rows; extra columns are ignored; a very long text is one turn like any other.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from . import common

STRETCH = 512
_LANES = 3


def _lane(k: int) -> Column:
    """31 bits of a turn's fingerprint; sums of them don't overflow."""
    return F.pmod(F.xxhash64(F.lit(k), F.col("step"), F.coalesce("role", F.lit("")), F.coalesce("text", F.lit(""))), F.lit((1 << 31) - 1))


def prefixes(turns: DataFrame) -> DataFrame:
    """(conv_id, step, n, k0, k1, k2): the key of each conversation's prefix up to each turn."""
    base = turns.groupBy("conv_id").agg(F.min("turn").alias("first"))
    rows = turns.select("conv_id", "turn", "role", "text").alias("t").join(base.alias("b"), F.col("t.conv_id").eqNullSafe(F.col("b.conv_id")))
    rows = rows.select("t.conv_id", (F.coalesce("t.turn", F.lit(0)) - F.coalesce("b.first", F.lit(0))).alias("step"), "t.role", "t.text")
    lanes = [f"k{k}" for k in range(_LANES)]
    steps = rows.select("conv_id", "step", F.lit(1).cast("long").alias("n"), *[_lane(k).alias(f"k{k}") for k in range(_LANES)]).groupBy("conv_id", "step").agg(*[F.sum(c).alias(c) for c in ("n", *lanes)])
    steps = steps.withColumn("stretch", F.floor(F.col("step") / STRETCH))
    inside = Window.partitionBy("conv_id", "stretch").orderBy("step").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    before = Window.partitionBy("conv_id").orderBy("stretch").rowsBetween(Window.unboundedPreceding, -1)
    whole = steps.groupBy("conv_id", "stretch").agg(*[F.sum(c).alias(c) for c in ("n", *lanes)])
    whole = whole.select("conv_id", "stretch", *[F.coalesce(F.sum(c).over(before), F.lit(0)).alias(f"{c}_before") for c in ("n", *lanes)])
    steps = steps.select("conv_id", "step", "stretch", *[F.sum(c).over(inside).alias(c) for c in ("n", *lanes)])
    on = F.col("s.conv_id").eqNullSafe(F.col("w.conv_id")) & (F.col("s.stretch") == F.col("w.stretch"))
    return steps.alias("s").join(whole.alias("w"), on).select("s.conv_id", "s.step", *[(F.col(f"s.{c}") + F.col(f"w.{c}_before")).alias(c) for c in ("n", *lanes)])


def maximal(turns: DataFrame, scratch: common.Scratch | None = None) -> DataFrame:
    """(conv_id, n_turns) of the conversations that stay; the prefixes lie in `scratch`, to be cleared once the result is written."""
    keys = ["n", *[f"k{k}" for k in range(_LANES)]]
    rows = (scratch or common.Scratch()).spill(prefixes(turns), "chat-prefixes")
    full = rows.groupBy("conv_id").agg(F.max_by(F.struct(*keys), "step").alias("full")).select("conv_id", "full.*")
    ends = full.withColumn("ends", F.lit(True))
    inner = rows.alias("r").join(full.alias("f"), F.col("r.conv_id").eqNullSafe(F.col("f.conv_id"))).where("r.n < f.n").select(*[F.col(f"r.{c}").alias(c) for c in keys]).distinct()
    firsts = ends.groupBy(*keys).agg(F.min("conv_id").alias("conv_id"))  # of equal conversations the smallest id; a null id only where alone
    return firsts.join(inner, keys, "left_anti").select("conv_id", F.col("n").alias("n_turns"))


def render(turns: DataFrame, kept: DataFrame) -> DataFrame:
    """(conv_id, n_turns, chunk, chat): each turn as a role line and its text, in turn order, a row for each stretch of turn numbers."""
    piece = F.concat(F.lit("<|"), F.coalesce("t.role", F.lit("")), F.lit("|>\n"), F.coalesce("t.text", F.lit("")), F.lit("\n"))
    turn = F.coalesce("t.turn", F.lit(0)).cast("long")
    rows = turns.alias("t").join(kept.alias("k"), F.col("t.conv_id").eqNullSafe(F.col("k.conv_id"))).select("t.conv_id", "k.n_turns", F.floor(turn / STRETCH).alias("chunk"), F.struct(turn.alias("turn"), piece.alias("piece")).alias("x"))
    return rows.groupBy("conv_id", "n_turns", "chunk").agg(F.array_sort(F.collect_list("x")).alias("x")).select("conv_id", "n_turns", "chunk", F.array_join(F.col("x.piece"), "").alias("chat"))


def op5_chat_snapshots(spark: SparkSession, sf_dir: str) -> DataFrame:
    turns = common.table(spark, sf_dir, "conversations")
    scratch = common.Scratch()
    kept = common.spill(maximal(turns, scratch), "chat-kept")
    scratch.clear()
    return render(turns, kept)


ORACLE = """
with t as (select conv_id, turn - min(turn) over (partition by conv_id) as step, turn, coalesce(role,'') as role, coalesce(text,'') as text from conversations),
p as (select conv_id, step, count(*) over w as n, md5(string_agg(step::varchar || chr(1) || role || chr(2) || text, chr(3)) over w) as k
  from t window w as (partition by conv_id order by step, role, text rows between unbounded preceding and current row)),
f as (select conv_id, max(n) as n, arg_max(k, n) as k from p group by conv_id),
stay as (select n, k, min(conv_id) as conv_id from f group by n, k),
m as (select conv_id, n from stay s where not exists (select 1 from p join f on p.conv_id = f.conv_id where p.n < f.n and p.n = s.n and p.k = s.k))
select m.conv_id, m.n::bigint as n_turns, floor(turn / 512)::bigint as chunk, string_agg('<|' || role || '|>' || chr(10) || text || chr(10), '' order by turn, '<|' || role || '|>' || chr(10) || text) as chat
from m join t on t.conv_id = m.conv_id group by m.conv_id, m.n, floor(turn / 512)
"""
