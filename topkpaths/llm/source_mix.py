"""Mixing sources to target weights: capped water-filling, then whole and fractional seeded repetitions.

Water-filling: source i has size S_i and weight w_i; its target is min(c * S_i, level * w_i) with the level at which
the targets add up to the wanted total. Sorted by c * S_i / w_i the capped sources form a prefix, so two running sums
over the (small) source table give the level at once.

Sampling: with e = target / S, every document is taken floor(e) times; for the rest, documents of a source stand in a
seeded order (md5 of seed and id) and are taken once more up to the place where the wanted words are reached. The
place is found from a histogram of the order (a fixed number of bins a source) and a running sum inside one bin, so no
source, however large, meets in one task. One more document, the largest that still fits, closes most of what is left.

Edge cases: null text has size 0; a null source is a source of its own, ordered last; documents with equal id and
size share their fate; empty tables give no rows; extra columns are ignored (`mix`) or kept (`materialise`).
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from . import common

#: Weights by rank of the source, and the most repetitions.
WEIGHTS, MAX_EPOCHS, SEED = (5, 2, 1), 3, "mix-1"
#: Hex digits of the order that make a histogram bin.
BIN_DIGITS = 3


def size_of(text: Column) -> Column:
    return F.coalesce(F.regexp_count(text, F.lit(common.WORD_PATTERN)), F.lit(0)).cast("long")


def targets(sizes: DataFrame, weights=WEIGHTS, cap: int = MAX_EPOCHS, share: float = 1.0) -> DataFrame:
    """(source, source_size) -> with weight, target. One row a source; `share` of all words is to be taken."""
    everything = Window.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    ranked = sizes.withColumn("k", F.row_number().over(Window.orderBy(F.col("source").asc_nulls_last())))
    weight = F.element_at(F.array(*[F.lit(int(w)) for w in weights]), (F.pmod(F.col("k") - 1, F.lit(len(weights))) + 1).cast("int"))
    w = ranked.withColumn("weight", weight.cast("long")).withColumn("cap", F.col("source_size") * cap)
    by_ratio = Window.orderBy(F.col("cap") / F.col("weight"), "k")
    before = by_ratio.rowsBetween(Window.unboundedPreceding, -1)
    w = w.select(
        "*", F.coalesce(F.sum("cap").over(before), F.lit(0)).alias("cap_before"), F.coalesce(F.sum("weight").over(before), F.lit(0)).alias("weight_before"),
        F.sum("source_size").over(everything).alias("total"), F.sum("weight").over(everything).alias("all_weight"),
    )
    wanted = F.col("total") if share == 1.0 else F.floor(F.col("total") * F.lit(float(share)))
    w = w.withColumn("level", (wanted - F.col("cap_before")) / (F.col("all_weight") - F.col("weight_before")))
    # the first source that its level does not fill settles the level of all after it
    w = w.withColumn("open_level", F.min(F.when(F.col("level") * F.col("weight") < F.col("cap"), F.struct("cap_before", "level"))).over(everything)["level"])
    capped = F.col("open_level").isNull() | (F.col("open_level") * F.col("weight") >= F.col("cap"))
    return w.select("source", "source_size", "weight", F.when(capped, F.col("cap").cast("double")).otherwise(F.col("open_level") * F.col("weight")).alias("target"), capped.alias("capped"))


def _order(seed: str) -> Column:
    return F.md5(F.concat(F.lit(seed), F.lit(":"), F.coalesce(F.col("doc_id").cast("string"), F.lit(""))).cast("binary"))


def plan(narrow: DataFrame, cap: int = MAX_EPOCHS, weights=WEIGHTS, share: float = 1.0) -> DataFrame:
    """One row a source: source, target, whole repetitions, the cut of the seeded order, and the document that fills up.

    narrow: doc_id, source, size, place (the seeded order).
    """
    bins = narrow.groupBy("source", F.substring("place", 1, BIN_DIGITS).alias("bin")).agg(F.sum("size").alias("bin_size"))
    bins = common.spill(bins, "mix-bins")
    goal = targets(bins.groupBy("source").agg(F.sum("bin_size").alias("source_size")), weights, cap, share)
    epochs = F.when(F.col("source_size") == 0, F.lit(0)).otherwise(F.floor(F.col("target") / F.col("source_size")))
    goal = goal.withColumn("whole", F.when(F.col("capped"), F.lit(cap)).otherwise(epochs).cast("long"))
    goal = goal.withColumn("rest", F.when(F.col("capped"), F.lit(0.0)).otherwise(F.col("target") - F.col("whole") * F.col("source_size")))
    goal = common.spill(goal, "mix-goal")
    same = lambda a, b: a["source"].eqNullSafe(b["source"])
    g, b = goal.alias("g"), bins.alias("b")
    upto = Window.partitionBy("source").orderBy("bin").rowsBetween(Window.unboundedPreceding, -1)
    b = bins.withColumn("below", F.coalesce(F.sum("bin_size").over(upto), F.lit(0))).alias("b")
    edge = (
        b.join(g, F.col("b.source").eqNullSafe(F.col("g.source")))
        .where("g.rest > 0 and b.below <= g.rest and b.below + b.bin_size > g.rest")
        .select(F.col("b.source").alias("source"), F.col("b.bin").alias("bin"), F.col("b.below").alias("below"), F.col("g.rest").alias("rest"))
    )
    n = narrow.withColumn("bin", F.substring("place", 1, BIN_DIGITS)).alias("n")
    inside = n.join(edge.alias("e"), F.col("n.source").eqNullSafe(F.col("e.source")) & (F.col("n.bin") == F.col("e.bin"))).select("n.source", "n.place", "n.doc_id", "n.size", "e.below", "e.rest")
    run = Window.partitionBy("source").orderBy("place", "doc_id", "size").rangeBetween(Window.unboundedPreceding, Window.currentRow)
    inside = inside.withColumn("sum", F.col("below") + F.sum("size").over(run))
    # the last document of the order that still fits; where none of the bin does, all bins before it are taken
    cut = inside.groupBy("source").agg(
        F.max(F.when(F.col("sum") <= F.col("rest"), F.struct("place", "doc_id", "size"))).alias("cut"),
        F.max(F.when(F.col("sum") <= F.col("rest"), F.col("sum"))).alias("reached"),
    )
    cut = edge.alias("e").join(cut.alias("c"), F.col("e.source").eqNullSafe(F.col("c.source")), "left").select("e.source", "e.bin", "c.cut", F.coalesce("c.reached", "e.below").alias("reached"), (F.col("e.rest") - F.coalesce("c.reached", "e.below")).alias("gap"))
    cut = common.spill(cut, "mix-cut")
    # one filler a source: the document after the cut that leaves the smallest gap, if it leaves a smaller one
    after = narrow.alias("n").join(cut.alias("c"), F.col("n.source").eqNullSafe(F.col("c.source"))).where(~_taken("n", "c") & (F.col("n.size") > 0) & (F.abs(F.col("n.size") - F.col("c.gap")) < F.col("c.gap")))
    filler = after.groupBy(F.col("n.source").alias("source")).agg(F.min_by(F.struct("n.doc_id", "n.size", "n.place"), F.struct(F.abs(F.col("n.size") - F.col("c.gap")), F.col("n.place"), F.col("n.doc_id"))).alias("filler"), F.lit(1).alias("one"))
    out = goal.alias("g").join(cut.alias("c"), F.col("g.source").eqNullSafe(F.col("c.source")), "left").join(filler.alias("f"), F.col("g.source").eqNullSafe(F.col("f.source")), "left")
    out = out.select("g.source", "g.source_size", "g.target", "g.whole", "g.rest", "c.bin", "c.cut", "f.filler")
    return common.spill(out, "mix-plan")


def _taken(row: str, cut: str) -> Column:
    """Whether the seeded order takes the row once more."""
    key = F.struct(F.col(f"{row}.place"), F.col(f"{row}.doc_id"), F.col(f"{row}.size"))
    below = F.substring(F.col(f"{row}.place"), 1, BIN_DIGITS) < F.col(f"{cut}.bin")
    return F.coalesce(F.when(F.col(f"{cut}.cut").isNull(), below).otherwise(key <= F.col(f"{cut}.cut")), F.lit(False))


def _repeats(row: str, cut: str) -> Column:
    same = F.coalesce((F.struct(F.col(f"{row}.doc_id"), F.col(f"{row}.size"), F.col(f"{row}.place")).eqNullSafe(F.col(f"{cut}.filler"))), F.lit(False))
    return F.col(f"{cut}.whole") + (_taken(row, cut) | same).cast("long")


def _narrow(docs: DataFrame, seed: str) -> DataFrame:
    return docs.select("doc_id", "source", size_of(F.col("text")).alias("size"), _order(seed).alias("place"))


def mix(docs: DataFrame, weights=WEIGHTS, cap: int = MAX_EPOCHS, seed: str = SEED, share: float = 1.0) -> DataFrame:
    """(doc_id, size, source_size, target, repeats, taken) for every document."""
    narrow = common.spill(_narrow(docs, seed), "mix-narrow")
    p = plan(narrow, cap, weights, share)
    out = narrow.alias("n").join(p.alias("p"), F.col("n.source").eqNullSafe(F.col("p.source"))).withColumn("repeats", _repeats("n", "p"))
    return out.select("n.doc_id", F.col("n.size").alias("size"), F.col("p.source_size").alias("source_size"), F.col("p.target").alias("target"), "repeats", (F.col("n.size") * F.col("repeats")).alias("taken"))


def materialise(docs: DataFrame, weights=WEIGHTS, cap: int = MAX_EPOCHS, seed: str = SEED, share: float = 1.0) -> DataFrame:
    """The mixed corpus: each document as often as the mix takes it, columns unchanged. The text is not shuffled."""
    narrow = common.spill(_narrow(docs, seed), "mix-narrow")
    p = plan(narrow, cap, weights, share)
    rows = docs.select(F.struct(*[docs[c] for c in docs.columns]).alias("row"), docs["doc_id"].alias("doc_id"), docs["source"].alias("source"), size_of(docs["text"]).alias("size"), _order(seed).alias("place"))
    out = rows.alias("n").join(p.alias("p"), F.col("n.source").eqNullSafe(F.col("p.source"))).select("n.row", _repeats("n", "p").alias("repeats")).where("repeats > 0")
    return out.select("row", F.explode(F.sequence(F.lit(1), F.col("repeats").cast("int"))).alias("copy")).select("row.*")


def op3_source_mix(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mix(common.table(spark, sf_dir, "documents"))


ORACLE = r"""
with recursive d as (select doc_id, source, coalesce(len(regexp_extract_all(text, '[^\x20\x09-\x0D]+')), 0)::bigint as size, md5('mix-1:' || coalesce(doc_id::varchar, '')) as place from documents),
s as (select source, sum(size)::bigint as source_size from d group by source),
w as (select *, [5,2,1][((row_number() over (order by source asc nulls last) - 1) % 3 + 1)::int] as weight, 3 * source_size as cap from s),
rounds(n, source, source_size, weight, cap, fixed) as (
  select 0, source, source_size, weight, cap, false from w
  union all
  select n + 1, source, source_size, weight, cap, fixed or level * weight >= cap from (
    select *, ((sum(source_size) over ())::double - (sum(case when fixed then cap else 0 end) over ())::double) / nullif((sum(case when fixed then 0 else weight end) over ())::double, 0) as level from rounds where n < 40) r),
last as (select * from rounds where n = 40),
lev as (select *, ((sum(source_size) over ())::double - (sum(case when fixed then cap else 0 end) over ())::double) / nullif((sum(case when fixed then 0 else weight end) over ())::double, 0) as level from last),
goal as (select source, source_size, case when fixed then cap::double else level * weight end as target, fixed,
  case when fixed then 3 when source_size = 0 then 0 else floor(level * weight / source_size)::bigint end as whole from lev),
run as (select d.*, g.source_size, g.target, g.whole, case when g.fixed then 0.0 else g.target - (g.whole * g.source_size)::double end as rest,
  sum(size) over (partition by d.source order by place, d.doc_id, size) as upto from d join goal g on d.source is not distinct from g.source),
cut as (select *, upto <= rest and rest > 0 as inn, rest - coalesce(max(case when upto <= rest then upto end) over (partition by source), 0) as gap from run),
fill as (select *, row_number() over (partition by source order by case when not inn and rest > 0 and size > 0 and abs(size - gap) < gap then 0 else 1 end, abs(size - gap), place, doc_id) = 1
  and (not inn and rest > 0 and size > 0 and abs(size - gap) < gap) as filler from cut)
select doc_id, size, source_size, target, (whole + (case when inn or filler then 1 else 0 end))::bigint as repeats, (size * (whole + (case when inn or filler then 1 else 0 end)))::bigint as taken from fill
"""
