"""Cost and accuracy measures over results and runs."""

from __future__ import annotations

import time

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from .. import bounds
from ..graph.model import Graph
from ..paths.budgeted import budgeted_search
from ..paths.canonical_growth import canonical_growth


def timed(call):
    """(result, seconds); the answers are on the driver by then."""
    began = time.perf_counter()
    out = call()
    return out, time.perf_counter() - began


def coherence(paths: DataFrame, groups: DataFrame) -> DataFrame:
    """(rank, group, share): how much of each path is of its commonest group; groups: (id, group)."""
    per = paths.select("rank", F.explode("nodes").alias("id")).join(groups, "id").groupBy("rank", "group").agg(F.count("*").alias("n"))
    total = Window.partitionBy("rank")
    first = Window.partitionBy("rank").orderBy(F.desc("n"), "group")
    return per.select("rank", "group", F.round(F.col("n") / F.sum("n").over(total), 4).alias("share"), F.row_number().over(first).alias("rk")).where("rk = 1").drop("rk")


def overlap(paths: DataFrame) -> DataFrame:
    """(a, b, shared): nodes that two answers share. k answers."""
    x, y = paths.select(F.col("rank").alias("a"), F.col("nodes").alias("na")), paths.select(F.col("rank").alias("b"), F.col("nodes").alias("nb"))
    return x.join(y, F.col("a") < F.col("b")).select("a", "b", F.size(F.array_intersect("na", "nb")).alias("shared"))


def surprise(paths: DataFrame, seen: DataFrame) -> DataFrame:
    """(rank, share): nodes of each answer that a user has not seen; seen: (id)."""
    at = paths.select("rank", F.explode("nodes").alias("id")).join(seen.withColumn("known", F.lit(1)), "id", "left")
    return at.groupBy("rank").agg(F.round(F.avg(F.when(F.col("known").isNull(), 1.0).otherwise(0.0)), 4).alias("share"))


def optimal_weights(g: Graph, upto: int) -> dict[int, int]:
    """Best weight of each length, by the exact method."""
    out = {}
    for i in range(1, upto + 1):
        row = canonical_growth(g, i, 1).paths.first()
        if row is not None:
            out[i] = row["weight"]
    return out


def bound_table(spark: SparkSession, g: Graph, upto: int, lengths) -> DataFrame:
    """(length, bound): worst-case bounds from the optimal weights of lengths up to `upto`; null where no path of that length exists, as then none is longer."""
    best = optimal_weights(g, upto)
    rows = [(n, int(bounds.split_bound(best, n, upto + 1, g.max_w)) if upto in best else None) for n in lengths]
    return spark.createDataFrame(rows, "length int, bound bigint")


def rho_table(spark: SparkSession, g: Graph, lengths, budgets) -> DataFrame:
    """(length, budget, weight, bound, rho, exact): quality of the budgeted search."""
    rows = []
    for n in lengths:
        for c in budgets:
            r = budgeted_search(g, n, c)
            top = r.paths.first()
            rows.append((n, c, top and top["weight"], r.summary["bound"] and float(r.summary["bound"]), r.summary["rho"], r.summary["exact"]))
    return spark.createDataFrame(rows, "length int, budget int, weight bigint, bound double, rho double, exact boolean")


def quality_table(spark: SparkSession, g: Graph, lengths, budget: int) -> DataFrame:
    """(length, method, weight, bound): exact, beam, budgeted and greedy side by side."""
    from ..api import heaviest_paths

    rows, best = [], optimal_weights(g, max(2, min(lengths)))
    for n in lengths:
        limit = int(bounds.best_split_bound(best, n))
        for method, options in (("canonical_growth", {}), ("beam", {}), ("budgeted", {"budget": budget}), ("greedy", {})):
            top = heaviest_paths(g, n, 1, method, **options).paths.first()
            rows.append((n, method, top and top["weight"], limit))
    return spark.createDataFrame(rows, "length int, method string, weight bigint, bound bigint")


def longest_length(spark: SparkSession, g: Graph, max_paths: int, upto: int, guards=("none", "ends", "strict")) -> DataFrame:
    """(guard, longest, held): the longest length that ordered buffers solve within a number of held paths."""
    from ..paths.ordered_buffers import Search

    rows = []
    for guard in guards:
        last = (guard, 1, 0)
        for n in range(2, upto + 1):
            run = Search(g, n, guard, budget=max_paths)
            run.more(1)
            if run.stopped:
                break
            last = (guard, n, run.held)
        rows.append(last)
    return spark.createDataFrame(rows, "guard string, longest int, held long")


def spark_costs(spark: SparkSession, call) -> tuple[object, dict]:
    """(result, jobs, stages, tasks, bytes read, bytes shuffled and bytes spilled to disk that it took)"""
    import uuid

    sc, group = spark.sparkContext, uuid.uuid4().hex
    sc.setJobGroup(group, "measured")
    out = call()
    sc._jsc.sc().listenerBus().waitUntilEmpty()
    tracker, store = sc.statusTracker(), sc._jsc.sc().statusStore()
    jobs = tracker.getJobIdsForGroup(group)
    stages = {s for j in jobs if (info := tracker.getJobInfo(j)) for s in info.stageIds}
    known = [store.lastStageAttempt(s) for s in stages if tracker.getStageInfo(s)]  # stages that were skipped have no figures
    sc._jsc.clearJobGroup()
    total = lambda f: sum(int(f(x)) for x in known)
    cost = {"jobs": len(jobs), "stages": len(stages), "tasks": total(lambda x: x.numTasks())}
    return out, cost | {"read_bytes": total(lambda x: x.inputBytes()), "shuffle_bytes": total(lambda x: x.shuffleWriteBytes()), "spill_bytes": total(lambda x: x.diskBytesSpilled())}


def cost_table(spark: SparkSession, g: Graph, length: int, methods) -> DataFrame:
    """(method, seconds, jobs, stages, tasks, read_bytes, shuffle_bytes, spill_bytes)"""
    from ..api import heaviest_paths

    rows = []
    for method in methods:
        (_, sec), cost = spark_costs(spark, lambda m=method: timed(lambda: heaviest_paths(g, length, 1, m)))
        rows.append((method, round(sec, 3), *cost.values()))
    return spark.createDataFrame(rows, "method string, seconds double, jobs int, stages int, tasks int, read_bytes bigint, shuffle_bytes bigint, spill_bytes bigint")
