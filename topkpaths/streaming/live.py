"""Structured Streaming over events: windows, sessions, pair counts, joins, and live top-k."""

from __future__ import annotations

from collections.abc import Callable

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from ..graph.builders import MEASURES, event_items
from ..graph.model import graph, nano
from ..paths.canonical_growth import canonical_growth
from ..runtime import scratch


def staged(spark: SparkSession, sf_dir: str, files: int = 4, table: Callable | None = None) -> tuple[str, str]:
    """Events in time order as several files in the shared folder: (path, schema)."""
    events = (table or event_items)(spark, sf_dir).withColumn("part", F.ntile(files).over(Window.orderBy("ts", "event_id")))
    path = scratch(spark, "stream-in")
    for i in range(1, files + 1):  # one after the other: a file stream reads by time of writing
        events.where(F.col("part") == i).drop("part").coalesce(1).write.mode("append").parquet(path)
    return path, ", ".join(f"{c} {t}" for c, t in events.drop("part").dtypes)


def stream(spark: SparkSession, source: tuple[str, str], watermark: str | None = "1 day", per_trigger: int = 1) -> DataFrame:
    s = spark.readStream.schema(source[1]).option("maxFilesPerTrigger", per_trigger).parquet(source[0])
    return s.withWatermark("ts", watermark) if watermark else s


def drained(df: DataFrame, mode: str = "append") -> DataFrame:
    """Runs a stream to its present end and gives the sink's table; 'append' goes to files, other modes to a batch-wise table."""
    spark = df.sparkSession
    checkpoint = scratch(spark, "stream-state")
    if mode == "append":
        out = scratch(spark, "stream-out")
        q = df.writeStream.format("parquet").option("path", out).option("checkpointLocation", checkpoint).outputMode("append").trigger(availableNow=True).start()
        q.awaitTermination()
        return spark.read.schema(df.schema).parquet(out)
    last: dict = {}

    def put(batch: DataFrame, n: int) -> None:
        path = scratch(spark, f"stream-{mode}")
        batch.write.parquet(path)
        last.setdefault("paths", []).append(path)

    q = df.writeStream.foreachBatch(put).option("checkpointLocation", checkpoint).outputMode(mode).trigger(availableNow=True).start()
    q.awaitTermination()
    paths = last.get("paths", [])
    return spark.read.schema(df.schema).parquet(*(paths[-1:] if mode == "complete" else paths)) if paths else spark.createDataFrame([], df.schema)


def tumbling(events: DataFrame, width: str = "1 day") -> DataFrame:
    return events.groupBy(F.window("ts", width).alias("w"), "k").agg(F.count("*").alias("n"), F.round(F.sum("value"), 4).alias("total")).select(F.col("w.start").alias("start"), "k", "n", "total")


def sliding(events: DataFrame, width: str = "7 days", step: str = "1 day") -> DataFrame:
    return events.groupBy(F.window("ts", width, step).alias("w")).agg(F.count("*").alias("n")).select(F.col("w.start").alias("start"), "n")


def sessions(events: DataFrame, gap: str = "6 hours") -> DataFrame:
    return events.groupBy(F.session_window("ts", gap).alias("w"), "user_id").agg(F.count("*").alias("n")).select("user_id", F.col("w.start").alias("start"), "n")


def pair_counts(events: DataFrame) -> DataFrame:
    """Counts of item pairs that one user has on one day: a stateful self-join by time, then an aggregate per batch."""
    a = events.select("user_id", "ts", F.col("k").alias("a"), "event_id")
    b = events.select(F.col("user_id").alias("u"), F.col("ts").alias("t"), F.col("k").alias("b"), F.col("event_id").alias("e"))
    return a.join(b, F.expr("user_id = u and a < b and t >= ts - interval 6 hours and t <= ts + interval 6 hours")).select("a", "b")


def open_sessions(events: DataFrame, gap_s: int = 21600) -> DataFrame:
    """(user_id, session, n): sessions kept as state per user and given out when a later event closes them, or at a timeout."""

    def step(key, batches, state: GroupState):
        start, last, n = state.get if state.exists else (None, None, 0)
        out = []
        if state.hasTimedOut:
            state.remove()
            yield pd.DataFrame({"user_id": [key[0]], "start_us": [start], "n": [n]})
            return
        for t in sorted(x for pdf in batches for x in pdf["us"]):
            if last is not None and t - last >= gap_s * 1_000_000:
                out.append((key[0], start, n))
                start, n = None, 0
            start, last, n = t if start is None else start, t, n + 1
        state.update((start, last, n))
        state.setTimeoutTimestamp(max(last // 1000 + gap_s * 1000, state.getCurrentWatermarkMs() + 1))
        yield pd.DataFrame(out, columns=["user_id", "start_us", "n"])

    rows = events.withColumn("us", F.unix_micros("ts"))
    return rows.groupBy("user_id").applyInPandasWithState(step, "user_id long, start_us long, n long", "start long, last long, n long", "append", GroupStateTimeout.EventTimeTimeout)


def _sessions_of(rows: DataFrame) -> DataFrame:
    return rows.select(F.to_date("ts").alias("day"), "user_id", F.col("k").alias("item")).where("day is not null and user_id is not null and item is not null").distinct()


def live_top(spark: SparkSession, source: tuple[str, str], length: int, k: int) -> DataFrame:
    """Top-k paths on the co-occurrence graph of all events so far, found anew after each batch; the last state is given.

    Pair and item counts are carried on: a batch is paired with what its own days' sessions held before, so it reads the days it
    touches and the counts, not the history. Each batch's state lies under its number, so a repeated batch replaces its own.
    """
    base = scratch(spark, "live")
    counts = "a long, b long, n long"  # a pair's sessions; b is null: an item's
    state: dict = {}

    def put(batch: DataFrame, n: int) -> None:
        now = _sessions_of(batch)
        days = [r[0] for r in now.select("day").distinct().collect()]  # days of one batch
        old = spark.read.schema("user_id long, item long, batch int, day date").parquet(f"{base}/seen") if state else spark.createDataFrame([], "user_id long, item long, batch int, day date")
        old = old.where((F.col("batch") < n) & F.col("day").isin(days)).select("day", "user_id", "item")
        now.join(old, ["day", "user_id", "item"], "left_anti").write.mode("overwrite").partitionBy("day").parquet(f"{base}/seen/batch={n}")
        new = spark.read.schema("user_id long, item long, day date").parquet(f"{base}/seen/batch={n}")
        both = old.join(new.select("day", "user_id").distinct(), ["day", "user_id"], "left_semi").withColumn("fresh", F.lit(False)).unionByName(new.withColumn("fresh", F.lit(True)))
        x = both.select("day", "user_id", F.col("item").alias("a"), F.col("fresh").alias("fa"))
        y = both.select("day", "user_id", F.col("item").alias("b"), F.col("fresh").alias("fb"))
        pairs = x.join(y, ["day", "user_id"]).where("a < b and (fa or fb)").select("a", "b", F.lit(1).alias("n"))
        gained = pairs.unionByName(new.select(F.col("item").alias("a"), F.lit(None).cast("long").alias("b"), F.lit(1).alias("n")))
        before = spark.read.schema(counts).parquet(state["counts"]) if state else spark.createDataFrame([], counts)
        path = f"{base}/counts-{n}"
        before.unionByName(gained).groupBy("a", "b").agg(F.sum("n").alias("n")).write.mode("overwrite").parquet(path)
        total = spark.read.schema(counts).parquet(path)
        items = total.where("b is null")
        met = total.where("b is not null").select("a", "b", F.col("n").alias("both")).join(items.select("a", F.col("n").alias("na")), "a").join(items.select(F.col("a").alias("b"), F.col("n").alias("nb")), "b")
        edges = met.select(F.col("a").alias("src"), F.col("b").alias("dst"), nano(MEASURES["dice"]()).alias("w"))
        state.update(counts=path, top=canonical_growth(graph(edges), length, k).named())

    q = stream(spark, source, None).writeStream.foreachBatch(put).option("checkpointLocation", scratch(spark, "live-state")).trigger(availableNow=True).start()
    q.awaitTermination()
    return state["top"]


__all__ = ["drained", "live_top", "open_sessions", "pair_counts", "sessions", "sliding", "staged", "stream", "tumbling"]
