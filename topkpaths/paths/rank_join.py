"""Threshold joins over score-sorted inputs: the general form over m relations, and the form over one edge list."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .. import bounds
from ..graph.model import Graph
from ..runtime import keep
from . import expand
from .result import PathResult


def edge_rank_scan(g: Graph, length: int, k: int = 1, block: int | str = "double", first: int = 64, ties: str = "exact", keep_partials: bool = False, agg: str = "sum", counters: bool = False) -> PathResult:
    """Reads the heaviest edges block by block; each block is joined with all edges read, at every position of a path.

    block: rows a round, or 'double'. ties: 'exact' reads on while an unread path could tie; 'source' stops at equality.
    keep_partials: writes the partial paths of a round instead of rebuilding them inside one plan. agg: any aggregate; with
    'max' an unread edge can stand beside the heaviest, so everything is read. counters: also counts joins (partial and whole paths made) and
    paths built, by jobs of their own.
    """
    spark = g.edges.sparkSession
    best: list = []
    read, size, steps, joins, built = 0, first if block == "double" else int(block), [], 0, 0
    slack = 1 if agg == "product" else 0  # products are rounded
    while read < g.n_edges:
        hi = min(g.n_edges, read + size)
        fresh, old, all_ = g.prefix(hi, read), g.prefix(read), g.prefix(hi)
        found = []
        for left in range(length):  # old edges before the first new one, any edges behind it
            paths = expand.start_paths(g, agg, fresh.edges)
            paths = paths if g.directed else expand.both_ways(paths)
            for _ in range(left):
                paths = expand.extend_left(paths, g, old.arcs(inward=True), agg=agg)
                joins += paths.count() if counters else 0
            for _ in range(length - 1 - left):
                paths = expand.extend_right(paths, g, all_.arcs(), agg=agg)
                joins += paths.count() if counters else 0
            found.append(keep(paths, "partials") if keep_partials else paths)
        made = reduce(DataFrame.union, found)
        if not g.directed:  # each undirected path comes once a direction
            made = made.where("element_at(nodes, 1) < element_at(nodes, -1)")
        built += made.count() if counters else 0
        best = expand.better(best, [(r[0], r[1]) for r in expand.top(made, k, g.directed, agg).collect()], k)  # k rows
        last = g.edges.where(F.col("eid") == hi - 1).first()["w"]
        read = hi
        theta = bounds.rank_scan_bound(last, g.max_w, length, agg) + slack
        steps.append((len(steps), length, float(theta), read, joins, built, 0, len(best)))
        if len(best) >= k and (best[-1][1] > theta if ties == "exact" else best[-1][1] >= theta):
            break
        size = size * 2 if block == "double" else size
    counted = {"joins": joins, "built": built, "duplicates": 0} if counters else {}
    return PathResult(expand.answers(spark, best, length, agg), {"exact": True, "edges_read": read, "exhausted": len(best) < k} | counted, steps, g.labels)


class Input:
    """A relation sorted by a score, read prefix by prefix. Scores are never null; ties are ordered by `ties`."""

    def __init__(self, df: DataFrame, score: str, ties: list[str]):
        self.df, self.score, self.ties = df, score, ties
        row = df.agg(F.max(score).alias("top"), F.count("*").alias("n")).first()
        self.top, self.n = float(row["top"] or 0), row["n"]
        self.depth, self.last = 0, self.top

    def read(self, depth: int) -> None:
        self.depth = min(self.n, depth)
        self.prefix = keep(self.df.orderBy(F.desc(self.score), *self.ties).limit(self.depth), "prefix")
        low = self.prefix.agg(F.min(self.score)).first()[0]
        self.last = float(low) if low is not None else self.top

    @property
    def done(self) -> bool:
        return self.depth >= self.n


def rank_join(inputs: list[Input], on: list[Column], order: list[str], k: int, f: str = "sum", pull: str = "round_robin", probe: str = "prefix", first: int = 256) -> tuple[DataFrame, dict]:
    """The k best joined rows by a monotone f of the scores.

    on[i] joins input i + 1 to those before. Each round deepens the inputs (all in turn, or the one whose bound is the
    highest), joins the prefixes (probe 'full': the last deepened one against whole inputs), and stops when k results
    exceed max over i of f(top, .., last read of i, .., top).
    """
    combine = {"sum": sum, "min": min}[f]
    scores = [F.col(i.score).cast("double") for i in inputs]
    total = reduce(lambda a, b: a + b, scores) if f == "sum" else F.least(*scores)
    for i in inputs:
        i.read(first)
    rounds = 0
    while True:
        rounds += 1
        parts = [i.prefix if probe == "prefix" or n == 0 else i.df for n, i in enumerate(inputs)]
        joined = parts[0]
        for other, cond in zip(parts[1:], on):
            joined = joined.join(other, cond)
        best = joined.withColumn("score", F.round(total, 6)).orderBy(F.desc("score"), *order).limit(k)
        rows = best.collect()  # k rows
        tops, lasts = [i.top for i in inputs], [i.last for i in inputs]
        limits = [combine([*tops[:n], lasts[n], *tops[n + 1 :]]) if not i.done else bounds.NONE_LEFT for n, i in enumerate(inputs)]
        if probe == "full":
            limits = limits[:1]
        if (len(rows) >= k and rows[-1]["score"] > max(limits)) or max(limits) == bounds.NONE_LEFT:
            return best, {"rounds": rounds, "depths": [i.depth for i in inputs], "threshold": max(limits)}
        open_ = [n for n, i in enumerate(inputs) if not i.done and n < len(limits)]
        for n in [max(open_, key=lambda n: limits[n])] if pull == "adaptive" else open_:
            inputs[n].read(inputs[n].depth * 4)
