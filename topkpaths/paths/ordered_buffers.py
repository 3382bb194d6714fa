"""Ordered buffers: one append-only buffer per length, a bound on everything still to come per length, releases above it.

Bounds never rise and no later path of a length exceeds its bound, so what was released of a level is exactly a range of
weights: buffers are written once and a release is a range filter. Edges are read in blocks from the heaviest on.
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .. import bounds
from ..graph.model import Graph
from ..runtime import keep
from . import expand
from .result import PathResult


class Level:
    """The buffer of one length: written batches, and the weight down to which it was released."""

    def __init__(self):
        self.batches: list[DataFrame] = []
        self.cut = float("inf")
        self.rows = 0

    def table(self) -> DataFrame | None:
        return reduce(DataFrame.union, self.batches) if self.batches else None

    def between(self, low: float) -> DataFrame | None:
        """Unreleased rows above `low`."""
        t = self.table()
        if t is None:
            return None
        t = t.where(F.col("w") > low) if low != bounds.NONE_LEFT else t
        return t.where(F.col("w") <= self.cut) if self.cut != float("inf") else t


def _highest(df: DataFrame | None, column: str = "w") -> float:
    if df is None:
        return bounds.NONE_LEFT
    v = df.agg(F.max(column)).first()[0]
    return bounds.NONE_LEFT if v is None else float(v)


class Search:
    """The state of a run; `more` continues it for further answers."""

    def __init__(self, g: Graph, length: int, guard: str = "ends", release: str | int = "drain", bound: str = "plain", block: int | None = None, budget: int | None = None, agg: str = "sum", access: str = "whole", counters: bool = False):
        if length < 1:
            raise ValueError("length is the number of edges, at least 1")
        if bound == "peak" and (guard == "none" or agg != "sum"):
            raise ValueError("the peak bound is for sums with a guard")
        if access == "lazy" and (guard != "strict" or release != "drain" or bound != "plain" or budget is not None):
            raise ValueError("lazy access goes with the strict guard, drained levels, the plain bound and no budget")
        self.g, self.length, self.guard, self.release, self.bound, self.budget = g, length, guard, release, bound, budget
        self.agg, self.access, self.counters, self.accesses = agg, access, counters, 0
        self.slack = 1 if agg == "product" else 0  # products are rounded
        self.block = block or max(64, g.n_edges // 32)  # doubles each round
        self.levels = {i: Level() for i in range(2, length + 1)}
        self.theta = {i: float(v) for i, v in bounds.first_bounds(length, g.max_w, agg).items()}
        self.read, self.joins, self.built, self.steps, self.stopped = 0, 0, 0, [], False
        self.unread_w = float(g.max_w)
        # lazy access: the edges read, the bounds, the weight down to which answers are looked for, and how far that is below the most
        self.base: list[DataFrame] = []
        self.limits, self.gap = dict(self.theta), g.max_w / 64
        self.goal = bounds.repeated(float(g.max_w), length) if agg in ("sum", "mean") else bounds.NONE_LEFT

    @property
    def held(self) -> int:
        return sum(v.rows for v in self.levels.values())

    def _append(self, level: int, slice_: DataFrame | None) -> None:
        """Extends a released slice into the next buffer."""
        if slice_ is None or self.stopped:
            return
        grown = expand.extend_both(slice_, self.g, self.guard, self.agg)
        buffer = self.levels[level]
        if self.counters:
            self.accesses += self._degrees_at_ends(slice_)
        if self.guard == "strict":
            batch = keep(grown, f"level{level}")
            made = new = batch.count()
        else:
            raw = keep(grown, f"grown{level}")
            made = raw.count()
            once = expand.deduplicated(raw, self.g.directed)
            # other sub-paths may have made it before; with the end guard only two edges of one weight in different blocks
            if buffer.batches and (level == 2 or self.guard in ("none", "peak")):
                once = once.join(expand.canonical(buffer.table(), self.g.directed).select("nodes"), "nodes", "left_anti").select(*expand.COLUMNS)
            batch = keep(once, f"level{level}")
            new = batch.count()
        self.joins += made
        if self.budget is not None and self.held + new > self.budget:  # the heaviest rows that fit
            room = max(0, self.budget - self.held)
            batch, new, self.stopped = keep(batch.orderBy(F.desc("w"), "nodes").limit(room), f"level{level}"), min(new, room), True
        self.built += new
        buffer.batches.append(batch)
        buffer.rows += new
        self.steps.append((len(self.steps), level, self.theta[level] if self.theta[level] != bounds.NONE_LEFT else None, self.read, made, new, made - new, self.held))

    def _degrees_at_ends(self, paths: DataFrame) -> int:
        """Steps that the adjacency holds at both ends of the paths: what whole access looks at."""
        total = 0
        for inward, end in ((False, -1), (True, 1)):
            degree = self.g.arcs(inward).groupBy("head").agg(F.count("*").alias("n"))
            total += paths.select(F.element_at("nodes", end).alias("head")).join(degree, "head").agg(F.sum("n")).first()[0] or 0
        return total

    def _slack(self, level: int) -> float:
        if self.bound != "peak":
            return float(self.g.max_w)
        live = [self.unread_w if self.read < self.g.n_edges else bounds.NONE_LEFT]
        live += [_highest(self.levels[j].between(bounds.NONE_LEFT), "peak_w") for j in range(2, level + 1)]
        top = max(live)
        return float(self.g.max_w) if top == bounds.NONE_LEFT else top

    def _read_block(self) -> DataFrame | None:
        """The next edges; the bound of length 2 falls to twice the last weight read."""
        if self.read >= self.g.n_edges:
            self.theta = dict.fromkeys(self.theta, bounds.NONE_LEFT)
            return None
        lo, hi = self.read, min(self.g.n_edges, self.read + self.block)
        self.block *= 2
        self.read = hi
        ends = {r["eid"]: float(r["w"]) for r in self.g.edges.where(F.col("eid").isin(hi - 1, hi)).select("eid", "w").collect()}  # two rows
        self.unread_w = ends.get(hi, bounds.NONE_LEFT)
        if 2 in self.theta:
            self.theta[2] = bounds.after_read(ends[hi - 1], self.agg) if hi < self.g.n_edges else bounds.NONE_LEFT
        return expand.start_paths(self.g, self.agg, self.g.edges.where((F.col("eid") >= lo) & (F.col("eid") < hi)))

    def _lazy_round(self) -> None:
        """Either the goal sinks or edges are read; then those extensions are made that come above the new cut of their length.

        All paths of the length above the goal are found from paths of i edges above goal - (length - i) * heaviest, so a level's cut is
        the higher one of that and of its bound. With a cut falling from `old` to `new`, a path released before takes the edges that
        lift it to a weight in (new, old], and one released now all that lift it above `new`; so each pair of path and edge is met once,
        the heavier edges of a node first, and all that a level holds is released.
        """
        old, slice_, heaviest = self.theta, None, float(self.g.max_w)
        if self.goal > self.limits[self.length]:
            self.gap *= 2
            below = bounds.repeated(heaviest, self.length) - self.gap
            self.goal = max(self.limits[self.length], below) if below > 0 else self.limits[self.length]
        else:
            self.theta = dict(self.limits)
            slice_ = self._read_block()
            if self.theta[2] != bounds.NONE_LEFT:
                for i in range(2, self.length):
                    self.theta[i + 1] = min(self.theta[i + 1], bounds.after_release(bounds.NONE_LEFT, self.theta[i], heaviest, self.agg))
            else:
                self.theta = dict.fromkeys(self.theta, bounds.NONE_LEFT)
            self.limits = self.theta
        new = self.theta = {i: max(v, self.goal - (self.length - i) * heaviest) for i, v in self.limits.items()}
        if slice_ is not None:
            self.base.append(slice_)
        fresh = slice_
        for level in range(2, self.length + 1):
            below = self.base if level == 2 else self.levels[level - 1].batches
            before = below[: len(below) - (fresh is not None)]
            parts = []
            for batches, top in (([fresh] if fresh is not None else [], None), (before, old[level])):
                if batches and (top is None or top != new[level]):
                    parts.append(expand.extend_both(reduce(DataFrame.union, batches), self.g, self.guard, self.agg, self._between(new[level], top)))
            fresh = None
            if parts:
                fresh = keep(reduce(DataFrame.union, parts), f"lazy{level}")
                n = fresh.count()
                self.joins, self.built, self.accesses = self.joins + n, self.built + n, self.accesses + n
                self.levels[level].batches.append(fresh)
                self.levels[level].rows += n
                self.steps.append((len(self.steps), level, new[level] if new[level] != bounds.NONE_LEFT else None, self.read, n, n, 0, self.held))

    def _between(self, low: float, top: float | None):
        """Join condition: the weight of the longer path is above `low` and at most `top`."""

        def condition(w, eid):
            made = expand.AGGREGATES[self.agg][0](F.col("p.w"), w)
            above = F.lit(True) if low == bounds.NONE_LEFT else made > low
            return above if top is None else above & (made <= top)

        return condition

    def _round(self) -> None:
        if self.access == "lazy":
            return self._lazy_round()
        slice_ = self._read_block()
        if self.length >= 2:
            self._append(2, slice_)
        for level in range(2, self.length):
            if self.stopped:
                return
            buffer, theta = self.levels[level], self.theta[level]
            low = theta
            if isinstance(self.release, int) and theta != bounds.NONE_LEFT:
                open_ = buffer.between(theta)
                row = None if open_ is None else open_.select("w").orderBy(F.desc("w")).limit(self.release).agg(F.min("w"), F.count("*")).first()
                if row is not None and row[1] == self.release:
                    low = float(row[0]) - 0.5  # down to the m-th weight, ties included
            out = buffer.between(low)
            if out is not None:
                self._append(level + 1, out)
                buffer.cut = low
            if not self.stopped:
                left = _highest(buffer.between(bounds.NONE_LEFT)) if (isinstance(self.release, int) or self.bound == "peak") else bounds.NONE_LEFT
                new = bounds.after_release(left, theta, self._slack(level), self.agg) if max(left, theta) != bounds.NONE_LEFT else bounds.NONE_LEFT
                self.theta[level + 1] = min(self.theta[level + 1], new)

    def ready(self) -> int:
        """Answers above the bound."""
        t = self.levels[self.length].table()
        if t is None:
            return 0
        th = self.theta[self.length]
        return (t if th == bounds.NONE_LEFT else t.where(F.col("w") > th + self.slack)).count()

    def done(self) -> bool:
        return self.read >= self.g.n_edges and all(v == bounds.NONE_LEFT for v in self.theta.values())

    def run(self, k: int) -> None:
        while not self.stopped and self.ready() < k and not self.done():
            self._round()

    def more(self, k: int) -> PathResult:
        """The k best; continues from the present state, so earlier work is used again."""
        spark = self.g.edges.sparkSession
        if self.length == 1:
            rows = expand.top(expand.start_paths(self.g, self.agg), k, self.g.directed, self.agg).collect()
            return PathResult(expand.answers(spark, rows, 1, self.agg), {"exact": True, "exhausted": len(rows) < k}, labels=self.g.labels)
        self.run(k)
        t, th = self.levels[self.length].table(), self.theta[self.length]
        rows = [] if t is None else expand.top(t if th == bounds.NONE_LEFT else t.where(F.col("w") > th + self.slack), k, self.g.directed, self.agg).collect()  # k rows
        summary = {"exact": not self.stopped or len(rows) >= k, "exhausted": len(rows) < k and not self.stopped, "edges_read": self.read, "joins": self.joins, "built": self.built, "duplicates": self.joins - self.built, "held": self.held}
        if self.counters or self.access == "lazy":
            summary["accesses"] = self.accesses
        return PathResult(expand.answers(spark, rows, self.length, self.agg), summary, self.steps, self.g.labels)


def ordered_buffers(g: Graph, length: int, k: int = 1, guard: str | None = None, release: str | int = "drain", bound: str = "plain", block: int | None = None, agg: str = "sum", access: str = "whole", counters: bool = False) -> PathResult:
    """Exact top-k of any aggregate. guard: none, peak, ends (the default), strict; release: drain, or the most rows a step; bound: plain, peak.

    access 'lazy' takes the edges at a path's ends only as far down as the bound of the longer path; it uses the strict guard.
    counters: also counts random accesses, by jobs of their own.
    """
    return Search(g, length, guard or ("strict" if access == "lazy" else "ends"), release, bound, block, None, agg, access, counters).more(k)
