"""Adjacency for methods that walk node by node: pulled once if it is small, else looked up for many nodes by one join."""

from __future__ import annotations

from collections.abc import Iterable, Iterator

import numpy as np
from pyspark.sql import functions as F

from ..graph.model import Graph

#: Edges up to which the adjacency is pulled to the driver, some 50 bytes each; nodes that one lookup asks for, at most.
PULL_EDGES, NODES_A_LOOKUP = 2_000_000, 1000
#: Edges that become Python rows at a time.
EDGE_ROWS = 2000


class _Steps:
    """For each head its steps: places of edges, and tails."""

    def __init__(self, heads: np.ndarray, tails: np.ndarray, places: np.ndarray, nodes: int):
        order = np.argsort(heads, kind="stable")
        self.tails, self.places = tails[order], places[order]
        self.start = np.concatenate(([0], np.cumsum(np.bincount(heads, minlength=nodes))))


class Pulled:
    """A whole graph in arrays: edges by rank, and the steps out of a node (ahead) and, with directions, into it (back)."""

    def __init__(self, g: Graph):
        rows = g.edges.select("src", "dst", "w", F.col("eid").cast("int").alias("eid")).toArrow()  # at most PULL_EDGES rows
        order = np.argsort(rows.column("eid").to_numpy())
        src, dst, self.w = (rows.column(c).to_numpy()[order] for c in ("src", "dst", "w"))
        del rows, order
        self.nodes = np.unique(np.concatenate((src, dst)))
        self.src, self.dst = (np.searchsorted(self.nodes, x).astype(np.int32) for x in (src, dst))
        del src, dst
        places, n = np.arange(len(self.w), dtype=np.int32), len(self.nodes)
        if g.directed:
            self.ahead, self.back = _Steps(self.src, self.dst, places, n), _Steps(self.dst, self.src, places, n)
        else:
            self.ahead = self.back = _Steps(np.concatenate((self.src, self.dst)), np.concatenate((self.dst, self.src)), np.concatenate((places, places)), n)
        self.parts: np.ndarray | None = None

    def __len__(self) -> int:
        return len(self.w)

    def edges(self, lo: int, hi: int) -> list[tuple[int, int, int]]:
        """(src, dst, w) of the edges at these places, from the heaviest on."""
        return list(zip(self.nodes[self.src[lo:hi]].tolist(), self.nodes[self.dst[lo:hi]].tolist(), self.w[lo:hi].tolist()))

    def every_edge(self) -> Iterator[tuple[int, int, int]]:
        for lo in range(0, len(self), EDGE_ROWS):
            yield from self.edges(lo, lo + EDGE_ROWS)

    def steps(self, node: int, inward: bool = False) -> list[tuple[int, int, int]]:
        """(w, place, node) of the steps from a node, in the order of the arrays."""
        at = int(np.searchsorted(self.nodes, node))
        if at == len(self.nodes) or self.nodes[at] != node:
            return []
        side = self.back if inward else self.ahead
        x, y = side.start[at], side.start[at + 1]
        places = side.places[x:y]
        return list(zip(self.w[places].tolist(), places.tolist(), self.nodes[side.tails[x:y]].tolist()))


    def component(self, node: int) -> int:
        """The connected component of a node, directions aside, by its smallest place; found for all nodes at the first call."""
        if self.parts is None:
            part = np.arange(len(self.nodes), dtype=np.int32)
            while np.any((a := part[self.src]) != (b := part[self.dst])):
                least = np.minimum(a, b)
                np.minimum.at(part, a, least)
                np.minimum.at(part, b, least)
                while np.any((up := part[part]) != part):
                    part = up
            self.parts, self.sizes = part, np.bincount(part)
        return int(self.parts[np.searchsorted(self.nodes, node)])


def pulled(g: Graph) -> Pulled:
    """The graph's arrays, pulled once; searches of several lengths share them."""
    if g.near is None:
        g.near = Pulled(g)
    return g.near


class Neighbours:
    """Steps out of a path's last node (ahead) and into its first one; without direction both are the same."""

    def __init__(self, g: Graph, pull: int | None = None):
        self.g, self.lookups = g, 0
        self.whole = pulled(g) if g.n_edges <= (PULL_EDGES if pull is None else pull) else None
        self.ahead: dict = {}
        self.back: dict = {} if g.directed else self.ahead

    def _fetch(self, nodes: Iterable[int], known: dict, inward: bool) -> None:
        new = sorted({n for n in nodes if n not in known})
        for at in range(0, len(new), NODES_A_LOOKUP):
            some = new[at : at + NODES_A_LOOKUP]
            wanted = self.g.edges.sparkSession.createDataFrame([(n,) for n in some], "head long")
            rows = self.g.arcs(inward).join(F.broadcast(wanted), "head").select("head", "w", "eid", "tail").collect()  # edges of at most NODES_A_LOOKUP nodes
            self.lookups += 1
            known.update({n: [] for n in some})
            for r in rows:
                known[r["head"]].append((r["w"], r["eid"], r["tail"]))

    def prepare(self, paths: Iterable[tuple]) -> None:
        """Looks up what is unknown around the ends of many paths at once."""
        if self.whole is not None:
            return
        paths = list(paths)
        if self.g.directed:
            self._fetch((p[-1] for p in paths), self.ahead, False)
            self._fetch((p[0] for p in paths), self.back, True)
        else:
            self._fetch((n for p in paths for n in (p[0], p[-1])), self.ahead, False)

    def _steps(self, path, node: int, inward: bool):
        if self.whole is not None:
            return self.whole.steps(node, inward)
        self.prepare([path])
        return (self.back if inward else self.ahead).get(node, ())

    def after(self, path) -> list[tuple[int, int, int]]:
        """(w, eid, node) of the steps behind the last node."""
        return [x for x in self._steps(path, path[-1], False) if x[2] not in path]

    def before(self, path) -> list[tuple[int, int, int]]:
        """(w, eid, node) of the steps before the first node."""
        return [x for x in self._steps(path, path[0], True) if x[2] not in path]

    def room(self, path, need: int) -> bool:
        """Whether that many nodes can be reached from the path's ends without its own; if not, it cannot become longer by so many edges."""
        reached: set = set()
        for front, inward in (((path[-1],), False), ((path[0],), True)) if self.g.directed else ((path[::len(path) - 1], False),):
            known = set(path)
            while front and len(reached) < need:
                self.prepare((n,) for n in front)
                front = {t for n in front for _, _, t in self._steps((n,), n, inward)} - known
                known |= front
                reached |= front
        return len(reached) >= need

    def turned(self, nodes: tuple) -> tuple:
        """The one writing of a path: without direction its smaller end comes first."""
        return nodes if self.g.directed or nodes[0] < nodes[-1] else nodes[::-1]
