"""The greedy baseline: from the heaviest edge, always the heaviest edge at either end; when stuck, the next start edge."""

from __future__ import annotations

from itertools import islice

from ..graph.model import Graph
from . import expand
from .neighbours import Neighbours
from .result import PathResult

#: Walks that go on side by side where neighbours are looked up by a join.
SIDE_BY_SIDE = 256


def end_greedy(g: Graph, length: int, k: int = 1, restarts: int | None = None, pull: int | None = None) -> PathResult:
    """The first k different paths of the length, in the order of their start edges; restarts: start edges tried at most, None for all.

    summary: restarts (start edges that led nowhere new) and found. Without enough paths every edge has been a start.
    """
    near, found, tried, seen = Neighbours(g, pull), [], 0, set()
    if near.whole is not None:
        starts, together = islice(near.whole.every_edge(), None if restarts is None else restarts + k), 1
    else:
        edges = g.edges.orderBy("eid").select("src", "dst", "w")
        starts, together = (edges if restarts is None else edges.limit(restarts + k)).toLocalIterator(), SIDE_BY_SIDE
    while len(found) < k and (rows := list(islice(starts, together))):
        walks = [[(a, b), w] for a, b, w in rows]
        going = [w for w in walks if len(w[0]) <= length]
        while going:
            near.prepare(w[0] for w in going)
            going = [w for w in going if _step(near, w) and len(w[0]) <= length]
        for path, weight in walks:
            nodes = near.turned(path)
            if len(path) == length + 1 and nodes not in seen and len(found) < k:
                seen.add(nodes)
                found.append((nodes, weight))
            elif len(found) < k:
                tried += 1
    return PathResult(expand.answers(g.edges.sparkSession, sorted(found, key=lambda r: (-r[1], r[0])), length), {"exact": False, "restarts": tried, "found": len(found)}, labels=g.labels)


def _step(near: Neighbours, walk: list) -> bool:
    """Adds the heaviest edge at either end (of equal ones the first by rank); False at a dead end."""
    path, weight = walk
    options = [(w, -i, side, t) for side, steps in ((0, near.before(path)), (1, near.after(path))) for w, i, t in steps]
    if not options:
        return False
    w, _, side, t = max(options)
    walk[:] = [(*path, t) if side else (t, *path), weight + w]
    return True
