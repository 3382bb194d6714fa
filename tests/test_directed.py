"""Directed graphs, lookups by a join, dead ends, aggregates and lazy access against plain searches."""

import random

import pytest

from topkpaths.api import heaviest_paths
from topkpaths.graph import builders as B
from topkpaths.graph.builders import literal
from topkpaths.paths import budgeted, neighbours

from .helpers import brute_paths

ARROWS = [(1, 2, 0.9), (3, 2, 0.8), (3, 4, 0.7), (4, 5, 0.6), (5, 3, 0.5), (2, 6, 0.1)]


def random_edges(seed, n=9, m=26, ties=False):
    r = random.Random(seed)
    pairs = {(a, b) for a, b in ((r.randrange(n), r.randrange(n)) for _ in range(m)) if a != b}
    return [(a, b, r.randrange(1, 5) / 10 if ties else r.randrange(1, 10**6) / 10**6) for a, b in sorted(pairs)]


def nano(edges, directed):
    best = {}
    for a, b, w in edges:
        key = (a, b) if directed else (min(a, b), max(a, b))
        best[key] = max(best.get(key, 0), round(w * 10**9))
    return [(a, b, w) for (a, b), w in best.items()]


def plain_greedy(edges, length, k, directed):
    edges = sorted(edges, key=lambda e: (-e[2], e[0], e[1]))
    found = []
    for a, b, w in edges:
        path, total = [a, b], w
        while len(path) <= length:
            steps = []
            for i, (x, y, v) in enumerate(edges):
                for p, q in ((x, y), (y, x))[: 1 if directed else 2]:
                    if p == path[-1] and q not in path:
                        steps.append((v, -i, 1, q))
                    if q == path[0] and p not in path:
                        steps.append((v, -i, 0, p))
            if not steps:
                break
            v, _, behind, t = max(steps)
            path, total = ([*path, t] if behind else [t, *path]), total + v
        nodes = tuple(path if directed or path[0] < path[-1] else path[::-1])
        if len(path) == length + 1 and (nodes, total) not in found and len(found) < k:
            found.append((nodes, total))
    return sorted(found, key=lambda r: (-r[1], r[0]))


def rows(result):
    return [(tuple(r["nodes"]), r["weight"]) for r in result.paths.orderBy("rank").collect()]


@pytest.mark.parametrize("directed", [True, False])
def test_greedy(spark, directed):
    for edges, length in ((ARROWS, 2), (random_edges(1), 4), (random_edges(2, ties=True), 3)):
        g, plain = literal(spark, edges, directed), plain_greedy(nano(edges, directed), length, 3, directed)
        assert rows(heaviest_paths(g, length, 3, "greedy")) == plain
        assert rows(heaviest_paths(g, length, 3, "greedy", pull=0)) == plain  # neighbours by a join
    assert rows(heaviest_paths(g, 8, 50, "greedy")) == plain_greedy(nano(edges, directed), 8, 50, directed)


@pytest.mark.parametrize("directed, engine", [(True, "tables"), (False, "tables"), (False, "memory")])
def test_budgeted(spark, directed, engine, monkeypatch):
    for edges, length in ((ARROWS, 3), (random_edges(3), 4)):
        plain = brute_paths(nano(edges, directed), length, directed)
        g = literal(spark, edges, directed)
        assert rows(heaviest_paths(g, length, 3, "budgeted", budget=10**5, engine=engine)) == plain[:3]
        monkeypatch.setattr(neighbours, "PULL_EDGES", 0 if directed else 400_000)
        few = heaviest_paths(g, length, 2, "budgeted", budget=4, engine=engine)
        monkeypatch.setattr(neighbours, "PULL_EDGES", 400_000)
        assert not few.summary["exact"] and set(rows(few)) <= set(plain) and len(rows(few)) == min(2, len(plain))
        assert few.summary["rho"] <= rows(few)[0][1] / plain[0][1] + 1e-9


@pytest.mark.parametrize("engine", ["tables", "memory"])
def test_dead_ends(spark, engine, monkeypatch):
    """More dead ends than completion reads at a time, all heavier than the one way on."""
    monkeypatch.setattr(budgeted, "TOP_ROWS", 20)
    edges = [(1, i, 0.9) for i in range(2, 70)] + [(100 + i, 101 + i, 0.1) for i in range(6)]
    r = heaviest_paths(literal(spark, edges), 6, 1, "budgeted", budget=500, engine=engine)
    assert not r.summary["exact"] and rows(r) == [(tuple(range(100, 107)), 600_000_000)]


def test_beam_follows_the_arrows(spark):
    plain = brute_paths(nano(ARROWS, True), 3, True)
    assert rows(heaviest_paths(literal(spark, ARROWS, True), 3, 2, "beam")) == plain[:2]


@pytest.mark.parametrize("agg", ["min", "max", "product", "mean"])
@pytest.mark.parametrize("method, options", [("ordered_buffers", {"block": 4}), ("ordered_buffers", {"access": "lazy", "block": 4}), ("edge_rank_scan", {"first": 4})])
def test_aggregates(spark, agg, method, options):
    fold = {"min": min, "max": max, "mean": sum, "product": lambda ws: ws[0] / 10**9 * ws[1] / 10**9 * ws[2]}[agg]
    edges = random_edges(4, 7, 16, ties=True)
    plain = brute_paths(nano(edges, False), 3, f=fold)
    scale = 3 if agg == "mean" else 1
    want = sorted(((n, round(round(w) / scale)) for n, w in plain), key=lambda r: (-r[1], r[0]))[:5]
    assert rows(heaviest_paths(literal(spark, edges), 3, 5, method, agg=agg, **options)) == want


@pytest.mark.parametrize("directed", [True, False])
def test_lazy_access(spark, directed):
    edges = random_edges(5, 10, 30, ties=True)
    plain = brute_paths(nano(edges, directed), 4, directed)
    g = literal(spark, edges, directed)
    for k in (2, 10**4):
        assert rows(heaviest_paths(g, 4, k, "ordered_buffers", access="lazy", block=8)) == plain[:k]


def test_lazy_access_spares_the_star(spark):
    """Three heavy edges beside a hub of light rays: whole access looks at the rays, lazy access doesn't."""
    g = literal(spark, B.adverse_star(60))
    whole = heaviest_paths(g, 3, 1, "ordered_buffers", guard="strict", block=4, counters=True)
    lazy = heaviest_paths(g, 3, 1, "ordered_buffers", access="lazy", block=4)
    assert rows(whole) == rows(lazy) == [((11, 12, 13, 101), 3 * 10**9)]
    assert lazy.summary["accesses"] * 50 < whole.summary["accesses"]


def test_counters(spark):
    """Growth makes every path once: without a bound as many as there are of lengths 2 to l."""
    edges = nano(random_edges(6), False)
    g = literal(spark, [(a, b, w / 10**9) for a, b, w in edges])
    want = sum(len(brute_paths(edges, n)) for n in (2, 3))
    got = heaviest_paths(g, 3, 10**5, "canonical_growth", counters=True).summary
    assert got["joins"] == got["built"] == want
    scan = heaviest_paths(g, 3, 10**5, "edge_rank_scan", counters=True, first=7).summary
    assert scan["built"] == len(brute_paths(edges, 3)) and scan["joins"] >= scan["built"]


def test_auto_is_exact_without_a_budget(spark):
    edges = [(i, i + 1, 0.5) for i in range(20)] + [(0, 30, 0.9), (30, 31, 0.9)]
    r = heaviest_paths(literal(spark, edges), 17, 1)
    assert r.summary["exact"] and rows(r) == brute_paths(nano(edges, False), 17)[:1]
    assert heaviest_paths(literal(spark, edges), 3, 1, budget=2).summary["exact"] is False
