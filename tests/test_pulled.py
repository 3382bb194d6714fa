"""The adjacency that is pulled to the driver: arrays, one pull for several searches, bytes an edge."""

import random
import tracemalloc

import pytest
from pyspark.sql import functions as F

from topkpaths.api import heaviest_paths
from topkpaths.graph.builders import literal
from topkpaths.graph.model import graph
from topkpaths.paths import budgeted, neighbours

from .helpers import brute_paths
from .test_directed import nano


def some_edges(seed, nodes=12, n=40):
    rng = random.Random(seed)
    return [(a, b, rng.randrange(1, 6) / 10) for a, b in (rng.sample(range(-3, nodes - 3), 2) for _ in range(n))]


def answers(result):
    return [(tuple(r["nodes"]), r["weight"]) for r in result.paths.orderBy("rank").collect()]


@pytest.mark.parametrize("directed", [True, False])
def test_steps(spark, directed):
    g = literal(spark, some_edges(1), directed)
    rows = [tuple(r) for r in g.edges.orderBy("eid").select("src", "dst", "w").collect()]
    got = neighbours.pulled(g)
    assert list(got.every_edge()) == rows and len(got) == g.n_edges and got.edges(5, 7) == rows[5:7]
    for node in range(-5, 12):
        out = [(w, i, b) for i, (a, b, w) in enumerate(rows) if a == node]
        into = [(w, i, a) for i, (a, b, w) in enumerate(rows) if b == node]
        assert sorted(got.steps(node)) == sorted(out if directed else out + into)
        assert sorted(got.steps(node, inward=True)) == sorted(into if directed else out + into)


def test_no_edges(spark):
    g = literal(spark, [(1, 1, 1.0)])
    assert answers(heaviest_paths(g, 3, 1, "greedy")) == [] and answers(heaviest_paths(g, 3, 1, "budgeted", budget=10)) == []


def test_one_pull_for_all_searches(spark, monkeypatch):
    made = []
    plain = neighbours.Pulled
    monkeypatch.setattr(neighbours, "Pulled", lambda g: made.append(1) or plain(g))
    g = literal(spark, some_edges(2))
    for length in (2, 3, 5):
        by_join = answers(heaviest_paths(g, length, 2, "greedy", pull=0))
        assert answers(heaviest_paths(g, length, 2, "greedy")) == by_join
        heaviest_paths(g, length, 2, "budgeted", budget=5)
    assert made == [1]


def test_many_edges_in_the_driver(spark):
    """More edges than rows of Python objects would leave room for: a ring of 500,000, whose weights repeat."""
    n = 500_000
    ring = spark.range(n).select(F.col("id").alias("src"), F.pmod(F.col("id") + 1, F.lit(n)).alias("dst"), (F.pmod(F.col("id") * 7919, F.lit(1009)) + 1).alias("w"))
    g = graph(ring)
    weight = [(i * 7919) % 1009 + 1 for i in range(n)]
    tracemalloc.start()
    try:
        found = answers(heaviest_paths(g, 40, 1, "budgeted", budget=200, engine="memory"))
        walked = answers(heaviest_paths(g, 40, 1, "greedy"))
        peak = tracemalloc.get_traced_memory()[1]
    finally:
        tracemalloc.stop()
    for nodes, w in (*found, *walked):
        assert len(set(nodes)) == 41
        assert w == sum(weight[a if (a + 1) % n == b else b] for a, b in zip(nodes, nodes[1:]))
    assert len(found) == len(walked) == 1 and peak < 200 * n


@pytest.mark.parametrize("patience", [1, 4])
def test_waiting_paths_are_not_lost(spark, patience, monkeypatch):
    """Completion in any order of waiting gives every path of the length in the end."""
    monkeypatch.setattr(budgeted, "PATIENCE", patience)
    monkeypatch.setattr(budgeted, "PART_PATIENCE", 2 * patience)
    for seed, length in ((3, 4), (4, 5), (5, 6)):
        edges = [(a, b, w) for a, b, w in some_edges(seed, 9, 14)] + [(a + 50, b + 50, w) for a, b, w in some_edges(seed + 10, 8, 11)]
        plain = brute_paths(nano(edges, False), length, False)
        for engine in ("memory", "tables") if seed == 3 else ("memory",):
            got = answers(heaviest_paths(literal(spark, edges), length, 10**4, "budgeted", budget=20, engine=engine))
            assert len(got) == len(set(got)) and sorted(got) == sorted(plain), (seed, engine)


def test_crowded_corners(spark):
    """Heavy cliques with fewer nodes than the length have more paths than can ever be tried; the answer is the light chain."""
    cliques = [(100 * c + a, 100 * c + b, 0.9) for c in (1, 2, 3) for a in range(22) for b in range(a)]
    chain = [(1000 + i, 1001 + i, 0.1) for i in range(30)]
    r = heaviest_paths(literal(spark, cliques + chain), 25, 1, "budgeted", budget=400)
    (nodes, w), = answers(r)
    assert w == 25 * 10**8 and min(nodes) >= 1000 and not r.summary["exact"]
