"""Every method against exhaustive search, on random graphs with and without ties, and edge cases."""

import random

import pytest

from topkpaths import bounds
from topkpaths.api import METHODS, heaviest_paths
from topkpaths.graph.builders import SIX_NODES, literal
from topkpaths.graph.components import components
from topkpaths.graph.model import clean, graph
from topkpaths.paths import sequential as seq
from topkpaths.paths.reductions import lightest_paths
from topkpaths.plans.sqlgen import heaviest_paths_sql
from topkpaths.runtime import keep

from .helpers import brute_paths


def random_edges(seed, nodes, share, weights):
    r = random.Random(seed)
    return [(a, b, r.choice(weights)) for a in range(nodes) for b in range(a + 1, nodes) if r.random() < share]


def answer(result):
    return [(tuple(r["nodes"]), r["weight"]) for r in result.paths.orderBy("rank").collect()]


EXACT = [
    ("enumerate", {}), ("avoidance_dp", {}), ("avoidance_dp", {"form": "visited"}), ("edge_rank_scan", {"first": 3}),
    ("ordered_buffers", {"block": 2}), ("ordered_buffers", {"guard": "none", "block": 4}), ("ordered_buffers", {"guard": "strict", "block": 4, "bound": "peak"}),
    ("canonical_growth", {}), ("canonical_growth", {"seed": None, "bands": 3}), ("budgeted", {"budget": 100_000, "block": 8}),
]


@pytest.mark.parametrize("method, options", EXACT)
@pytest.mark.parametrize("seed, weights", [(1, (1, 2, 3)), (2, tuple(range(10, 400)))])
def test_exact_methods(spark, method, options, seed, weights):
    edges = random_edges(seed, 7, 0.6, weights)
    g = graph(spark.createDataFrame(edges, "src long, dst long, w long"))
    assert answer(heaviest_paths(g, 3, 5, method, **options)) == brute_paths(edges, 3)[:5]


@pytest.mark.parametrize("seed", range(40))
def test_sequential_forms(seed):
    edges = random_edges(seed, random.Random(seed).randint(4, 7), 0.7, (1, 2, 3, 4))
    for n in (2, 3, 4):
        want = brute_paths(edges, n)[:4]
        for guard in ("none", "peak", "ends", "strict"):
            got = seq.buffers(edges, n, 4, guard=guard)["paths"]
            assert [w for _, w in got] == [w for _, w in want]
        assert [w for _, w in seq.buffers(edges, n, 4, lazy=True)["paths"]] == [w for _, w in want]
        if want:
            assert seq.rank_scan(edges, n, 4, exact_ties=True)["paths"] == want


@pytest.mark.parametrize("agg, f", [("min", min), ("max", max)])
def test_aggregates(spark, agg, f):
    edges = random_edges(5, 7, 0.6, (3, 5, 8, 9))
    g = graph(spark.createDataFrame(edges, "src long, dst long, w long"))
    assert answer(heaviest_paths(g, 3, 6, "canonical_growth", agg=agg)) == brute_paths(edges, 3, f=f)[:6]


def test_directed(spark):
    r = random.Random(3)
    edges = [(a, b, r.randint(1, 50)) for a in range(6) for b in range(6) if a != b and r.random() < 0.5]
    g = graph(spark.createDataFrame(edges, "src long, dst long, w long"), directed=True)
    want = brute_paths(edges, 3, directed=True)[:6]
    for method, options in (("enumerate", {}), ("canonical_growth", {}), ("avoidance_dp", {}), ("ordered_buffers", {"guard": "strict"}), ("edge_rank_scan", {"first": 4})):
        assert answer(heaviest_paths(g, 3, 6, method, **options)) == want, method


def test_lightest_is_the_flip(spark):
    edges = random_edges(7, 7, 0.6, tuple(range(1, 90)))
    g = graph(spark.createDataFrame(edges, "src long, dst long, w long"))
    want = sorted(brute_paths(edges, 3), key=lambda r: (r[1], r[0]))[:5]
    assert answer(lightest_paths(g, 3, 5)) == want
    # the reciprocal is not order-equivalent for sums: 1 + 9 is lighter than 5 + 6, 1/1 + 1/9 heavier than 1/5 + 1/6 - and the other way round for 2 + 2
    assert 1 / 4 + 1 / 4 < 1 / 1 + 1 / 8 and 4 + 4 < 1 + 8


def test_edge_cases(spark):
    one = literal(spark, [(1, 2, 0.5)])
    for method in ("enumerate", "canonical_growth", "ordered_buffers", "edge_rank_scan", "avoidance_dp"):
        assert answer(heaviest_paths(one, 1, 3, method)) == [((1, 2), 500_000_000)]
        assert answer(heaviest_paths(one, 2, 3, method)) == []
    same = literal(spark, [(1, 2, 1.0), (2, 3, 1.0), (3, 4, 1.0), (5, 6, 1.0)])
    got = heaviest_paths(same, 2, 9)
    assert answer(got) == [((1, 2, 3), 2_000_000_000), ((2, 3, 4), 2_000_000_000)] and got.summary["exhausted"]
    whole = literal(spark, [(a, b, 0.1 * (a + b)) for a in range(5) for b in range(a + 1, 5)])
    assert len(answer(heaviest_paths(whole, 4, 100))) == 60
    rows = spark.createDataFrame([(1, 1, 1.0), (1, 2, float("nan")), (2, 1, 0.3), (1, 2, 0.4), (None, 2, 1.0), (2, 3, None), (3, 2, 0.0), (3, 4, -0.5)], "src long, dst long, w double")
    assert sorted(tuple(r) for r in clean(rows).collect()) == [(1, 2, 400_000_000), (2, 3, 0), (3, 4, -500_000_000)]
    with pytest.raises(ValueError):
        heaviest_paths(one, 0, 1)


def test_empty_graph(spark):
    g = graph(spark.createDataFrame([], "src long, dst long, w long"))
    for method in ("canonical_growth", "enumerate", "ordered_buffers", "edge_rank_scan"):
        assert answer(heaviest_paths(g, 3, 2, method)) == []


def test_heuristics_stay_below_bounds(spark):
    edges = [(a, b, w) for a, b, w in SIX_NODES]
    g = graph(spark.createDataFrame(edges, "src long, dst long, w long"))
    best = brute_paths(edges, 4)[0][1]
    for method, options in (("beam", {}), ("greedy", {}), ("pairwise_dp", {}), ("budgeted", {"budget": 25, "block": 4})):
        got = heaviest_paths(g, 4, 1, method, **options)
        assert answer(got)[0][1] <= best
        if got.summary.get("rho"):
            assert got.summary["rho"] <= answer(got)[0][1] / best <= 1
    assert set(METHODS) >= {"beam", "greedy", "pairwise_dp", "budgeted"}


def test_bounds():
    assert bounds.rank_scan_bound(77, 93, 4) == 356 and bounds.after_read(70) == 140
    assert bounds.split_bound({1: 10, 2: 19, 3: 27}, 8, 4, 10) == 2 * 27 + 19
    assert bounds.split_bound({1: 10}, 8, 2, 10) == 80
    assert bounds.best_split_bound({1: 10, 2: 19, 3: 27}, 8) <= bounds.split_bound({1: 10, 2: 19, 3: 27}, 8, 4, 10)
    assert bounds.rho(None, 5) is None


def test_sql_forms(spark):
    edges = random_edges(11, 7, 0.6, tuple(range(1, 60)))
    g = graph(spark.createDataFrame(edges, "src long, dst long, w long"))
    for form in ("self_join", "recursive"):
        assert [(tuple(r["nodes"]), r["w"]) for r in heaviest_paths_sql(spark, g, 3, 4, form).collect()] == brute_paths(edges, 3)[:4]


def test_components(spark):
    r = random.Random(2)
    edges = [(i, i + 1) for i in range(0, 60)] + [(100 + i, 100 + r.randint(0, i - 1)) for i in range(1, 40)] + [(500, 500)]
    got = {x["node"]: x["root"] for x in components(spark.createDataFrame(edges, "u long, v long"), keep).collect()}
    assert all(got[i] == 0 for i in range(1, 61)) and all(got[100 + i] == 100 for i in range(1, 40)) and 500 not in got


def test_growth_plan_has_no_nested_loop(spark):
    """Frontiers meet adjacency by equi-joins; paths are cut inside the join."""
    from topkpaths.paths import expand

    g = literal(spark, [(a, b, w / 100) for a, b, w in SIX_NODES])
    plan = expand.extend_both(expand.start_paths(g), g, "strict")._jdf.queryExecution().toString()
    assert "CartesianProduct" not in plan and "BroadcastNestedLoopJoin" not in plan and "HashJoin" in plan


def test_long_ranks(spark):
    from topkpaths.graph.model import rank_edges

    rows = [(i, i + 1 + i % 7, i % 13) for i in range(500)]
    got = rank_edges(spark.createDataFrame(rows, "src long, dst long, w long"), small=False).orderBy("eid").collect()
    assert [(r["src"], r["dst"], r["w"]) for r in got] == sorted(rows, key=lambda e: (-e[2], e[0], e[1])) and [r["eid"] for r in got] == list(range(500))


def test_peak_bound_never_reads_more(spark):
    g = literal(spark, [(a, b, w / 100) for a, b, w in SIX_NODES])
    a, b = (heaviest_paths(g, 3, 1, "ordered_buffers", bound=x, block=2) for x in ("plain", "peak"))
    assert answer(a) == answer(b) and b.summary["edges_read"] <= a.summary["edges_read"]


def test_more_answers_reuse_the_state(spark):
    from topkpaths.paths.ordered_buffers import Search

    edges = random_edges(9, 8, 0.6, tuple(range(1, 40)))
    run = Search(graph(spark.createDataFrame(edges, "src long, dst long, w long")), 3, block=4)
    assert answer(run.more(3)) == brute_paths(edges, 3)[:3]
    assert answer(run.more(12)) == brute_paths(edges, 3)[:12]


