"""Queries that take the whole of their table, and searches that take the whole of their buffers."""

import random

import pytest

from topkpaths.api import heaviest_paths
from topkpaths.graph import builders as B
from topkpaths.graph.builders import literal
from topkpaths.paths import budgeted
from topkpaths.paths.layered import layered_paths
from topkpaths.plans import registry

from .helpers import duck, rows_of


def best_chains(rows, k):
    """The k heaviest chains from the first layer to the last, by plain lists of the k best for each node."""
    layers = sorted({r[0] for r in rows})
    best = {r[1]: [(0, (r[1],))] for r in rows if r[0] == layers[0]}
    for layer in layers:
        new = {}
        for _, a, b, w in (r for r in rows if r[0] == layer):
            new.setdefault(b, []).extend((v - w, n + (b,)) for v, n in best.get(a, []))
        best = {b: sorted(v)[:k] for b, v in new.items()}
    return [(n, -v) for v, n in sorted(x for v in best.values() for x in v)[:k]]


@pytest.fixture(scope="module")
def days(spark, sf):
    return [tuple(r) for r in B.layer_edges(spark, sf).select("layer", "src", "dst", "w").collect()]


@pytest.mark.parametrize("name, k", [("p_layered_bfs", 5), ("p_layered_dfs", 5), ("p_layered_ta", 5), ("app_stable_chains", 3)])
def test_all_layers(spark, sf, days, name, k):
    got = registry.queries()[name](spark, sf).orderBy("rank").collect()
    assert [r["length"] for r in got] == [len({r[0] for r in days})] * k
    assert [(tuple(map(int, r["path"].split(">"))), r["weight"]) for r in got] == best_chains(days, k)


@pytest.mark.parametrize("method", ["bfs", "dfs", "ta"])
def test_layers_against_all_chains(spark, method):
    """Ties, dead ends and a heavy first half that leads nowhere."""
    r = random.Random(5)
    rows = [(i, 100 * i + a, 100 * (i + 1) + b, r.randrange(1, 4)) for i in range(6) for a in range(4) for b in range(4) if r.random() < 0.6]
    rows += [(0, 50, 150, 90), (1, 150, 250, 90), (2, 250, 350, 90)]
    chains = [((a,), 0) for a in {x[1] for x in rows if x[0] == 0}]
    for i in range(6):
        chains = [(n + (b,), v + w) for n, v in chains for layer, a, b, w in rows if layer == i and n[-1] == a]
    want = sorted(chains, key=lambda c: (-c[1], c[0]))[:4]
    got = layered_paths(spark.createDataFrame(rows, "layer long, src long, dst long, w long"), 4, method, first=2).paths.orderBy("rank").collect()
    assert [(tuple(x["nodes"]), x["weight"]) for x in got] == want


def test_budget_reads_buffers_to_the_end(spark, monkeypatch):
    """A heavy star leads nowhere; the only path of the length starts below the first rows of the buffer."""
    monkeypatch.setattr(budgeted, "TOP_ROWS", 4)
    edges = [(1, i, 0.9) for i in range(2, 9)] + [(100 + i, 101 + i, 0.1) for i in range(5)]
    r = heaviest_paths(literal(spark, edges), 5, 1, "budgeted", budget=25, block=64, engine="tables")
    assert not r.summary["exact"]
    assert [tuple(x["nodes"]) for x in r.paths.collect()] == [tuple(range(100, 106))]


@pytest.mark.parametrize("name", ["j_full", "g_induced"])
def test_whole_tables(spark, sf, name):
    got = rows_of(registry.queries()[name](spark, sf))
    assert got[1] and got == duck(registry.oracles()[name], sf)
    if name == "j_full":
        assert {r[0] is None for r in got[1]} == {r[1] is None for r in got[1]} == {True, False}
