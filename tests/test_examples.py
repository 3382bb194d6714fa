"""The worked examples, step by step."""

import pytest

from topkpaths.graph.builders import SIX_NODES, adverse_star, chain_and_star
from topkpaths.paths import sequential as seq


def thousandths(rows):
    return [(a, b, round(w * 1000)) for a, b, w in rows]


def test_six_nodes_best_paths():
    want = {2: ((1, 2, 3), 186), 3: ((3, 2, 1, 6), 262), 4: ((4, 3, 2, 1, 6), 335), 5: ((4, 3, 2, 1, 6, 5), 407)}
    for n, best in want.items():
        assert seq.rank_scan(SIX_NODES, n)["paths"] == [best]
        for guard in ("none", "peak", "ends", "strict"):
            assert seq.buffers(SIX_NODES, n, guard=guard)["paths"] == [best]
        assert seq.buffers(SIX_NODES, n, lazy=True)["paths"] == [best]


def test_rank_scan_thresholds():
    got = seq.rank_scan(SIX_NODES, 4)
    assert got["steps"][3][2] == 356 and got["steps"][-1][2] == 337 and got["edges_read"] == 15


@pytest.mark.parametrize("n, none, ends", [(2, (3, 24, 3, 21), (3, 22, 1, 21)), (3, (4, 68, 9, 59), (4, 60, 1, 59)), (4, (6, 286, 73, 213), (6, 224, 11, 213)), (5, (15, 952, 392, 560), (15, 592, 32, 560))])
def test_buffer_counters(n, none, ends):
    for guard, want in (("none", none), ("ends", ends)):
        r = seq.buffers(SIX_NODES, n, guard=guard)
        assert (r["edges_read"], r["joins"], r["duplicates"], r["built"]) == want


@pytest.mark.parametrize("n", [5, 20])
def test_chain_and_star(n):
    edges = thousandths(chain_and_star(n))
    guarded, free = seq.buffers(edges, 3), seq.buffers(edges, 3, guard="none")
    assert guarded["paths"] == [((1, 2, 3, 4), 2001)]
    assert (guarded["joins"], free["joins"], guarded["edges_read"]) == (5, 6, 3)
    assert seq.rank_scan(edges, 3)["edges_read"] == n + 5


def test_adverse_star():
    edges = thousandths(adverse_star(30))
    assert seq.rank_scan(edges, 3)["edges_read"] == 3
    eager, lazy = seq.buffers(edges, 3), seq.buffers(edges, 3, lazy=True)
    assert eager["paths"] == lazy["paths"] and lazy["accesses"] < eager["accesses"]


def test_guard_makes_each_path_once_without_ties():
    r = seq.buffers([(a, b, 1000 * w + i) for i, (a, b, w) in enumerate(SIX_NODES)], 5)
    assert seq.buffers(SIX_NODES, 5, guard="strict")["duplicates"] == 0
    assert r["duplicates"] < seq.buffers(SIX_NODES, 5, guard="none")["duplicates"]


def test_one_sided_growth_reads_more():
    """The rejected form: still exact, but it waits for light beginnings."""
    for n in (2, 3, 4):
        one, both = seq.buffers(SIX_NODES, n, 3, ends="one"), seq.buffers(SIX_NODES, n, 3, guard="none")
        assert [w for _, w in one["paths"]] == [w for _, w in both["paths"]] and one["edges_read"] >= both["edges_read"]
    chain = thousandths(chain_and_star(10))
    assert seq.buffers(chain, 3, ends="one")["edges_read"] > seq.buffers(chain, 3)["edges_read"]
