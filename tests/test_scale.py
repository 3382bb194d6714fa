"""Ways taken only beyond a size, forced on small tables and held against the plain way."""

import random

from pyspark.sql import functions as F

from topkpaths.graph import builders as B
from topkpaths.graph import model as M
from topkpaths.graph import pair_blocks
from topkpaths.paths import expand
from topkpaths.paths.canonical_growth import canonical_growth
from topkpaths.plans import measures
from topkpaths.sources import arc_source
from topkpaths.streaming import live

from .helpers import brute_paths, rows_of


def test_a_long_session_is_dealt(spark):
    rng = random.Random(3)
    rows = {(s, f"w{rng.randrange(60)}") for s, n in ((1, 200), (2, 12), (3, 1)) for _ in range(n)}
    s = spark.createDataFrame(sorted(rows), "session int, item string")
    want = sorted((a, b) for t, a in rows for u, b in rows if t == u and a < b)
    for part in (1, 5, 512):
        assert sorted(map(tuple, B.session_pairs(s, part).collect())) == want


def test_no_sessions(spark):
    assert B.pair_counts(spark.createDataFrame([], "session int, item string")).count() == 0


def test_neighbours_in_blocks(spark):
    rng = random.Random(5)
    vs = [(i, [float(rng.randrange(-3, 4)) for _ in range(4)]) for i in range(60)] + [(100, [0.0] * 4), (101, None)]
    norm = lambda v: sum(x * x for x in v) ** 0.5
    real = [(i, v) for i, v in vs if v and norm(v)]
    want = set()
    for a, v in real:
        near = sorted((round(1 - sum(x * y for x, y in zip(v, u)) / (norm(v) * norm(u)), 9), b) for b, u in real if b != a)
        want |= {(min(a, b), max(a, b)) for _, b in near[:3]}
    df = spark.createDataFrame(vs, "id long, v array<double>")
    for block in (7, 2048):
        assert {(r.src, r.dst) for r in B.knn(df, 3, block).collect()} == want


def test_dictionary_by_ranges(spark, monkeypatch):
    rows = [(f"n{i * 7 % 50}", f"n{i % 31}") for i in range(200)] + [(None, "x")]
    e = spark.createDataFrame(rows, "a string, b string")
    plain = rows_of(M.encode(e, "a", "b")[1])
    monkeypatch.setattr(M, "SMALL_LABELS", 2)
    assert rows_of(M.encode(e, "a", "b")[1]) == plain
    assert [r[0] for r in M.encode(e, "a", "b")[1].select("id").orderBy("label").collect()] == list(range(1, len(plain[1]) + 1))


def test_arc_files_in_ranges(tmp_path):
    lines = ["c comment", "p sp 4 3", *[f"a {i} {i * 3} {i * i}" for i in range(1, 40)], "a 1", ""]
    (tmp_path / "x.gr").write_text("\n".join(lines))
    (tmp_path / "_SUCCESS").write_text("")
    want = [(i, i * 3, i * i) for i in range(1, 40)]
    for size in (1, 7, 64, 10_000):
        assert [r for s in arc_source.spans(arc_source.arc_files(str(tmp_path)), size) for r in arc_source.arcs_of(s)] == want


def test_live_counts_are_carried(spark, sf):
    """Top paths over several batches equal those of one batch."""
    few, one = (live.live_top(spark, live.staged(spark, sf, files=n), 2, 5) for n in (3, 1))
    assert rows_of(few) == rows_of(one)


def test_hub_heads_are_dealt(spark, monkeypatch):
    """Stars with chords, whose centres are dealt over several keys: the same paths as brute force, directed or not."""
    rng = random.Random(9)
    edges = {(0, i): rng.randrange(1, 50) for i in range(1, 25)} | {(25, i): rng.randrange(1, 50) for i in range(1, 20)}
    edges |= {(i, i + 1): rng.randrange(1, 50) for i in range(1, 20)}
    rows = [(a, b, w) for (a, b), w in edges.items()]
    monkeypatch.setattr(M, "SMALL_EDGES", 4)
    monkeypatch.setattr(M, "HUB_ARCS", 6)
    for directed in (False, True):
        g = M.graph(spark.createDataFrame(rows, "src long, dst long, w long"), directed)
        assert {r.hub: r.parts for r in g.hubs.collect()} == {0: 4, 25: 4}
        want = [(list(n), w) for n, w in brute_paths(rows, 4, directed)[:7]]
        got = canonical_growth(g, 4, 7, width=4).paths.orderBy("rank").collect()
        assert [(r.nodes, r.weight) for r in got] == want
        grown = expand.extend_both(expand.start_paths(g), g)
        assert sorted(tuple(r.nodes) for r in expand.deduplicated(grown, directed).collect()) == sorted(n for n, _ in brute_paths(rows, 2, directed))
    monkeypatch.setattr(M, "HUB_ARCS", 100)
    assert M.graph(spark.createDataFrame(rows, "src long, dst long, w long")).hubs is None


def test_costs_of_a_run(spark):
    _, cost = measures.spark_costs(spark, lambda: spark.range(1000).repartition(3).groupBy((F.col("id") % 7).alias("k")).count().collect())
    assert cost["jobs"] >= 1 and cost["tasks"] >= cost["stages"] >= 2 and cost["shuffle_bytes"] > 0 and cost["spill_bytes"] == 0


def test_word_pairs_are_counted_in_blocks(spark):
    """The graph of words is the same by blocks and by a join of all pairs, and only sessions are shuffled for it."""
    sf = "/root/testdata/sf0.01"
    (blocks, by_blocks), (plain, by_pairs) = (measures.spark_costs(spark, lambda m=m: sorted(map(tuple, B.word_edges(spark, sf, m).collect()))) for m in (None, 0))
    assert blocks == plain and len(blocks) > 20_000
    assert by_blocks["shuffle_bytes"] < by_pairs["shuffle_bytes"] / 3


def test_dice_pairs_in_slices(spark):
    """Few pairs a slice, an item in every session, a very long session, sessions of one or no item; cuts at an exact Dice value."""
    rng = random.Random(8)
    sessions = [["all", *{f"w{min(rng.randrange(50), rng.randrange(50))}" for _ in range(rng.randrange(9))}] for _ in range(300)] + [[f"w{i}" for i in range(400)], ["all"], []]
    df = spark.createDataFrame([(s,) for s in sessions], "items array<string>").repartition(3)
    sizes, shared = {}, {}
    for s in sessions:
        for a in s:
            sizes[a] = sizes.get(a, 0) + 1
            for b in s:
                if a < b:
                    shared[a, b] = shared.get((a, b), 0) + 1
    for cut, least, support in ((0.1, 1, 1), (0.2, 5, 3), (1.0, 1, 1)):
        want = sorted((a, b, c, sizes[a], sizes[b]) for (a, b), c in shared.items() if min(sizes[a], sizes[b]) >= least and c >= support and 2.0 * c / (sizes[a] + sizes[b]) >= cut)
        for few in (7, 100_000):
            assert want and sorted(map(tuple, pair_blocks.dice_pairs(df, cut, least, support, slice_pairs=few).collect())) == want
    assert pair_blocks.dice_pairs(df.where("false"), 0.1).count() == 0 and pair_blocks.dice_pairs(df, 0.1, max_items=3) is None
