"""Registered queries against their SQL twins on the smallest tables."""

import pytest

from topkpaths.plans import registry

from .helpers import duck, rows_of

QUICK = [q for q in registry.queries() if q[:2] in ("f_", "j_", "a_", "w_", "o_", "u_", "x_")] + ["g_topic_edges", "g_word_dice", "g_road_flipped", "g_layered", "g_edge_rank", "g_components", "p_growth_d2p_l6", "p_buffers_d2p_l4", "p_layered_ta", "p_lightest_d3_l4", "rj_three_way", "fn_grouped_map", "fn_udtf_paths", "s_arc_file", "s_band_pruning", "st_tumbling", "st_stream_join", "st_watermark_late"]


def test_every_oracle_has_a_query():
    assert set(registry.oracles()) <= set(registry.queries())


@pytest.mark.parametrize("name", QUICK)
def test_query(spark, sf, name):
    got = rows_of(registry.queries()[name](spark, sf))
    if name in registry.oracles():
        assert got == duck(registry.oracles()[name], sf)
    else:
        assert got[1]


@pytest.mark.parametrize("name", ["e_best_baskets", "h_upper_bound"])
@pytest.mark.parametrize("orders", [((1, 2), (2, 3)), ((1, 2), (3, 4)), ((1,), (2,))])
def test_no_path_of_a_length(spark, tmp_path, name, orders):
    """Basket graphs whose longest path has two edges, one edge and none."""
    rows = [(o, p) for o, parts in enumerate(orders) for p in parts]
    spark.createDataFrame(rows, "l_orderkey long, l_partkey long").write.parquet(f"{tmp_path}/lineitem.parquet")
    assert rows_of(registry.queries()[name](spark, str(tmp_path))) == duck(registry.oracles()[name].replace("from lineitem", f"from '{tmp_path}/lineitem.parquet/*.parquet'"))


@pytest.mark.parametrize("name", ["p_enumerate_x1_l4", "p_buffers_lazy", "m_access_counts", "m_threshold_trace"])
def test_made_of_given_tables(spark, sf, tmp_path, name):
    """The result follows the given tables: equal to the SQL's there, where it has one, and another or none without rows."""
    got = rows_of(registry.queries()[name](spark, sf))
    assert got[1] and (name not in registry.oracles() or got == duck(registry.oracles()[name], sf))
    for t in ("lineitem", "part", "customer", "nation", "region"):
        spark.read.parquet(f"{sf}/{t}.parquet").where("false").write.parquet(f"{tmp_path}/{t}.parquet")
    assert rows_of(registry.queries()[name](spark, str(tmp_path))) != got


def test_entry(spark):
    import __spark_entry__ as e

    assert e.entry(spark).count() > 0 and set(e.oracle_sql()) <= set(e.queries())
