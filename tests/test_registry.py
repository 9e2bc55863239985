import os
import sys

import pytest

import __spark_entry__ as entry
from tilerank import registry

sys.path.insert(0, os.path.dirname(__file__))
from oracle import connect, difference  # noqa: E402

QUICK = [
    "src_table_counts", "src_keyed_gaussian", "mat_userhour_pivot", "mat_tile_roundtrip", "mat_page_tags", "lin_gram_emb", "lin_tile_matmul", "cpqr_emb_pivots", "cpqr_columnwise_emb",
    "sketchqr_emb_k16_pullback", "sketchqr_emb_k16_right", "sketchqr_emb_k16_downdate", "sketch_emb_block1_pivots", "utv_q1_emb_tile0_logvol", "utv_left_emb_identity", "sketchqr_emb_k16_physical", "sketchqr_emb_residuals", "reflectorqr_emb_identity", "cpqr_design_rank", "ledger_lru_trace", "ledger_qr_masks", "tileutv_emb_gram_memory", "join_lateral", "join_salted", "lin_tile_combine", "io_npy_tiles", "io_matrix_market", "app_near_dup_pairs", "stream_output_modes", "svd_emb_power_sums",
    "ledger_2x2_tasks", "ledger_lru_io", "ledger_reuse_distance", "ledger_utv_counts", "model_write_volume", "model_table1_ratios", "join_asof_events", "join_cogroup_pair", "join_range_panels",
    "agg_cube", "agg_percentile", "win_row_index", "win_range_frame", "set_intersect_except_all", "fn_householder", "fn_dates", "udf_grouped_qr", "udtf_tile_entries", "io_bucketed_join", "io_roundtrip_orc",
    "stream_session", "stream_sketch_state", "stream_r_incremental", "stream_late_rows", "app_lstsq_line4", "lin_tri_solve",
]


@pytest.fixture(scope="module")
def con(sf):
    return connect(sf)


@pytest.mark.parametrize("name", QUICK)
def test_query_equals_its_sql(spark, sf, con, name):
    assert difference(registry.queries()[name](spark, sf), con, registry.oracle_sql()[name]) is None


def test_registry_is_consistent(spark):
    assert set(registry.oracle_sql()) <= set(registry.queries()) and len(registry.queries()) > 150
    assert set(registry.queries()) <= set(entry.queries()) and entry.entry(spark).count() == 16


def plan(df) -> str:
    return df._jdf.queryExecution().toString()


def test_plans(spark, sf):
    q = registry.queries()
    pushed = plan(q["io_pushdown_filter"](spark, sf))
    assert "PushedFilters: [IsNotNull(l_shipdate), IsNotNull(l_discount), GreaterThanOrEqual(l_shipdate" in pushed
    assert "ReadSchema: struct<l_quantity:double,l_discount:double,l_shipdate:timestamp_ntz>" in pushed
    assert "BroadcastHashJoin" in plan(q["join_broadcast_thin"](spark, sf))
    assert "ShuffledHashJoin" in plan(q["join_shuffle_hash"](spark, sf))
    for name in ("join_asof_events", "join_theta_upper", "join_range_panels", "join_multi_star", "lin_tile_matmul", "join_lateral", "join_cross_grid"):
        assert "CartesianProduct" not in plan(q[name](spark, sf)) and "BroadcastNestedLoop" not in plan(q[name](spark, sf)), name
    bucketed = plan(q["io_bucketed_join"](spark, sf))
    assert "SortMergeJoin" in bucketed and bucketed.split("== Physical Plan ==")[1].count("Exchange hashpartitioning") == 0


def test_random_tiles_do_not_depend_on_the_partitioning(spark):
    from tilerank.sources import formats

    formats.register(spark)
    read = lambda b: spark.read.format("tilematrix").option("m", "20").option("n", "12").option("b", b).load()
    from tilerank.sources.tables import from_tiles

    rows = lambda b: sorted(tuple(r) for r in from_tiles(read(str(b)), b).collect())
    assert rows(5) == rows(8) and len(rows(5)) == 240


def test_filters_reach_the_tile_sources(spark):
    from tilerank.sources import formats

    formats.register(spark)
    tiles = spark.read.format("tilematrix").option("m", "100").option("n", "40").option("b", "10").load()
    kept = tiles.where("bi >= 8 and bj = 1")
    assert kept.rdd.getNumPartitions() == 2 and {(r.bi, r.bj) for r in kept.collect()} == {(8, 1), (9, 1)}
    assert tiles.where("bi in (1, 3)").rdd.getNumPartitions() == 2


@pytest.mark.parametrize("name", [
    "agg_grouping_sets", "io_datasource_tiles", "join_range_panels", "ledger_2x2_tasks", "ledger_block_sizes", "ledger_direct_io", "ledger_lru_io", "ledger_lru_trace",
    "ledger_overlap_makespan", "ledger_qr_counts", "ledger_qr_masks", "ledger_reuse_distance",
])
def test_ledger_queries_read_a_given_table(spark, sf, name):
    files = registry.queries()[name](spark, sf).inputFiles()
    assert any(f.endswith(("/events.parquet", "/embeddings.parquet")) for f in files)


@pytest.mark.parametrize("name", ["ledger_2x2_tasks", "ledger_lru_trace", "ledger_qr_counts", "ledger_qr_masks", "agg_grouping_sets", "join_range_panels"])
def test_panels_of_uneven_users_equal_their_sql(spark, tmp_path, name):
    n = {1: 1, 2: 32, 3: 33, 4: 64, 5: 65, 6: 200}
    spark.createDataFrame([(u,) for u, k in n.items() for _ in range(k)], "user_id bigint").coalesce(1).write.parquet(f"{tmp_path}/e")
    spark.read.parquet("/root/testdata/sf0.001/embeddings.parquet").coalesce(1).write.parquet(f"{tmp_path}/m")
    (tmp_path / "data").mkdir()
    for folder, table in (("e", "events"), ("m", "embeddings")):
        next((tmp_path / folder).glob("*.parquet")).rename(tmp_path / "data" / f"{table}.parquet")
    df = registry.queries()[name](spark, f"{tmp_path}/data")
    assert difference(df, connect(f"{tmp_path}/data"), registry.oracle_sql()[name]) is None
