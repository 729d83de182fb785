"""A cross-section of the registered queries against DuckDB on the smallest tables, values and columns alike."""

import pandas as pd
import pytest

from bcfilter import registry

NAMES = (
    "hash_linear hash_md5 hash_blocked size_fp_rate size_best_k fig_fp_curves bf_positions bf_probe_join bf_probe_broadcast bf_probe_shuffle bf_probe_negative bf_union bf_intersect wire_roundtrip bf_blocked "
    "clear_randomized clear_random clear_min_fn clear_max_fp clear_ratio clear_ratio_live clear_min_fn_live clear_ratio_scope_b clear_ratio_weighted clear_budget m_marginal exact_fp_fn baseline_exception_list "
    "w_sim_table_ratio w_random_law w_trace_success w_trace_beta_sweep w_trace_links_missed w_trace_merge w_contamination w_sim_table_random m_confidence w_live_ratio w_trace_nodes_missed w_trace_cycles w_trace_live_collision m_aspect_matrix w_hot_urls w_hot_users st_watermark st_online_b join_asof join_interval join_prefilter_exact join_prefilter_lossy agg_bitmap win_range udtf_positions udf_block_clear sql_contains st_probe st_reclear"
).split()


def rows(df: pd.DataFrame):
    def cell(x):
        if x is None or x is pd.NA or x is pd.NaT or (isinstance(x, float) and x != x):
            return "null"
        return f"{x:.9g}" if isinstance(x, float) else str(x)

    df = df[sorted(df.columns)]
    return list(df.columns), sorted(tuple(map(cell, r)) for r in df.itertuples(index=False, name=None))


@pytest.mark.parametrize("name", NAMES)
def test_query_matches_duckdb(spark, sf, duck, name):
    assert rows(registry.QUERIES[name](spark, sf).toPandas()) == rows(duck.execute(registry.ORACLE_SQL[name]).df())


def test_every_oracle_belongs_to_a_query():
    assert set(registry.ORACLE_SQL) <= set(registry.QUERIES)
    assert len(registry.QUERIES) > 200
