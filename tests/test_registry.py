"""Registered queries against their SQL on the smallest tables."""

import os

import numpy as np
import pandas as pd
import pytest

from halo import registry

duckdb = pytest.importorskip("duckdb")
TABLES = "region nation customer supplier part orders lineitem events embeddings conversations".split()
QUICK = ["grid_zero_fill", "time_unit_blocks", "autocov_events_exact", "lag_gram_events", "ar2_yule_walker", "ma1_innovations_depth2", "arma_predict_fixed", "banded_predict_embeddings", "irregular_window_1h", "mesh_stencil", "hop_membership", "traffic_one_step", "asof_orders", "append_layout", "stored_block_range", "truth_series", "ma_depth_sweep", "integration_order", "arma_blocks_truth", "arma_stream_truth", "prediction_intervals", "gof_report", "graph_autocov_k2", "network_residuals", "traffic_simulate_blocks", "cross_membership", "autocov_users_h24", "banded_fit_suppliers_diag", "stream_late_rows", "stream_interval_join", "sql_surface", "udaf_panel_lag", "udf_norm", "layout_comparison"]


@pytest.fixture(scope="module")
def con(tiny):
    c = duckdb.connect()
    for t in TABLES:
        p = f"{tiny}/{t}.parquet"
        c.execute(f"create view {t} as select * from read_parquet('{p + '/*.parquet' if os.path.isdir(p) else p}')")
    return c


def plain(df):
    df = df[sorted(df.columns)]
    return df.sort_values(list(df.columns)).reset_index(drop=True).astype(object).map(lambda x: None if pd.isna(x) else float(x) if not isinstance(x, str) else x)


@pytest.mark.parametrize("name", QUICK)
def test_query_equals_sql(spark, tiny, con, name):
    got, want = plain(registry.queries()[name](spark, tiny).toPandas()), plain(con.execute(registry.oracle_sql()[name]).df())
    assert list(got.columns) == list(want.columns) and len(got) == len(want)
    for c in got.columns:
        a, b = got[c].tolist(), want[c].tolist()
        assert all(x == y or (x is not None and y is not None and not isinstance(x, str) and np.isclose(x, y, atol=1e-6, equal_nan=True)) for x, y in zip(a, b)), c


def test_entry(spark, tiny):
    assert registry.flagship(spark, tiny).count() == 50


@pytest.mark.parametrize("name", ["time_blocks_membership", "blocks_replication", "one_sided_replication", "cross_replication", "recursive_walk", "udtf_psi"])
def test_blocks_read_their_table(spark, tiny, con, name):
    """Membership comes from the rows of the table, not from the grid alone; equal to its SQL."""
    scans = registry.queries()[name](spark, tiny)._jdf.queryExecution().optimizedPlan().toString().count("parquet")
    assert scans > 0
    test_query_equals_sql(spark, tiny, con, name)
