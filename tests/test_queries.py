"""A selection of registered queries against their DuckDB SQL on the smallest tables."""

import glob
import math
import os

import duckdb
import pytest

from shiftscan import catalogue

SMALL = "/root/testdata/sf0.001"
PICKED = [
    "feed_unpivot_lineitem", "msg_render", "msg_parse_offset", "msg_parse_equal", "html_lang_by_offset", "route_load_skew", "series_windows", "seed_values", "rotation_printed_safe", "few_labels", "rotation_anchor", "kmeans_native",
    "kmeans_iterations", "memo_canonical_hits", "transition_full", "anomalies_ten", "anomalies_all_equal", "cluster_ops", "markov_ops_k53", "release_idle", "unsynced_inversions", "anomaly_asof_order", "anomaly_interval_events",
    "chain_staged", "ingest_lazy", "memo_canonical_labels", "release_delay", "fleet_synced", "stream_correlate", "share_grouping_sets", "udf_labels_sql", "stream_session", "stream_dedup", "stream_anomalies",
]


@pytest.fixture(scope="module")
def duck():
    con = duckdb.connect()
    for path in glob.glob(f"{SMALL}/*.parquet"):
        con.execute(f"CREATE VIEW {os.path.basename(path)[:-8]} AS SELECT * FROM '{path}'")
    return con


def plain(df):
    def cell(x):
        if x is None or x != x:
            return ""
        return f"{x:.9g}" if isinstance(x, float) and not (math.isfinite(x) and x == int(x)) else f"{x:.0f}" if isinstance(x, float) else str(x)

    df = df[sorted(df.columns)]
    return sorted(tuple(map(cell, r)) for r in df.astype(object).itertuples(index=False, name=None))


@pytest.mark.parametrize("name", PICKED)
def test_query(spark, duck, name):
    got, want = catalogue.RUNS[name](spark, SMALL).toPandas(), duck.execute(catalogue.SQL[name]).df()
    assert sorted(got.columns) == sorted(want.columns) and plain(got) == plain(want)


def test_every_oracle_has_a_query():
    assert set(catalogue.SQL) <= set(catalogue.RUNS)
