"""Queries against their SQL on the smallest tables."""

import os

import duckdb
import pytest

import __spark_entry__ as entry
from rankscan import workloads
from tests.conftest import TINY

NAMES = [
    "bin_orders_daily", "bin_event_points", "user_value_index", "detrend_moving_median", "segment_ship_daily", "rank_average_ties", "law_product_n30_w8", "law_udtf_n30_w8", "mc_error_vs_exact",
    "best_interval_vectors", "best_interval_critical_filter", "overlap_pairs", "discord_sax_vectors", "fixed_window_w7_ship", "planted_grid_truth", "asof_region_order",
    "best_regions_users", "best_regions_vectors", "best_regions_vectors_powell", "best_regions_udtf",
]


def test_names():
    assert set(workloads.ORACLE_SQL) <= set(workloads.QUERIES)
    assert len(workloads.ORACLE_SQL) >= 70
    assert set(entry.oracle_sql()) <= set(entry.queries())


@pytest.mark.parametrize("name", NAMES)
def test_against_sql(spark, name):
    con = duckdb.connect()
    for file in os.listdir(TINY):
        con.execute(f"CREATE VIEW {file.removesuffix('.parquet')} AS SELECT * FROM '{TINY}/{file}'")
    got = workloads.QUERIES[name](spark, TINY)
    cols = sorted(got.columns)
    want = con.execute(workloads.ORACLE_SQL[name])
    names = [c[0] for c in want.description]
    assert sorted(names) == cols

    def rows(data):
        return sorted((tuple(round(v, 6) if isinstance(v, float) else v for v in r) for r in data), key=repr)

    assert rows(got.select(*cols).collect()) == rows([tuple(r[names.index(c)] for c in cols) for r in want.fetchall()])


def test_entry(spark):
    df = entry.entry(spark)
    assert df.count() > 0 and {"series_id", "s", "w", "log10_p", "global_rank"} <= set(df.columns)
