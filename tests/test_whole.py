"""Queries of the whole study beside those that SQL repeats."""

from inspect import signature

import pytest

from pyspark.sql import functions as F

from rankscan import workloads as W
from rankscan.operators import prepare as P
from rankscan.operators import ranking as K
from rankscan.operators import scan as S
from rankscan.plans.detect import detect_events
from rankscan.sources import families as C
from rankscan.sources import planted
from tests.conftest import TINY

REPORTS = ["recall_report", "rank_summary_report", "false_positive_report", "separation_report", "interval_join_truth", "full_recall_report"]


class Stop(Exception):
    pass


@pytest.fixture
def grids(monkeypatch):
    """Stops a query where it makes its grid; holds (points, every)."""
    seen = []

    def spy(spark, n=1000, *args, every=1, **more):
        seen.append((n, every))
        raise Stop

    monkeypatch.setattr(planted, "grid_truth", spy)
    return seen


@pytest.mark.parametrize("name", ["planted_grid_values", "planted_outlier_values", *REPORTS])
def test_the_whole_study_has_every_series(spark, grids, name):
    with pytest.raises(Stop):
        W.QUERIES[f"{name}_whole"](spark, TINY)
    assert grids == [(1000, 1)] and W.STUDY["w_max"] == 100


@pytest.mark.parametrize("name", ["pivot_restart_curve", "misses_by_bump_width", "synthetic_report", "theta_sweep", "minimiser_gap", "cluster_regions_grid", "trend_report"])
def test_experiments_take_every_series(spark, grids, name):
    with pytest.raises(Stop):
        W.QUERIES[name](spark, TINY)
    assert grids == [(1000, 1)]


def test_best_windows_by_workers_are_those_by_sql(spark):
    values = planted.grid_values(planted.grid_truth(spark, 90, every=80), 90).cache()
    got = K.rank_events(W._scanned(values, 90, 40), per_series="best").collect()
    want = K.rank_events(S.scan_sql(values, [90], 40), per_series="best").collect()
    assert len(want) == 25 and max(r["w"] for r in want) > 16
    cols = ["series_id", "s", "w", "q", "log10_p", "global_rank"]
    assert sorted(tuple(r[c] for c in cols) for r in got) == sorted(tuple(r[c] for c in cols) for r in want)


def test_best_windows_may_be_as_wide_as_in_detection(spark):
    best = W._supplier_best_wide(spark, TINY).cache()
    want = K.best_per_series(S.scan_sql(C.supplier_weekly(spark, TINY), [357], 40))
    cols = ["series_id", "s", "w", "q", "log10_p"]
    assert sorted(map(tuple, best.select(*cols).collect())) == sorted(map(tuple, want.select(*cols).collect()))
    assert best.agg(F.max("w")).first()[0] > 6
    rolled = W.QUERIES["rollup_region_hits_wide"](spark, TINY).where("region is null").first()
    assert (rolled["series"], rolled["width"]) == best.agg(F.count("*"), F.sum("w")).first()[:]
    hours = W.QUERIES["best_interval_events_hourly_wide"](spark, TINY).agg(F.max("w")).first()[0]
    assert hours > 6


def test_long_and_short_series_are_searched_alike_by_default(spark):
    values = planted.grid_values(planted.grid_truth(spark, 80, every=500), 80).cache()
    short = values.where("t <= 40").withColumn("series_id", F.concat(F.lit("short"), "series_id"))
    packed = P.segment(values.union(short), 80, 10)
    key = lambda df: sorted((r["series_id"], r["s"], r["w"], r["hits"]) for r in df.collect())
    assert key(S.search_segments(packed, 10, exhaustive_cells=600)) == key(S.search_segments(packed, 10, search="exhaustive"))
    assert signature(detect_events).parameters["search"].default == "exhaustive"
