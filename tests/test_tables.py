"""Queries of the study and of the laws that take their series from the given tables."""

import pytest
from pyspark.sql import functions as F

from rankscan import workloads as W
from rankscan.sources import families as C
from rankscan.sources import planted
from tests.conftest import SMALL, TINY
from tests.test_queries import test_against_sql as against_sql

LAWS = {"law_conditioning_n50_w3_10_20": "events", "law_convergence": "events", "law_critical_sums_n64": "embeddings"}


@pytest.mark.parametrize("name", ["false_positive_report", "full_recall_report", "interval_join_truth", *LAWS])
def test_these_have_sql_over_a_table(spark, name):
    assert LAWS.get(name, "events") in W.ORACLE_SQL[name]
    against_sql(spark, name)


@pytest.mark.parametrize("name", LAWS)
def test_laws_see_every_window_of_the_table(spark, name):
    rows = W.QUERIES[name](spark, SMALL).groupBy("n", "w").agg(F.sum("windows").alias("windows")).collect()
    whole = {"events": lambda n: 10_000 // n, "embeddings": lambda n: 500}[LAWS[name]]
    assert rows and all(r["windows"] == whole(r["n"]) * (r["n"] - r["w"] + 1) for r in rows)


def test_restarted_searches_take_every_block(spark):
    ids = {f"e{k}" for k in range(10)}
    assert {r[0] for r in W.detect_powell_grid(spark, SMALL).select("series_id").collect()} == ids
    assert {r[0] for r in W.cluster_regions_grid(spark, SMALL).select("series_id").distinct().collect()} == ids
    assert W.events_ranked_report(spark, SMALL).first()["events"] == 2  # in blocks 0 and 5


@pytest.mark.parametrize("name, columns", [("false_positive_report_whole", 1), ("full_recall_report_whole", 1), ("interval_join_truth_whole", 4)])
def test_whole_reports_rank_the_blocks(spark, name, columns):
    rows = W.QUERIES[name](spark, SMALL).collect()
    assert rows and len(rows[0]) == columns
    if columns == 4:
        assert {r["series_id"] for r in rows} <= {f"e{k}" for k in range(10)}


def test_events_are_planted_in_whole_blocks_alone(spark):
    series = C.event_blocks(spark, TINY, 300)  # three of 300 and one of 100
    truth, values = planted.plant_grid(series, 300)
    kinds = {r["series_id"]: r["kind"] for r in truth.collect()}
    assert kinds == {"e0": "single", "e1": "none", "e2": "none", "e3": "none"}
    both = values.join(series.withColumnRenamed("value", "was"), ["series_id", "t"])
    assert both.count() == 1000
    moved = both.where("abs(value - was) > 1e-5").select("series_id").distinct().collect()
    assert [r[0] for r in moved] == ["e0"]
