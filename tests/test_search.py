import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F

from rankscan.functions import regions as R
from rankscan.functions.nulllaw import Law
from rankscan.operators import baselines as B
from rankscan.operators import prepare as P
from rankscan.operators import ranking as K
from rankscan.operators import scan as S
from rankscan.plans.detect import detect_events
from rankscan.plans.planner import choose_search
from rankscan.sources import planted


def surface(values, w_max, mode="tail"):
    ranks = R.hashed_ranks(np.asarray(values, float), "x", np.arange(1, len(values) + 1))
    return R.Surface(ranks, Law.exact(len(values), w_max).tables(mode), 1, w_max)


@given(st.tuples(*[st.integers(1, 60)] * 4), st.sampled_from([0.05, 0.25, 0.5, 0.75, 1.0]))
def test_both_forms_of_the_overlap_test(x, theta):
    s1, w1, s2, w2 = x
    assert R.overlaps_by_terms(*x, theta) == bool(R.overlaps(*x, theta)) == bool(R.overlaps(s2, w2, s1, w1, theta))
    if theta == 1.0:
        assert bool(R.overlaps(*x, theta)) == ((s1, w1) == (s2, w2))


def test_clusters_of_the_fixture():
    points = [(50, 10, -9), (51, 10, -8), (50, 11, -7), (120, 8, -6), (120, 9, -5), (48, 40, -4)]
    s, w, p = (np.array(x) for x in zip(*points))
    assert sorted(map(len, R.cluster(s, w, p, 0.75))) == [1, 2, 3]
    assert sorted(map(len, R.cluster(s, w, p, 0.05))) == [2, 4]
    for members in R.cluster(s, w, p, 0.75):
        assert members[0] == min(members, key=lambda i: p[i])
        assert all(R.overlaps(s[i], w[i], s[j], w[j], 0.75) for i in members for j in members)


@given(st.lists(st.integers(-5, 5), min_size=2, max_size=40), st.integers(0, 3))
@settings(deadline=None)
def test_ranks_are_permutations_kept_by_increasing_maps(values, k):
    v, t = np.array(values, float), np.arange(1, len(values) + 1)
    r = R.hashed_ranks(v, "s", t)
    assert sorted(r) == list(range(1, len(v) + 1))
    grown = [np.exp(v / 3), v**3, 2 * v + 7, v][k]
    assert (R.hashed_ranks(grown, "s", t) == r).all()
    assert all(r[i] < r[j] for i in range(len(v)) for j in range(len(v)) if v[i] < v[j])


def test_restarts_reach_the_true_minimum_more_often_the_more_there_are():
    rng = np.random.default_rng(5)
    reached = {5: 0, 30: 0}
    for k in range(25):
        v = rng.normal(0, 5, 300)
        v += 60 * np.exp(-((np.arange(300) - rng.integers(60, 240)) ** 2) / (2 * 3.0**2))
        f = surface(v, 40)
        true = min(f.row(w)[1].min() for w in range(1, 41))
        for r in reached:
            s, w, p, evals = R.powell(f, *R.starts(f"s{k}", 0, r, 300, 1, 40, 42))
            assert p.min() >= true - 1e-12 and np.allclose(f(s, w), p) and evals.min() > 0
            reached[r] += bool(p.min() <= true + 1e-9)
    assert reached[5] <= reached[30] and reached[30] >= 23


@pytest.mark.parametrize("name", ["coordinate", "pattern"])
def test_other_minimisers_end_on_the_surface(name):
    f = surface(np.random.default_rng(1).normal(size=120), 20)
    s, w, p, _ = R.MINIMISERS[name](f, *R.starts("a", 0, 10, 120, 1, 20, 1))
    assert np.allclose(f(s, w), p) and np.isfinite(p).all()


def test_an_outlier_moves_the_discord_not_the_event():
    rng = np.random.default_rng(2)
    v = rng.normal(0, 5, 400) + 40 * np.exp(-((np.arange(400) - 200) ** 2) / (2 * 4.0**2))
    spoiled = v.copy()
    spoiled[50] = -200
    best = []
    for x in (v, spoiled):
        f = surface(x, 40)
        best.append(min((f.row(w)[1].min(), w) for w in range(1, 41)))
    assert abs(best[0][0] - best[1][0]) < 1.5
    assert abs(B.discord_of(v, 20, False)[0] - 190) < 25 and abs(B.discord_of(spoiled, 20, False)[0] - 41) < 25


@pytest.mark.parametrize("znorm", [False, True])
def test_discords_by_words_equal_brute_force(znorm):
    for k in range(5):
        v = np.random.default_rng(k).normal(size=90)
        a, b = B.discord_of(v, 8, znorm), B.discord_by_words(v, 8, znorm)
        assert a[0] == b[0] and a[2] == pytest.approx(b[2])


def test_planner():
    assert choose_search(1000, 100) == "exhaustive" and choose_search(5000, 1000) == "powell"


# ---- on Spark ---------------------------------------------------------------------------------------------------------


@pytest.fixture(scope="module")
def series(spark):
    truth = planted.grid_truth(spark, 300, every=100)
    return planted.grid_values(truth, 300).cache()


def test_segments_cover_every_window(spark):
    long = spark.range(1, 2500).select(F.lit("a").alias("series_id"), F.col("id").alias("t"), F.rand(1).alias("value"))
    short = spark.range(1, 8).select(F.lit("b").alias("series_id"), F.col("id").alias("t"), F.rand(1).alias("value"))
    rows = P.segment(long.union(short), 1000, 100).orderBy("series_id", "seg_id").collect()
    assert [(r["series_id"], r["seg_start"], r["n"]) for r in rows] == [("a", 1, 1000), ("a", 901, 1000), ("a", 1500, 1000), ("b", 1, 7)]
    assert all(r["t"] == list(range(r["seg_start"], r["seg_start"] + r["n"])) for r in rows)
    spans = [(r["seg_start"], r["seg_start"] + 999) for r in rows[:3]]
    assert all(any(a <= s and s + 99 <= b for a, b in spans) for s in range(1, 2400))
    assert P.segment(short, 1000, 100, short="drop").count() == 0


def test_invalid_values_are_left_out(spark):
    df = spark.createDataFrame([("a", 1, 1.0), ("a", 2, None), ("a", 3, float("nan")), ("a", 4, 2.0), ("b", 1, None)], "series_id string, t bigint, value double")
    rows = P.segment(df, 10, 3).collect()
    assert [(r["series_id"], r["t"]) for r in rows] == [("a", [1, 4])]
    assert detect_events(df.limit(0), 10, 3).count() == 0


def test_results_do_not_depend_on_partitions(spark, series):
    def rows(df):
        return sorted((r["series_id"], r["s"], r["w"], round(r["log10_p"], 9), r["hits"], r["global_rank"]) for r in detect_events(df, 200, 20, search="powell", restarts=10).collect())

    assert rows(series.coalesce(1)) == rows(series.repartition(7))


def test_worker_surface_equals_sql_surface(spark, series):
    packed = P.segment(series, 300, 12)
    a = S.search_segments(packed, 12, output="surface").selectExpr("series_id", "s", "w", "q", "round(log10_p, 6) p")
    b = S.scan_sql(series, [300], 12).selectExpr("series_id", "s", "w", "q", "log10_p p")
    assert a.exceptAll(b).count() == 0 and a.count() == b.count()


def test_planted_events_lead_the_ranking(spark):
    truth = planted.grid_truth(spark, 1000, every=25).cache()
    packed = P.segment(planted.grid_values(truth, 1000), 1000, 100)
    ranked = K.rank_events(S.search_segments(packed, 100, search="powell", restarts=30), per_series="best").cache()
    known = {r[0] for r in truth.where("kind <> 'none'").select("series_id").collect()}
    order = [r["series_id"] for r in ranked.orderBy("global_rank").select("series_id").collect()]
    assert len(order) == truth.select("series_id").distinct().count()
    assert len(known & set(order[: len(known)])) >= len(known) - 1
    assert ranked.join(truth.where("kind = 'none'"), "series_id").where("log10_p <= -8").count() == 0


def test_global_rank_has_no_gaps(spark):
    df = spark.range(1000).selectExpr("cast(id as string) series_id", "(id * 7919) % 1000 / 3.0 log10_p", "id s", "1 w")
    rows = K.rank_rows(df, F.asc("log10_p"), F.asc("series_id")).collect()
    assert sorted(r["global_rank"] for r in rows) == list(range(1, 1001))
    assert [r["log10_p"] for r in sorted(rows, key=lambda r: r["global_rank"])] == sorted(r["log10_p"] for r in rows)


def test_plans(spark, series):
    plan = S.scan_sql(series, [300], 5)._jdf.queryExecution().toString()
    assert "BroadcastHashJoin" in plan and "CartesianProduct" not in plan
    packed = P.segment(series.select("series_id", "t", "value"), 300, 20)._jdf.queryExecution().executedPlan().toString()
    assert "Python" not in packed and "CartesianProduct" not in packed


def test_stream_finds_what_the_batch_finds(spark, series, tmp_path):
    from rankscan.streaming.detect import detect_stream

    one = series.where("series_id in ('g0', 'g100')")
    for k, (a, b) in enumerate([(1, 150), (151, 230), (231, 300)]):
        one.where(f"t between {a} and {b}").coalesce(1).write.parquet(f"{tmp_path}/in/{k}")
        run = detect_stream(spark.readStream.schema(series.schema).parquet(f"{tmp_path}/in/*"), 120, 20).writeStream.format("parquet").option("path", f"{tmp_path}/out").option("checkpointLocation", f"{tmp_path}/state").trigger(availableNow=True).start()
        run.awaitTermination()
    got = {(r["series_id"], r["seg_start"], r["s"], r["w"]) for r in spark.read.parquet(f"{tmp_path}/out").collect()}
    packed = P.segment(one, 120, 20).where("seg_start % 100 = 1")
    want = {(r["series_id"], 100 * r["seg_id"] + 1, r["s"], r["w"]) for r in S.search_segments(packed, 20, search="powell", restarts=30).collect()}
    assert got == want
