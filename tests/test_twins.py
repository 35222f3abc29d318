"""The search, the clustering and the merge against plain Python twins, and laws from files."""

import math

import numpy as np
import pytest
from pyspark.sql import functions as F

from rankscan.functions import nulllaw as N
from rankscan.functions import regions as R
from rankscan.operators import laws as L
from rankscan.operators import prepare as P
from rankscan.operators import ranking as K
from rankscan.operators import scan as S
from rankscan.plans.detect import detect_events


def plain_cluster(points, theta):
    """Best first into the first cluster whose every member it overlaps; points are (log10_p, s, w, more...)."""
    out = []
    for p in sorted(points):
        for c in out:
            if all(min(p[1] + p[2], m[1] + m[2]) - max(p[1], m[1]) >= theta * max(p[2], m[2]) for m in c):
                c.append(p)
                break
        else:
            out.append([p])
    return out


@pytest.mark.parametrize("theta", [0.05, 0.5, 0.75])
def test_clustering_equals_its_twin(theta):
    rng = np.random.default_rng(3)
    for _ in range(40):
        s, w, p = rng.integers(1, 60, 50), rng.integers(1, 25, 50), np.round(rng.normal(-5, 2, 50), 1)
        got = [[(p[i], s[i], w[i]) for i in c] for c in R.cluster(s, w, p, theta)]
        want = plain_cluster(list(zip(p, s, w)), theta)
        assert got == want
        assert [(p[i], s[i], w[i]) for i in R.best_cluster(s, w, p, theta)] == want[0]


def test_half_tables_score_as_whole_ones():
    for mode in N.MODES:
        whole = N.Law.exact(40, 12).tables(mode)
        held = N.LawTables.build(40, 12, mode)
        assert held.half == (mode in N.SYMMETRIC)
        for w in range(1, 13):
            q = np.arange(len(whole[w])) + N.least_sum(w)
            assert np.array_equal(held.scores(w, q), whole[w])


def test_search_ends_where_its_twin_says_no_neighbour_is_better():
    rng = np.random.default_rng(8)
    for k in range(5):
        v = rng.normal(size=200)
        f = R.Surface(R.hashed_ranks(v, "a", np.arange(200)), N.LawTables.build(200, 30), 1, 30)
        s, w, p, _ = R.powell(f, *R.starts(f"a{k}", 0, 20, 200, 1, 30, 42))
        for i in range(20):
            near = [f(np.array([s[i] + a]), np.array([w[i] + b]))[0] for a in (-1, 0, 1) for b in (-1, 0, 1)]
            assert p[i] == min(near) and math.isfinite(p[i])


def test_restarts_reach_the_true_minimum_of_planted_series():
    rng, n, w_max = np.random.default_rng(11), 600, 60
    laws = {m: N.LawTables.build(n, w_max, m) for m in ("tail", "mass")}
    reached = {m: 0 for m in laws}
    for k in range(40):
        v = rng.normal(0, 5, n) + (20 + 80 * rng.random()) * np.exp(-((np.arange(n) - rng.integers(120, 480)) ** 2) / (2 * (1.5 + 9 * rng.random()) ** 2))
        ranks = R.hashed_ranks(v, "a", np.arange(n))
        for m, law in laws.items():
            f = R.Surface(ranks, law, 1, w_max)
            true = min(f.row(w)[1].min() for w in range(1, w_max + 1))
            reached[m] += bool(R.powell(f, *R.starts(f"a{k}", 0, 30, n, 1, w_max, 42))[2].min() <= true + 1e-9)
    assert min(reached.values()) >= 39


def test_merge_joins_what_two_segments_share_and_nothing_else(spark):
    rng = np.random.default_rng(5)
    rows, n_s, stride = [], 60, 45
    for series in range(12):
        for seg in range(1 + series % 4):
            start = 1 + seg * stride
            for k in range(15):
                w = int(rng.integers(1, 14))
                s = start + int(rng.integers(0, n_s - w + 1))
                p = float(np.round(rng.normal(-4, 1), 2))
                rows.append((str(series), seg, k, s, w, 1, n_s, "high", p, False, 2, float(np.round(rng.random(), 3)), [(s, w, p, k)], start))
    from rankscan import schema

    got = K.merge_segments(spark.createDataFrame(rows, schema.REGIONS).repartition(3), 0.5).collect()
    want = []
    for series in range(12):
        mine = [r for r in rows if r[0] == str(series)]
        last = (series % 4) * stride + 1
        shared = [r for r in mine if (r[13] < last and r[3] + r[4] - 1 >= r[13] + stride) or (r[13] > 1 and r[3] <= r[13] - stride + n_s - 1)]
        want += [(r[0], r[8], r[3], r[4], r[10], r[11], 1) for r in mine if r not in shared]
        islands, reach = [], -1
        for r in sorted(shared, key=lambda r: (r[3], r[4])):
            if r[3] > reach:
                islands.append([])
            islands[-1].append(r)
            reach = max(reach, r[3] + r[4] - 1)
        for island in islands:
            for c in plain_cluster([(r[8], r[3], r[4], r[1], r[2], r[10], r[11]) for r in island], 0.5):
                want.append((str(series), c[0][0], c[0][1], c[0][2], sum(x[5] for x in c), max(x[6] for x in c), len(c)))
    assert sorted((r["series_id"], r["log10_p"], r["s"], r["w"], r["hits"], r["hit_share"], len(r["members"])) for r in got) == sorted(want)


def test_best_of_each_series_is_the_best_of_all_its_regions(spark):
    rows = [(f"x{k}", t, float(v)) for k in range(4) for t, v in enumerate(np.random.default_rng(k).normal(size=150 + 10 * k).cumsum(), 1)]
    series = spark.createDataFrame(rows, "series_id string, t bigint, value double")
    cols = ["series_id", "s", "w", "log10_p"]
    best = detect_events(series, 60, 10, per_series="best").select(cols).collect()
    every = K.best_per_series(detect_events(series, 60, 10)).select(cols).collect()
    assert sorted(map(tuple, best)) == sorted(map(tuple, every)) and len(best) == 4


def test_laws_are_made_once_and_read_by_workers(spark):
    files = L.LawFiles(spark, 7, "mass").prepare(spark, [33])
    held = files._read(33)
    assert held is not None and np.array_equal(held.flat, N.LawTables.build(33, 7, "mass").flat)
    packed = P.segment(spark.range(1, 34).select(F.lit("a").alias("series_id"), F.col("id").alias("t"), F.rand(3).alias("value")), 33, 7)
    found = S.search_segments(packed, 7, mode="mass", output="surface").collect()
    assert len(found) == sum(33 - w + 1 for w in range(1, 8))


def test_a_long_series_segments_are_spread_over_tasks(spark):
    long = spark.range(1, 20_000).select(F.when(F.col("id") > 0, "a").alias("series_id"), F.col("id").alias("t"), F.rand(1).alias("value"))
    sizes = [r[1] for r in P.segment(long, 300, 40).groupBy(F.spark_partition_id()).count().collect()]
    assert len(sizes) > 1 and max(sizes) < sum(sizes)


@pytest.mark.parametrize("digits", [6, 9])
def test_of_equal_scores_the_earliest_is_the_best_in_every_search(digits):
    """Equal tails differ in their floats' last digits, and near ones agree in six decimals only."""
    tables, rng = N.LawTables.build(60, 10), np.random.default_rng(7)
    lost = 0
    for _ in range(1500):
        f = R.Surface(rng.permutation(60) + 1, tables, 1, 10)
        cells = [(round(float(p), digits), s, w) for w in range(1, 11) for s, p in enumerate(f.row(w)[1], 1)]
        want = min(cells)
        s, w, p = S.local_minima(f, digits)
        i = R.best_cluster(s, w, p, 0.75, digits)[0]
        assert (s[i], w[i]) == want[1:] == f.best(digits)[:2]
        s, w, p, evals = R.powell(f, *R.starts("a", 0, 60, 60, 1, 10, 42))
        lost += want[1:] not in zip(s.tolist(), w.tolist())
        s, w, p, _ = R.with_best(f, s, w, p, evals, digits)
        i = R.best_cluster(s, w, p, 0.75, digits)[0]
        assert (s[i], w[i]) == want[1:] and round(float(p[i]), digits) == want[0]
    assert lost  # restarts alone do not end in each of some equal windows
