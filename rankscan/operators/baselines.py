"""What the method is compared with: discord search, chi-square test, randomisation, fixed windows, raw deviation."""

from __future__ import annotations

import zlib
from collections import defaultdict
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window

from rankscan import schema
from rankscan.functions import regions as R
from rankscan.functions.nulllaw import LawTables
from rankscan.operators.laws import LawFiles
from rankscan.operators.ranking import best_per_series, rank_rows


def _normalised(windows: np.ndarray) -> np.ndarray:
    sd = windows.std(1, keepdims=True)
    return (windows - windows.mean(1, keepdims=True)) / np.where(sd > 0, sd, 1)


def nearest_all(v: np.ndarray, n: int, znorm: bool) -> tuple[np.ndarray, np.ndarray]:
    """Squared distance of every window to its nearest window that does not overlap it, and that one's place."""
    if znorm:
        x = _normalised(np.lib.stride_tricks.sliding_window_view(v, n))
        d = np.maximum((x**2).sum(1)[:, None] + (x**2).sum(1)[None] - 2 * x @ x.T, 0)
    else:
        # along each diagonal of the difference table a window's distance is a running sum less one n back
        m = len(v) - n + 1
        d = np.full((m, m), np.inf)
        for k in range(n, m):
            run = np.concatenate([[0], np.cumsum((v[k:] - v[:-k]) ** 2)])
            both = np.maximum(run[n:] - run[:-n], 0)
            i = np.arange(m - k)
            d[i, i + k] = d[i + k, i] = both
    i = np.arange(len(d))
    d[np.abs(i[:, None] - i[None]) < n] = np.inf
    return d.min(1), d.argmin(1)


def discord_of(v: np.ndarray, n: int, znorm: bool) -> tuple[int, int, float]:
    near, at = nearest_all(v, n, znorm)
    p = int(np.where(np.isfinite(near), np.round(near, 9), -1).argmax())
    return p + 1, int(at[p]) + 1, float(np.sqrt(near[p])) if np.isfinite(near[p]) else 0.0


def _word(x: np.ndarray, letters: int, alphabet: int) -> tuple:
    z = (x - x.mean()) / (x.std() or 1)
    cuts = {2: [0.0], 3: [-0.43, 0.43], 4: [-0.67, 0.0, 0.67]}[alphabet]
    return tuple(np.searchsorted(cuts, [p.mean() for p in np.array_split(z, letters)]).tolist())


def discord_by_words(v: np.ndarray, n: int, znorm: bool, letters: int = 3, alphabet: int = 3) -> tuple[int, int, float]:
    """The same answer with early abandoning: windows of rare words are tried first, and each is compared first with
    windows of its own word, which are likely near."""
    m = len(v) - n + 1
    windows = np.lib.stride_tricks.sliding_window_view(v, n)
    shown = _normalised(windows) if znorm else windows
    words = [_word(x, letters, alphabet) for x in windows]
    buckets = defaultdict(list)
    for i, word in enumerate(words):
        buckets[word].append(i)
    best, exact, where, near_at = -1.0, 0.0, 0, 0
    for i in sorted(range(m), key=lambda i: (len(buckets[words[i]]), i)):
        nearest, at = np.inf, -1
        own = np.array([j for j in buckets[words[i]] if abs(i - j) >= n], np.int64)
        others = np.array([j for j in range(m) if abs(i - j) >= n and words[j] != words[i]], np.int64)
        for group in (own, others):
            for a in range(0, len(group), 64):
                part = group[a : a + 64]
                d = ((shown[part] - shown[i]) ** 2).sum(1)
                if d.min() < nearest:
                    nearest, at = float(d.min()), int(part[d.argmin()])
                if nearest < best - 1e-9:
                    break
            if nearest < best - 1e-9:
                break
        shown_d = round(nearest, 9) if np.isfinite(nearest) else -1.0
        if shown_d > best or shown_d == best and i < where:
            best, exact, where, near_at = shown_d, nearest, i, at
    return where + 1, near_at + 1, float(np.sqrt(exact)) if np.isfinite(exact) else 0.0


def discords(segments: DataFrame, n: int, znorm: bool = False, method: str = "brute") -> DataFrame:
    """Each segment's window that is farthest from its nearest non-overlapping window. Segments shorter than 2n have none."""
    find = discord_of if method == "brute" else discord_by_words

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for pdf in batches:
            rows = [(r.series_id, r.seg_id, n, *find(np.asarray(r.values, float), n, znorm)) for r in pdf.itertuples(index=False) if r.n >= 2 * n]
            yield pd.DataFrame(rows, columns=["series_id", "seg_id", "n", "pos", "nn_pos", "distance"])

    return segments.mapInPandas(run, schema.DISCORDS)


def discords_sql(series: DataFrame, n: int) -> DataFrame:
    """Nearest-neighbour distances by a self join of windows with a residual condition; for short series only."""
    order = Window.partitionBy("series_id").orderBy("t").rowsBetween(0, n - 1)
    windows = series.select("series_id", "t", F.collect_list("value").over(order).alias("x")).where(F.size("x") == n)
    a, b = windows.alias("a"), windows.alias("b")
    d = F.aggregate(F.zip_with("a.x", "b.x", lambda p, q: (p - q) * (p - q)), F.lit(0.0), lambda s, x: s + x)
    near = a.join(b, (F.col("a.series_id") == F.col("b.series_id")) & (F.abs(F.col("a.t") - F.col("b.t")) >= n)).groupBy("a.series_id", "a.t").agg(F.min(d).alias("d"))
    return near.select("series_id", F.col("t").cast("int").alias("pos"), F.sqrt("d").alias("distance"))


def rank_discords(found: DataFrame) -> DataFrame:
    best = best_per_series(found, "distance", least=False)
    return rank_rows(best, F.desc("distance"), F.asc("series_id"))


def chi_square(series: DataFrame, sigma: str | float = "diff") -> DataFrame:
    """Chi-square of a constant baseline per series: chi2, dof, reduced. ``sigma``: "diff" (from first differences),
    "mad" (median absolute first difference) or a number."""
    rows = series
    if isinstance(sigma, str):
        rows = rows.withColumn("d", F.col("value") - F.lag("value").over(Window.partitionBy("series_id").orderBy("t")))
        noise = F.sum(F.col("d") * F.col("d")) / (2 * F.count("d")) if sigma == "diff" else F.pow(1.4826 * F.median(F.abs("d")), 2) / 2
    else:
        noise = F.lit(float(sigma) ** 2)
    out = rows.groupBy("series_id").agg(F.var_pop("value").alias("var"), F.count("value").alias("n"), noise.alias("noise"))
    return out.select("series_id", (F.col("var") * F.col("n") / F.nullif("noise", F.lit(0.0))).alias("chi2"), (F.col("n") - 1).cast("int").alias("dof")).withColumn("reduced", F.col("chi2") / F.nullif("dof", F.lit(0)))


def randomization_test(segments: DataFrame, shuffles: int, w_max: int, mode: str = "tail", seed: int = 42, share: int = 50) -> DataFrame:
    """Empirical p of each segment's best window: the share of shuffled copies whose best window is at least as extreme.

    Shuffles are dealt to tasks in shares, seeded by segment and share.
    """
    laws = LawFiles(segments.sparkSession, w_max, mode)

    def best(ranks: np.ndarray, tables: LawTables) -> float:
        f = R.Surface(ranks, tables, 1, w_max)
        return min(float(f.row(w)[1].min()) for w in range(f.w_min, f.w_max + 1))

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for pdf in batches:
            rows = []
            for r in pdf.itertuples(index=False):
                tables = laws.get(r.n)
                ranks = R.hashed_ranks(np.asarray(r.values, float), r.series_id, np.asarray(r.t))
                real = best(ranks, tables)
                rng = np.random.default_rng([seed, zlib.crc32(f"{r.series_id}|{r.seg_id}".encode()), r.share])
                n = min(share, shuffles - r.share * share)
                rows.append((r.series_id, r.seg_id, real, n, sum(best(rng.permutation(ranks), tables) <= real for _ in range(n))))
            yield pd.DataFrame(rows, columns=["series_id", "seg_id", "log10_p", "n", "hits"])

    shares = segments.withColumn("share", F.explode(F.sequence(F.lit(0), F.lit(-(-shuffles // share) - 1))))
    done = shares.mapInPandas(run, "series_id string, seg_id int, log10_p double, n int, hits int")
    return done.groupBy("series_id", "seg_id").agg(F.min("log10_p").alias("log10_p"), ((F.sum("hits") + 1) / (F.sum("n") + 1)).alias("empirical_p"))


def fixed_window(series: DataFrame, w: int) -> DataFrame:
    """Greatest and least sum of the windows of one width, and where (the first of equals)."""
    order = Window.partitionBy("series_id").orderBy("t").rowsBetween(0, w - 1)
    sums = series.select("series_id", "t", F.sum("value").over(order).alias("x"), F.count("*").over(order).alias("c")).where(F.col("c") == w)
    return sums.groupBy("series_id").agg(F.max("x").alias("most"), F.max_by("t", F.struct("x", -F.col("t"))).alias("most_at"), F.min("x").alias("least"), F.min_by("t", F.struct("x", "t")).alias("least_at"))


def deviations(series: DataFrame, w_max: int) -> DataFrame:
    """The window of largest |sum of deviations from the mean| / sqrt(width): overdensity without significance."""
    whole = Window.partitionBy("series_id")
    centred = series.select("series_id", "t", (F.col("value") - F.avg("value").over(whole)).alias("d"))
    run = centred.select("series_id", "t", F.sum("d").over(whole.orderBy("t").rowsBetween(Window.unboundedPreceding, 0)).alias("c"))
    before = run.select("series_id", F.col("t").alias("u"), F.col("c").alias("c0")).unionAll(run.where("t = 1").select("series_id", F.lit(0).cast("bigint"), F.lit(0.0)))
    ends = run.withColumn("w", F.explode(F.sequence(F.lit(1), F.lit(w_max)))).where("t >= w").withColumn("u", F.col("t") - F.col("w"))
    score = F.round(F.abs(F.col("c") - F.col("c0")) / F.sqrt("w"), 6)
    all_rows = ends.join(before, ["series_id", "u"]).select("series_id", (F.col("u") + 1).alias("s"), "w", score.alias("score"))
    key = F.struct("score", -F.col("w"), -F.col("s"))
    return all_rows.groupBy("series_id").agg(F.max("score").alias("score"), F.max_by("s", key).alias("s"), F.max_by("w", key).alias("w"))
