"""Series with planted events: digest noise, so that any engine makes the same values, plus bumps."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from rankscan.sources.tables import cut

WIDTHS, HEIGHTS = 19, 17


def uniform(*parts: Column) -> Column:
    """In (0, 1), from the digest's first eight hexadecimal digits."""
    digits = F.substring(F.md5(F.concat_ws("|", *[p.cast("string") for p in parts])), 1, 8)
    return (F.conv(digits, 16, 10).cast("bigint") + 0.5) / float(1 << 32)


def grid_truth(spark: SparkSession, n: int = 1000, singles: int = WIDTHS * HEIGHTS, doubles: int = 50, nulls: int = 1627, every: int = 1, seed: int = 42, places: DataFrame | None = None) -> DataFrame:
    """One row per planted event, and one of kind none for each series without: the grid of widths and heights, then
    double events, then noise. ``every`` keeps each so-manieth series of the full grid's numbering.
    ``places`` (series_id, k, place) are given series instead, each with its place in that numbering."""
    if places is None:
        k = F.col("id")
        places = spark.range(0, singles + doubles + nulls, every).select(F.concat(F.lit("g"), k.cast("string")).alias("series_id"), k.alias("k"), k.alias("place"))
    ids, place = places, F.col("place")
    kind = F.when(place < singles, "single").when(place < singles + doubles, "double").otherwise("none")
    rows = ids.withColumn("kind", kind).withColumn("event_no", F.explode(F.when(F.col("kind") == "double", F.array(F.lit(0), F.lit(1))).otherwise(F.array(F.lit(0)))))
    j = F.when(F.col("kind") == "single", place).otherwise((place * 7 + F.col("event_no") * 53) % (WIDTHS * HEIGHTS))
    rows = rows.withColumn("bump_theta", 1.5 + 0.5 * (j % WIDTHS)).withColumn("height", 20.0 + 5 * F.floor(j / WIDTHS))
    u = uniform(F.lit(seed), F.lit("peak"), F.col("k"), F.col("event_no"))
    single = F.floor(0.2 * n + u * 0.6 * n)
    double = F.floor(F.when(F.col("event_no") == 0, 0.2 * n + u * 0.1 * n).otherwise(0.7 * n + u * 0.1 * n))
    peak = F.when(F.col("kind") == "double", double).otherwise(single).cast("bigint")
    shown = lambda c: F.when(F.col("kind") != "none", c)
    rows = rows.withColumn("t_peak", shown(peak)).withColumn("half", F.ceil(2 * F.col("bump_theta")).cast("bigint"))
    return rows.select("series_id", "k", "kind", "event_no", "t_peak", (F.col("t_peak") - F.col("half")).alias("t_lo"), (F.col("t_peak") + F.col("half")).alias("t_hi"), shown(F.col("height")).alias("height"), shown(F.col("bump_theta")).alias("bump_theta"))


def grid_values(truth: DataFrame, n: int = 1000, sigma: float = 5.0, seed: int = 42) -> DataFrame:
    """The series of ``grid_truth``: bumps plus Gaussian noise, rounded to six decimals. One row per series is joined to
    nothing: bumps are gathered per series first, points are made after."""
    bumps = truth.groupBy("series_id", "k").agg(F.array_sort(F.collect_list(F.when(F.col("kind") != "none", F.struct("event_no", "t_peak", "height", "bump_theta")))).alias("b"))
    points = bumps.withColumn("t", F.explode(F.sequence(F.lit(1).cast("bigint"), F.lit(n).cast("bigint"))))
    u1, u2 = (uniform(F.lit(seed), F.col("k"), F.col("t"), F.lit(i)) for i in (1, 2))
    noise = F.sqrt(-2 * F.ln(u1)) * F.cos(2 * 3.141592653589793 * u2) * sigma
    bump = F.aggregate("b", F.lit(0.0), lambda a, x: a + x["height"] * F.exp(-(F.col("t") - x["t_peak"]) * (F.col("t") - x["t_peak"]) / (2 * x["bump_theta"] * x["bump_theta"])))
    return points.select("series_id", "t", F.round(bump + noise, 6).alias("value"))


def plant_grid(series: DataFrame, n: int, seed: int = 42) -> tuple[DataFrame, DataFrame]:
    """The grid's events in given series (series_id, k, t, value; t from 1 without gaps): truth and values. Kinds are
    scattered over k as the grid has them; a series of fewer than n points keeps its values and counts as one without event.
    Heights are in fifths of a series' robust noise, as the grid's are of its own."""
    ends = series.groupBy("series_id", "k").agg(F.max("t").alias("length"))
    whole = WIDTHS * HEIGHTS + 50 + 1627
    # a step near the golden section, so that any run of k has all kinds
    place = F.when(F.col("length") == n, F.col("k") * 1237 % whole).otherwise(whole - 1)
    truth = cut(grid_truth(series.sparkSession, n, seed=seed, places=ends.select("series_id", "k", place.alias("place"))))
    events = truth.where("kind <> 'none'").groupBy("series_id").agg(F.array_sort(F.collect_list(F.struct("event_no", "t_peak", "height", "bump_theta"))).alias("b"))
    noise = robust_sigma(series.join(events.select("series_id"), "series_id")).withColumn("sigma", F.round("sigma", 6))
    gap = lambda x: F.col("t") - x["t_peak"]
    bump = F.aggregate("b", F.lit(0.0), lambda a, x: a + x["height"] * F.exp(-gap(x) * gap(x) / (2 * x["bump_theta"] * x["bump_theta"])))
    rows = series.join(events.join(noise, "series_id"), "series_id", "left")
    return truth, rows.select("series_id", "t", F.round(F.col("value") + F.coalesce(bump * F.col("sigma") / 5, F.lit(0.0)), 6).alias("value"))


def add_outlier(series: DataFrame, truth: DataFrame, n: int = 1000, seed: int = 42) -> DataFrame:
    """One point a series is set to -5 times its height (60 for noise), away from any event's peak or not."""
    at = truth.groupBy("series_id", "k").agg(F.max(F.coalesce("height", F.lit(60.0))).alias("h"))
    at = at.select("series_id", "h", (1 + F.floor(uniform(F.lit(seed), F.lit("outlier"), F.col("k")) * n)).cast("bigint").alias("t_out"))
    return series.join(at, "series_id").select("series_id", "t", F.when(F.col("t") == F.col("t_out"), -5 * F.col("h")).otherwise(F.col("value")).alias("value"))


def robust_sigma(series: DataFrame) -> DataFrame:
    """Noise per series from the median absolute first difference."""
    from pyspark.sql import Window

    step = series.select("series_id", F.abs(F.col("value") - F.lag("value").over(Window.partitionBy("series_id").orderBy("t"))).alias("d"))
    return step.groupBy("series_id").agg((1.4826 * F.median("d") / 2**0.5).alias("sigma"))


def plant(series: DataFrame, share: int, height: float, bump_theta: float, seed: int = 42) -> tuple[DataFrame, DataFrame]:
    """Adds a bump of ``height`` robust sigmas to one in ``share`` series; returns the series and the truth."""
    ends = series.groupBy("series_id").agg(F.max("t").alias("n"))
    # exact as an integer test on the digest
    pick = (F.floor(uniform(F.lit(seed), F.lit("pick"), F.col("series_id")) * share) == 0) & (F.col("n") > 20)
    peak = F.floor(0.2 * F.col("n") + uniform(F.lit(seed), F.lit("peak"), F.col("series_id")) * 0.6 * F.col("n")).cast("bigint")
    half = int(2 * bump_theta + 0.999999)
    truth = ends.where(pick).select("series_id", F.lit("single").alias("kind"), F.lit(0).alias("event_no"), peak.alias("t_peak"), (peak - half).alias("t_lo"), (peak + half).alias("t_hi"), F.lit(float(height)).alias("height"), F.lit(float(bump_theta)).alias("bump_theta"))
    truth = cut(truth)
    all_rows = series.join(cut(robust_sigma(series)), "series_id").join(truth.select("series_id", "t_peak"), "series_id", "left")
    bump = F.col("sigma") * height * F.exp(-F.pow(F.col("t") - F.col("t_peak"), 2) / (2 * bump_theta**2))
    return all_rows.select("series_id", "t", (F.col("value") + F.coalesce(bump, F.lit(0.0))).alias("value")), truth
