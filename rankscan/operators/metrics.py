"""Accuracy and cost measures of a ranking against known events."""

from __future__ import annotations

import time
from collections.abc import Callable

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window

from rankscan.functions.nulllaw import memo_cells  # noqa: F401  a cost measure, listed with the others
from rankscan.operators.ranking import interval_join, rank_events


def match_truth(regions: DataFrame, truth: DataFrame, bin_width: int = 64, least: float = 0.25) -> DataFrame:
    """Pairs of region and event: the region holds the peak, or their overlap is at least ``least`` of the longer."""
    events = truth.where("kind <> 'none'").select("series_id", "kind", "event_no", "t_peak", "t_lo", "t_hi")
    r = regions.withColumn("e", F.col("s") + F.col("w") - 1)
    both = interval_join(r, events, "series_id", bin_width, "s", "e", "t_lo", "t_hi")
    inter = F.least("e", "t_hi") - F.greatest("s", "t_lo") + 1
    return both.where(((F.col("t_peak") >= F.col("s")) & (F.col("t_peak") <= F.col("e"))) | (inter >= least * F.greatest(F.col("w"), F.col("t_hi") - F.col("t_lo") + 1)))


def known_ranks(ranked: DataFrame, truth: DataFrame) -> DataFrame:
    """Rank and score of each series with a known event, by kind."""
    kinds = truth.where("kind <> 'none'").select("series_id", "kind").distinct()
    return ranked.join(kinds, "series_id").select("series_id", "kind", "global_rank", "log10_p")


def rank_summary(known: DataFrame) -> DataFrame:
    """Per kind: events, median rank (lower middle) and its score, last rank and its score."""
    order = Window.partitionBy("kind").orderBy("global_rank")
    rows = known.withColumn("i", F.row_number().over(order)).withColumn("n", F.count("*").over(Window.partitionBy("kind")))
    mid = F.col("i") == F.floor((F.col("n") + 1) / 2)
    return rows.groupBy("kind").agg(F.count("*").alias("events"), F.max(F.when(mid, F.col("global_rank"))).alias("median_rank"), F.max(F.when(mid, F.col("log10_p"))).alias("median_log10_p"), F.max("global_rank").alias("last_rank"), F.max_by("log10_p", "global_rank").alias("last_log10_p"))


def recall_at(ranked: DataFrame, truth: DataFrame, percents: list[float]) -> DataFrame:
    """Share of series with known events in the best percent of ranks."""
    known, total = known_ranks(ranked, truth), ranked.agg(F.count("*").alias("total"))
    rows = known.crossJoin(F.broadcast(total)).withColumn("percent", F.explode(F.array(*[F.lit(float(p)) for p in percents])))  # one row
    return rows.groupBy("percent").agg(F.avg((F.col("global_rank") <= F.col("percent") * F.col("total") / 100).cast("double")).alias("recall"))


def percent_for_full_recall(ranked: DataFrame, truth: DataFrame) -> DataFrame:
    total = ranked.agg(F.count("*").alias("total"))
    return known_ranks(ranked, truth).agg(F.max("global_rank").alias("last")).crossJoin(total).select((100 * F.col("last") / F.col("total")).alias("percent"))


def hits_in_top(ranked: DataFrame, truth: DataFrame, k: int) -> int:
    """Series with a known event among the best k."""
    known = truth.where("kind <> 'none'").select("series_id")
    return ranked.where(F.col("global_rank") <= k).join(known, "series_id", "left_semi").count()


def false_positives_in_top(ranked: DataFrame, truth: DataFrame, k: int | None = None) -> DataFrame:
    """Rows without a known event among the best k (by default as many as there are series with events)."""
    known = truth.where("kind <> 'none'").select("series_id").distinct()
    most = F.lit(k).alias("k") if k is not None else F.count("*").alias("k")
    rows = ranked.crossJoin(F.broadcast(known.agg(most))).where(F.col("global_rank") <= F.col("k"))  # one row
    return rows.join(known, "series_id", "left_anti").agg(F.count("*").alias("false_positives"))


def separation(ranked: DataFrame, truth: DataFrame) -> DataFrame:
    """The worst score of a known event beside the best score of any other series."""
    known = truth.where("kind <> 'none'").select("series_id").distinct().withColumn("known", F.lit(True))
    rows = ranked.join(known, "series_id", "left")
    return rows.agg(F.max(F.when(F.col("known"), F.col("log10_p"))).alias("worst_event"), F.min(F.when(F.col("known").isNull(), F.col("log10_p"))).alias("best_other"))


def found_events(regions: DataFrame, truth: DataFrame, log10_alpha: float) -> DataFrame:
    """Every known event with whether a region below alpha matches it."""
    hit = match_truth(regions.where(F.col("log10_p") <= log10_alpha), truth).select("series_id", "event_no").distinct().withColumn("found", F.lit(True))
    return truth.where("kind <> 'none'").join(hit, ["series_id", "event_no"], "left").withColumn("found", F.coalesce("found", F.lit(False)))


def restart_curve(search: Callable[[int], DataFrame], truth: DataFrame, restarts: list[int], log10_alpha: float = -8.0) -> DataFrame:
    """Percent of single and double events found by number of restarts."""
    from functools import reduce

    curves = [found_events(search(r), truth, log10_alpha).groupBy("kind").agg((100 * F.avg(F.col("found").cast("double"))).alias("percent")).withColumn("restarts", F.lit(r)) for r in restarts]
    return reduce(DataFrame.unionByName, curves).groupBy("restarts").pivot("kind", ["single", "double"]).agg(F.first("percent"))


def ranked_finds(regions: DataFrame, truth: DataFrame) -> DataFrame:
    """Every event by its best region, and the best other region of each series, ranked together: series_id, known,
    log10_p, global_rank."""
    pairs = match_truth(regions, truth).select("series_id", "seg_id", "region_id", "event_no", "log10_p")
    events = pairs.groupBy("series_id", "event_no").agg(F.min("log10_p").alias("log10_p")).select("series_id", F.lit(True).alias("known"), "log10_p", F.col("event_no").alias("s"), F.lit(1).alias("w"))
    rest = regions.join(pairs.select("series_id", "seg_id", "region_id").distinct(), ["series_id", "seg_id", "region_id"], "left_anti")
    none = truth.where("kind = 'none'").select("series_id").distinct()
    others = rest.join(none, "series_id", "left_semi").groupBy("series_id").agg(F.min("log10_p").alias("log10_p"))
    return rank_events(events.unionByName(others.select("series_id", F.lit(False).alias("known"), "log10_p", F.lit(0).cast(events.schema["s"].dataType).alias("s"), F.lit(1).alias("w")))).drop("s", "w")


def misses_by_width(found: DataFrame) -> DataFrame:
    return found.groupBy("bump_theta").agg(F.count("*").alias("events"), F.sum((~F.col("found")).cast("int")).alias("missed"))


def low_chi2_in_top(ranked: DataFrame, chi2: DataFrame, k: int, cut: float = 3.0) -> DataFrame:
    return ranked.where(F.col("global_rank") <= k).join(chi2, "series_id").where(F.col("reduced") < cut).agg(F.count("*").alias("low_chi2"))


def rank_agreement(a: DataFrame, b: DataFrame, k: int) -> DataFrame:
    """Correlation of two rankings' ranks, and the share of the best k that they have in common."""
    x = a.select("series_id", F.col("global_rank").alias("ra")).join(b.select("series_id", F.col("global_rank").alias("rb")), "series_id")
    both = F.sum(((F.col("ra") <= k) & (F.col("rb") <= k)).cast("int"))
    return x.agg(F.corr("ra", "rb").alias("spearman"), (both / F.least(F.lit(k), F.count("*"))).alias("shared"))


def theta_curve(candidates: DataFrame, thetas: list[float]) -> DataFrame:
    """Number of regions and the best score by overlap threshold, from one search's end points."""
    import numpy as np
    import pandas as pd

    from rankscan.functions.regions import cluster

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        s, w, p = (pdf[c].to_numpy() for c in ("s", "w", "log10_p"))
        rows = [(pdf["series_id"].iloc[0], t, len(cluster(s, w, p, t)), float(np.min(p))) for t in thetas]
        return pd.DataFrame(rows, columns=["series_id", "theta", "regions", "best_log10_p"])

    return candidates.groupBy("series_id", "seg_id").applyInPandas(run, "series_id string, theta double, regions int, best_log10_p double")


def search_gap(restarted: DataFrame, exhaustive: DataFrame) -> DataFrame:
    """Per segment: the best score by restarts less the true one, never negative, and evaluations spent."""
    a = restarted.groupBy("series_id", "seg_id").agg(F.min("log10_p").alias("found"), F.sum("evals").alias("evals"))
    b = exhaustive.groupBy("series_id", "seg_id").agg(F.min("log10_p").alias("least"))
    return a.join(b, ["series_id", "seg_id"]).select("series_id", "seg_id", (F.col("found") - F.col("least")).alias("gap"), "evals")


def timed(run: Callable[[], DataFrame], series: int) -> dict[str, float]:
    """Seconds of a full run, per series, and series per second."""
    start = time.perf_counter()
    run().write.format("noop").mode("overwrite").save()
    s = time.perf_counter() - start
    return {"seconds": s, "seconds_per_series": s / max(1, series), "series_per_second": series / s}


def scaling_curve(run: Callable[[DataFrame], DataFrame], segments: DataFrame, shares: list[float]) -> list[dict[str, float]]:
    """Time over growing parts of the collection: linear if every series costs the same."""
    total = segments.count()
    key = F.pmod(F.xxhash64("series_id", "seg_id"), F.lit(1000)) / 1000
    return [{"share": x, **timed(lambda x=x: run(segments.where(key < x)), int(total * x))} for x in shares]


__all__ = [n for n in dir() if not n.startswith("_")] + ["rank_events"]
