"""The whole chain: series to ranked event regions."""

from __future__ import annotations

from pyspark.sql import DataFrame

from rankscan.operators.prepare import segment, whole
from rankscan.operators.ranking import merge_segments, rank_events
from rankscan.operators.scan import search_segments
from rankscan.sources.tables import cut


def detect_events(
    series: DataFrame, n_s: int = 1000, w_max: int = 100, detrend: str = "linear", law: str = "exact", search: str = "exhaustive", restarts: int = 30, theta: float = 0.75, score: str = "tail",
    ties: str = "hashed", alpha: float | None = None, seed: int = 42, short: str = "own_n", per_series: str = "all", samples: int = 100_000, w_min: int = 1, rank: bool = True,
    digits: int = 9, fixed: bool = False,
) -> DataFrame:
    """Packs segments (the one shuffle of the points), then detrends, ranks, searches and clusters in one Arrow pass;
    only regions are shuffled after that: merged where segments overlap and numbered over the collection. With
    ``per_series="best"`` a segment gives one row, and hits are those in the segment that holds the best region.

    The whole plane is searched unless told otherwise; ``auto`` and ``powell`` are approximate (see ``search_segments``).
    Scores equal to ``digits`` decimals are ties throughout, which go to the earliest.

    ``series``: (series_id, t, value). Points without a value make gaps: a region's s is the time of its last point less
    w - 1. NaN is the greatest value, or left out if a line is taken off. A series without a valid value yields nothing.

    ``fixed`` takes every series, of whatever length, for one segment of n_s points, and scores it by their law, where windows
    of sums beyond it have no place. Its missing values are then points and above all others, of which digests decide; points
    at one time count together. No line can be taken off.
    """
    if fixed and detrend != "none":
        raise ValueError("fixed takes missing values for points, which have no line")
    packed = whole(series.select("series_id", "t", "value")) if fixed else segment(series.select("series_id", "t", "value"), n_s, w_max, short=short, nan=detrend == "none")
    output = "best" if per_series == "best" and rank else "regions"
    found = search_segments(packed, w_max, w_min, score, search, restarts, theta, law, samples, detrend, ties, alpha, seed, output=output, n_s=n_s, digits=digits, fixed=fixed)
    if output == "best":
        return rank_events(found, "best", digits=digits)
    merged = merge_segments(cut(found), theta, digits)
    return rank_events(merged, per_series, digits=digits) if rank else merged
