"""Streams of points: bins, sliding counts, sessions, duplicates, and detection of completed segments with bounded state."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from rankscan.functions import regions as R
from rankscan.operators.laws import LawFiles


def _timed(points: DataFrame, late: str) -> DataFrame:
    return points.withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", late)


def tumbling_counts(points: DataFrame, key: str, width: str = "1 hour", late: str = "1 hour") -> DataFrame:
    """Points per key and bin; a bin is final when the watermark has passed it, later points are dropped."""
    return _timed(points, late).groupBy(F.col(key).alias("series_id"), F.window("ts", width)).agg(F.count("*").alias("value")).select("series_id", F.col("window.start").alias("ts"), "value")


def sliding_counts(points: DataFrame, key: str, width: str, slide: str, late: str = "1 hour") -> DataFrame:
    return _timed(points, late).groupBy(F.col(key).alias("series_id"), F.window("ts", width, slide)).agg(F.count("*").alias("value")).select("series_id", F.col("window.start").alias("ts"), "value")


def sessions(points: DataFrame, key: str, gap: str = "30 minutes", late: str = "1 hour") -> DataFrame:
    return _timed(points, late).groupBy(F.col(key).alias("series_id"), F.session_window("ts", gap)).agg(F.count("*").alias("value")).select("series_id", F.col("session_window.start").alias("start"), F.col("session_window.end").alias("end"), "value")


def deduplicated(points: DataFrame, id_col: str, late: str = "1 hour") -> DataFrame:
    return _timed(points, late).dropDuplicatesWithinWatermark([id_col])


def with_law(windows: DataFrame, law: DataFrame) -> DataFrame:
    """Scores windows (n, w, q) of a stream by a static law of bounded size."""
    return windows.join(F.broadcast(law), ["n", "w", "q"], "left")


REGION = "series_id string, seg_start bigint, s bigint, w int, log10_p double, hits int"


def detect_stream(series: DataFrame, n_s: int, w_max: int, restarts: int = 30, theta: float = 0.75, seed: int = 42) -> DataFrame:
    """Regions of each completed segment of a stream (series_id, t, value) that comes in order of t within a series.

    The state of a series is its last n_s values at most; every n_s - w_max new values complete a segment, as in a batch.
    """
    laws = LawFiles(series.sparkSession, w_max).prepare(series.sparkSession, [n_s])
    stride = n_s - w_max

    def run(key: tuple, batches: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        times, values = (list(x) for x in state.get) if state.exists else ([], [])
        rows = pd.concat(list(batches)).sort_values("t")
        times += rows["t"].tolist()
        values += rows["value"].tolist()
        out = []
        while len(values) >= n_s:
            t = np.array(times[:n_s])
            f = R.Surface(R.hashed_ranks(np.array(values[:n_s]), key[0], t), laws.get(n_s), 1, w_max)
            s0, w0, angles = R.starts(key[0], int(t[0] - 1) // stride, restarts, n_s, 1, f.w_max, seed)
            s, w, p, _ = R.with_best(f, *R.powell(f, s0, w0, angles))
            for members in R.cluster(s, w, p, theta):
                i = members[0]
                out.append((key[0], int(t[0]), int(t[0] + s[i] - 1), int(w[i]), float(p[i]), len(members)))
            times, values = times[stride:], values[stride:]
        state.update((times, values))
        if out:
            yield pd.DataFrame(out, columns=["series_id", "seg_start", "s", "w", "log10_p", "hits"])

    return series.groupBy("series_id").applyInPandasWithState(run, REGION, "times array<bigint>, values array<double>", "append", GroupStateTimeout.NoTimeout)
