"""SQL entry points: scalar and aggregate pandas functions and a table function."""

from __future__ import annotations

from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql.functions import pandas_udf, udtf
from pyspark.sql.types import ArrayType, DoubleType, LongType

from rankscan.functions import nulllaw as N
from rankscan.functions import regions as R


#: Widest window where none is given, as in ``detect_events``.
W_MAX = 100


@lru_cache(maxsize=8)
def _law(n: int, w_max: int) -> N.LawTables:
    """One worker's tables, a few at most."""
    return N.LawTables.build(n, w_max)


@pandas_udf(ArrayType(LongType()))
def rank_array(values: pd.Series, keys: pd.Series) -> pd.Series:
    """Ranks of an array's values; ties by digest of the key and the place."""
    return pd.Series([R.hashed_ranks(np.asarray(v, float), str(k), np.arange(1, len(v) + 1)) for v, k in zip(values, keys)])


@pandas_udf(DoubleType())
def log10_binom(n: pd.Series, w: pd.Series) -> pd.Series:
    return pd.Series([N.log10_binom(int(a), int(b)) for a, b in zip(n, w)])


@pandas_udf(DoubleType())
def interval_log10_p(q: pd.Series, w: pd.Series, n: pd.Series) -> pd.Series:
    """Log10 of the smaller tail of a rank sum."""
    out = np.empty(len(q))
    for (size, width), at in pd.DataFrame({"n": n, "w": w}).groupby(["n", "w"]).indices.items():
        out[at] = _law(int(size), int(width)).scores(int(width), q.to_numpy()[at].astype(int))
    return pd.Series(out)


@pandas_udf(ArrayType(DoubleType()))
def best_interval(value: pd.Series, t: pd.Series, w_max: pd.Series = None) -> list:
    """Aggregate: (s, w, log10_p) of a series' most significant window of at most ``w_max`` points (100, as in detection)."""
    order = np.argsort(t.to_numpy(), kind="stable")
    v, at = value.to_numpy()[order], t.to_numpy()[order]
    w_max = min(len(v), W_MAX if w_max is None else int(w_max.iloc[0]))
    f = R.Surface(R.hashed_ranks(v, "", at), _law(len(v), w_max), 1, w_max)
    best = min((float(p.min()), w, int(p.argmin()) + 1) for w in range(1, f.w_max + 1) for p in [f.row(w)[1]])
    return [float(best[2]), float(best[1]), best[0]]


@pandas_udf(DoubleType())
def discord_score(value: pd.Series, t: pd.Series) -> float:
    """Aggregate: the distance of a series' discord of length 8."""
    from rankscan.operators.baselines import discord_of

    v = value.to_numpy()[np.argsort(t.to_numpy(), kind="stable")]
    return discord_of(v, 8, False)[2] if len(v) >= 16 else 0.0


@udtf(returnType="series_id string, s int, w int, log10_p double, hits int")
class EventRegions:
    """SELECT * FROM event_regions(TABLE(series) PARTITION BY (series_id) ORDER BY (t), w_max [, restarts [, digits]]): one series is
    held at a time; scores equal to ``digits`` decimals are ties. The plane is searched whole or by restarts as ``choose_search`` has it; given restarts are always used."""

    def __init__(self):
        self.rows: list[tuple[int, float]] = []
        self.series, self.w_max, self.restarts, self.digits = "", 0, None, 9

    def eval(self, row, w_max: int, restarts: int = None, digits: int = 9):
        self.series, self.w_max, self.restarts, self.digits = row["series_id"], w_max, restarts, digits
        self.rows.append((row["t"], row["value"]))

    def terminate(self) -> Iterator[tuple]:
        if not self.rows:
            return
        from rankscan.operators.scan import local_minima
        from rankscan.plans.planner import choose_search

        t, v = (np.array(x) for x in zip(*self.rows))
        w_max = min(self.w_max, len(v))
        f = R.Surface(R.hashed_ranks(v.astype(float), self.series, t), _law(len(v), w_max), 1, w_max)
        if self.restarts is None and choose_search(len(v), w_max) == "exhaustive":
            s, w, p = local_minima(f, self.digits)
        else:
            s0, w0, angles = R.starts(self.series, 0, 30 if self.restarts is None else self.restarts, len(v), 1, w_max, 42)
            s, w, p, _ = R.with_best(f, *R.powell(f, s0, w0, angles), self.digits)
        for members in R.cluster(s, w, p, 0.75, self.digits):
            i = members[0]
            yield self.series, int(s[i]), int(w[i]), float(p[i]), len(members)


@udtf(returnType="n int, w int, phi int, ways string")
class PartitionLaw:
    """SELECT * FROM partition_law(n, w): exact counts as text."""

    def eval(self, n: int, w: int):
        for k, ways in enumerate(N.law_by_product(n, w)):
            yield n, w, k + N.least_sum(w), str(ways)


def register(spark: SparkSession) -> None:
    for name, f in (("rank_array", rank_array), ("log10_binom", log10_binom), ("interval_log10_p", interval_log10_p), ("best_interval", best_interval), ("discord_score", discord_score)):
        spark.udf.register(name, f)
    spark.udtf.register("event_regions", EventRegions)
    spark.udtf.register("partition_law", PartitionLaw)
