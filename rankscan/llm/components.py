"""Connected components of an edge table by alternating star contractions (shuffles only; nothing is collected)."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import cut


def _round(edges: DataFrame) -> DataFrame:
    """Every vertex's greater neighbours, then its lesser ones, move to its least neighbour."""
    both = edges.unionAll(edges.select(F.col("b").alias("a"), F.col("a").alias("b")))
    least = both.groupBy("a").agg(F.least(F.min("b"), F.col("a")).alias("m"))
    large = both.join(least.hint("merge"), "a").where(F.col("b") > F.col("a")).select(F.col("b").alias("a"), F.col("m").alias("b"))
    large = large.where("a <> b").distinct()
    down = large.select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b"))
    least = down.groupBy("a").agg(F.min("b").alias("m"))
    small = down.join(least.hint("merge"), "a").select("a", "b", "m")
    out = small.select(F.col("b").alias("a"), F.col("m").alias("b")).unionAll(small.select("a", F.col("m").alias("b")))
    return out.where("a <> b").distinct()


def components(edges: DataFrame, a: str = "a", b: str = "b") -> DataFrame:
    """(vertex, label): label is the least vertex of its component; vertices without an edge are absent.

    Loops and repeated or null-ended edges add nothing.
    """
    now = edges.select(F.greatest(a, b).alias("a"), F.least(a, b).alias("b")).where(F.col(a).isNotNull() & F.col(b).isNotNull() & (F.col(a) != F.col(b)))
    now, last = cut(now.distinct()), None
    while True:
        mark = now.agg(F.count("*"), F.coalesce(F.sum(F.pmod(F.xxhash64("a", "b"), F.lit(1 << 40))), F.lit(0))).first()
        if mark[0] == 0 or mark == last:
            break
        last, now = mark, cut(_round(now))
    return now.select(F.col("a").alias("vertex"), F.col("b").alias("label")).unionAll(now.select("b", "b").distinct())
