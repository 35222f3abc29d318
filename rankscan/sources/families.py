"""Series made of the given tables."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import Window

from rankscan.operators import prepare as P
from rankscan.sources.tables import read_table, unpack

DAY_US, HOUR_US = 86_400_000_000, 3_600_000_000


def _day(column: str, origin: str) -> Column:
    return F.datediff(F.col(column), F.lit(origin)) + 1


def orders_daily(spark: SparkSession, d: str) -> DataFrame:
    """Orders a day by priority, 1995-01-01 being day 1, days without orders 0."""
    rows = read_table(spark, d, "orders", "o_orderpriority", "o_orderdate")
    counts = rows.groupBy(F.col("o_orderpriority").alias("series_id"), _day("o_orderdate", "1995-01-01").cast("bigint").alias("t")).agg(F.count("*").cast("double").alias("value"))
    return P.fill_gaps(counts, lo=1, hi=2405)


def ship_daily(spark: SparkSession, d: str) -> DataFrame:
    """Lines shipped a day by return flag and line status, 1995-01-02 being day 1."""
    rows = read_table(spark, d, "lineitem", "l_returnflag", "l_linestatus", "l_shipdate")
    counts = rows.groupBy(F.concat("l_returnflag", "l_linestatus").alias("series_id"), _day("l_shipdate", "1995-01-02").cast("bigint").alias("t")).agg(F.count("*").cast("double").alias("value"))
    return P.fill_gaps(counts, lo=1, hi=2499)


def events_hourly(spark: SparkSession, d: str) -> DataFrame:
    """Events an hour by type over January 2024's first 30 days."""
    points = read_table(spark, d, "events", "event_type", "ts")
    origin = 1_704_067_200_000_000
    return P.fill_gaps(P.bin_points(points, "event_type", "ts", width_us=HOUR_US, origin_us=origin), lo=1, hi=720)


def event_points(spark: SparkSession, d: str, n_bins: int = 720) -> DataFrame:
    """Events by type as a point process over its whole span, in equal bins."""
    points = read_table(spark, d, "events", "event_type", "ts")
    return P.fill_gaps(P.bin_points(points, "event_type", "ts", n_bins=n_bins), lo=1, hi=n_bins)


def event_blocks(spark: SparkSession, d: str, n: int) -> DataFrame:
    """Event values by blocks of n consecutive event ids, in order of id: (series_id, k, t, value)."""
    rows = read_table(spark, d, "events", "event_id", "value").where("event_id is not null and value is not null and not isnan(value)")
    rows = rows.withColumn("k", F.expr(f"event_id div {n}"))
    t = F.row_number().over(Window.partitionBy("k").orderBy("event_id", "value")).cast("bigint")
    return rows.select(F.concat(F.lit("e"), F.col("k").cast("string")).alias("series_id"), "k", t.alias("t"), "value")


def user_values(spark: SparkSession, d: str) -> DataFrame:
    """Values of each user's events in order of time: series of unequal length."""
    return P.index_by_order(read_table(spark, d, "events", "user_id", "ts", "event_id", "value"), "user_id", "value", "ts", "event_id")


def supplier_weekly(spark: SparkSession, d: str) -> DataFrame:
    """Revenue a week by supplier, in whole cents, weeks without lines 0; the survey's stand-in."""
    rows = read_table(spark, d, "lineitem", "l_suppkey", "l_shipdate", "l_extendedprice", "l_discount")
    week = F.expr("datediff(l_shipdate, date '1995-01-02') div 7 + 1")
    cents = F.floor(F.col("l_extendedprice") * (1 - F.col("l_discount")) * 100 + 0.5).cast("bigint")
    sums = rows.groupBy(F.col("l_suppkey").cast("string").alias("series_id"), week.cast("bigint").alias("t")).agg(F.sum(cents).cast("double").alias("value"))
    return P.fill_gaps(sums, lo=1, hi=357)


def supplier_tiles(spark: SparkSession, d: str) -> DataFrame:
    """Each supplier's nation and region; a dimension of at most as many rows as there are suppliers."""
    s, n, r = read_table(spark, d, "supplier", "s_suppkey", "s_nationkey"), read_table(spark, d, "nation"), read_table(spark, d, "region")
    near = s.join(F.broadcast(n), s["s_nationkey"] == n["n_nationkey"]).join(F.broadcast(r), n["n_regionkey"] == r["r_regionkey"])
    return near.select(F.col("s_suppkey").cast("string").alias("series_id"), F.col("n_name").alias("nation"), F.col("r_name").alias("region"))


def vector_series(spark: SparkSession, d: str) -> DataFrame:
    return unpack(read_table(spark, d, "embeddings", "vec_id", "embedding"), "vec_id", "embedding")


def part_price(spark: SparkSession, d: str) -> DataFrame:
    """Prices by part key: a saw-tooth. The index is arithmetic, no global sort."""
    rows = read_table(spark, d, "part", "p_partkey", "p_retailprice")
    least = rows.agg(F.min("p_partkey").alias("lo"))
    return rows.crossJoin(F.broadcast(least)).select(F.lit("part").alias("series_id"), (F.col("p_partkey") - F.col("lo") + 1).cast("bigint").alias("t"), F.col("p_retailprice").alias("value"))


def turn_lengths(spark: SparkSession, d: str) -> DataFrame:
    rows = read_table(spark, d, "conversations", "conv_id", "turn", "text").withColumn("size", F.length("text"))
    return P.index_by_order(rows, "conv_id", "size", "turn")


def doc_lengths(spark: SparkSession, d: str) -> DataFrame:
    return P.index_by_order(read_table(spark, d, "documents", "lang", "doc_id", "n_chars"), "lang", "n_chars", "doc_id")


def label_bits(spark: SparkSession, d: str) -> DataFrame:
    """A series of two values: the extreme of ties."""
    rows = read_table(spark, d, "labels", "doc_id", "quality").withColumn("key", F.lit("quality"))
    return P.index_by_order(rows, "key", "quality", "doc_id")


def page_lengths(spark: SparkSession, d: str) -> DataFrame:
    rows = read_table(spark, d, "pages", "page_id", "html").withColumns({"key": F.lit("pages"), "size": F.length("html")})
    return P.index_by_order(rows, "key", "size", "page_id")
