"""Ranking of regions over a whole collection, thresholds, and joins of intervals."""

from __future__ import annotations

from collections.abc import Iterator

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window


def overlaps(s1: Column, w1: Column, s2: Column, w2: Column, theta: float) -> Column:
    """Whether the signed intersection is at least theta of the longer interval."""
    return F.least(s1 + w1, s2 + w2) - F.greatest(s1, s2) >= theta * F.greatest(w1, w2)


def overlaps_by_terms(s1: Column, w1: Column, s2: Column, w2: Column, theta: float) -> Column:
    total = F.greatest(s1 + w1, s2 + w2) - F.least(s1, s2)
    both = total - (F.abs(s1 - s2) + F.abs(s1 + w1 - s2 - w2))
    return (both >= theta * w1) & (both >= theta * w2)


def _score(column: str, digits: int = 9) -> Column:
    """Windows of other widths may have one and the same tail, of which floats differ in the last digits: those are ties."""
    return F.round(column, digits) if column == "log10_p" else F.col(column)


def best_per_series(regions: DataFrame, by: str = "log10_p", least: bool = True, digits: int = 9) -> DataFrame:
    """Each series' best row: one partially aggregated shuffle. Ties go to the earliest, then the shortest."""
    key = F.struct(_score(by, digits) if least else -F.col(by), *[c for c in ("s", "w", "seg_id", "pos") if c in regions.columns])
    best = regions.groupBy("series_id").agg(F.min_by(F.struct(*regions.columns), key).alias("b"))
    return best.select("b.*")


def rank_rows(rows: DataFrame, *order: Column, name: str = "global_rank", partitions: int | None = None) -> DataFrame:
    """A global rank without a one-task window: rows are dealt by ranges of the order, each range is numbered by itself,
    and a table of one row per range gives the numbers before it."""
    n = partitions or int(rows.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    from rankscan.sources.tables import cut

    dealt = cut(rows.repartitionByRange(n, *order).withColumn("_part", F.spark_partition_id()))
    sizes = dealt.groupBy("_part").agg(F.count("*").alias("_size"))
    before = sizes.alias("a").join(sizes.alias("b"), F.col("b._part") < F.col("a._part"), "left").groupBy("a._part").agg(F.coalesce(F.sum("b._size"), F.lit(0)).alias("_before"))
    local = dealt.withColumn("_row", F.row_number().over(Window.partitionBy("_part").orderBy(*order)))
    return local.join(F.broadcast(before), "_part").withColumn(name, F.col("_row") + F.col("_before")).drop("_part", "_row", "_before")


def rank_events(regions: DataFrame, per_series: str = "all", order: tuple[str, ...] = ("log10_p",), digits: int = 9) -> DataFrame:
    """``per_series``: all regions, or the best of each series. Order "hits" counts the most frequent first. Scores equal to
    ``digits`` decimals are ties."""
    rows = best_per_series(regions, digits=digits) if per_series == "best" else regions
    keys = [F.desc(c) if c in ("hits", "hit_share") else _score(c, digits).asc() for c in order]
    return rank_rows(rows, *keys, F.asc("series_id"), F.asc("s"), F.asc("w"))


def filter_significant(regions: DataFrame, alpha: float = 1e-8) -> DataFrame:
    import math

    return regions.where(F.col("log10_p") <= math.log10(alpha))


def top_percent(ranked: DataFrame, percent: float) -> DataFrame:
    total = ranked.agg((F.count("*") * percent / 100).alias("_most"))
    return ranked.crossJoin(F.broadcast(total)).where(F.col("global_rank") <= F.col("_most")).drop("_most")  # one row


def interval_join(left: DataFrame, right: DataFrame, key: str, bin_width: int, l0: str, l1: str, r0: str, r1: str) -> DataFrame:
    """Pairs of one key whose closed intervals [l0, l1], [r0, r1] meet. Intervals are cut at bin edges, bins are joined by
    equality, and a pair is kept in the bin where its intersection begins, so no pair comes twice."""
    a = left.withColumn("_bin", F.explode(F.sequence(F.floor(F.col(l0) / bin_width), F.floor(F.col(l1) / bin_width))))
    b = right.withColumn("_bin", F.explode(F.sequence(F.floor(F.col(r0) / bin_width), F.floor(F.col(r1) / bin_width))))
    both = a.join(b, [key, "_bin"]).where((F.col(l0) <= F.col(r1)) & (F.col(r0) <= F.col(l1)))
    return both.where(F.floor(F.greatest(l0, r0) / bin_width) == F.col("_bin")).drop("_bin")


def asof_join(left: DataFrame, right: DataFrame, key: str, left_t: str, right_t: str, value: str) -> DataFrame:
    """The latest value of ``right`` at or before each left row, by one union and one ordered window per key."""
    l_rows = left.select(F.col(key), F.col(left_t).alias("_t"), F.lit(1).alias("_side"), F.struct(*left.columns).alias("_row"), F.lit(None).cast(right.schema[value].dataType).alias("_v"))
    r_rows = right.select(F.col(key), F.col(right_t).alias("_t"), F.lit(0).alias("_side"), F.lit(None).cast(l_rows.schema["_row"].dataType).alias("_row"), F.col(value).alias("_v"))
    order = Window.partitionBy(key).orderBy("_t", "_side").rowsBetween(Window.unboundedPreceding, 0)
    return l_rows.unionAll(r_rows).withColumn(value, F.last("_v", ignorenulls=True).over(order)).where("_side = 1").select("_row.*", value)


def merge_segments(regions: DataFrame, theta: float = 0.75, digits: int = 9) -> DataFrame:
    """Clusters, on whole-series starts, the regions that reach into another segment of their series, so that an event in
    two overlapping segments counts once; all others, and series of one segment, pass as they are.

    A region can only meet one of another segment where the segments overlap. Such regions fall into islands (runs of
    regions that touch), and an island, whose size segments' overlap bounds, is one task's group: a long series' regions
    are never held together.
    """
    columns = [f.name for f in regions.schema]
    along = Window.partitionBy("series_id").orderBy("seg_start")
    segments = regions.groupBy("series_id", "seg_start").agg(F.max("n").alias("_n"))
    segments = segments.select("series_id", "seg_start", F.lead("seg_start").over(along).alias("_next"), F.max(F.col("seg_start") + F.col("_n") - 1).over(along.rowsBetween(Window.unboundedPreceding, -1)).alias("_before"))
    seamed = segments.where("_next is not null or _before is not null")
    seamed = seamed.withColumnsRenamed({"series_id": "_series", "seg_start": "_start"})
    shared = F.coalesce(F.col("s") + F.col("w") - 1 >= F.col("_next"), F.lit(False)) | F.coalesce(F.col("s") <= F.col("_before"), F.lit(False))
    placed = regions.join(seamed, (F.col("series_id") == F.col("_series")) & (F.col("seg_start") == F.col("_start")), "left").withColumn("_shared", shared)
    by_start = Window.partitionBy("series_id").orderBy("s", "w")
    reach = F.max(F.col("s") + F.col("w") - 1).over(by_start.rowsBetween(Window.unboundedPreceding, -1))
    opens = F.coalesce((F.col("s") > reach).cast("int"), F.lit(1))
    islands = placed.where("_shared").select(*columns, opens.alias("_opens")).withColumn("_island", F.sum("_opens").over(by_start.rowsBetween(Window.unboundedPreceding, 0))).drop("_opens")

    dealt = islands.repartition("series_id", "_island").sortWithinPartitions("series_id", "_island", "log10_p", "s", "w", "seg_id", "region_id")
    return placed.where("not _shared").select(*columns).unionAll(dealt.mapInArrow(_merge_islands(theta, digits), regions.schema))


def _merge_islands(theta: float, digits: int = 9):
    """Rows sorted by series and island to rows of their clusters; only an island that goes on in the next batch is held."""
    import numpy as np
    import pyarrow as pa

    from rankscan.functions.regions import cluster

    def merged(rows: pa.Table, edges: list[int]) -> pa.RecordBatch:
        s, w, p, hits, share = (rows[c].to_numpy() for c in ("s", "w", "log10_p", "hits", "hit_share"))
        groups = []
        for a, b in zip(edges, [*edges[1:], len(rows)]):
            groups += [[a]] if b - a == 1 else [[a + i for i in g] for g in cluster(s[a:b], w[a:b], p[a:b], theta, digits)]
        lead, sizes = [g[0] for g in groups], [len(g) for g in groups]
        flat = np.concatenate(groups)
        first = np.cumsum(sizes) - sizes
        members = rows["members"].combine_chunks().take(pa.array(flat))
        ends = np.cumsum(members.value_lengths().to_numpy())[first + sizes - 1]
        out = rows.drop_columns("_island").take(pa.array(lead)).combine_chunks().to_batches()[0]
        new = {"hits": pa.array(np.add.reduceat(hits[flat], first), pa.int32()), "hit_share": pa.array(np.maximum.reduceat(share[flat], first))}
        new["members"] = pa.ListArray.from_arrays(pa.array(np.append(0, ends), pa.int32()), members.flatten())
        return pa.RecordBatch.from_arrays([new[c].cast(out.schema.field(c).type) if c in new else out[c] for c in out.schema.names], schema=out.schema)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held = None
        for batch in batches:
            if not batch.num_rows:
                continue
            rows = pa.Table.from_batches([batch])
            rows = rows if held is None else pa.concat_tables([held, rows])
            series, island = rows["series_id"].to_numpy(), rows["_island"].to_numpy()
            edges = np.flatnonzero(np.append(True, (series[1:] != series[:-1]) | (island[1:] != island[:-1]))).tolist()
            held = rows.slice(edges[-1])
            if len(edges) > 1:
                yield merged(rows.slice(0, edges[-1]), edges[:-1])
        if held is not None:
            yield merged(held, [0])

    return run
