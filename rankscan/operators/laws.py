"""The null law as tables: built once per (n, w), stored, and reused by every series of that length."""

from __future__ import annotations

import io
import math
import uuid
from collections.abc import Iterator
from functools import reduce

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import Window

from rankscan import schema
from rankscan.functions import nulllaw as N
from rankscan.sources.tables import shared_dir, shared_path

_FITS = 10**38


def _rows(n: int, w: int, ways: list[int] | None, mass: np.ndarray, method: str, samples: int | None) -> pd.DataFrame:
    with np.errstate(divide="ignore"):
        low, up = np.log10(np.minimum(np.cumsum(mass), 1)), np.log10(np.minimum(np.cumsum(mass[::-1])[::-1], 1))
        logs = np.log10(mass)
    from decimal import Decimal

    exact = [Decimal(int(x)) if x < _FITS else None for x in ways] if ways is not None else None
    return pd.DataFrame({"n": n, "w": w, "phi": np.arange(len(mass)) + N.least_sum(w), "ways": exact, "log10_mass": logs, "log10_lower": low, "log10_upper": up, "method": method, "samples": samples})


def build_null_law(spark: SparkSession, lengths: list[int], w_max: int, method: str = "exact", samples: int = 100_000, seed: int = 42, tasks: int = 16) -> DataFrame:
    """Rows of ``schema.NULL_LAW``; every method but "exact" is one task per (n, w) or per share of the draws.

    exact: growing pool, doubles; product: generating function, integers; memo: recurrence, integers; mc: sampling.
    """
    if method == "mc":
        return law_by_sampling(spark, lengths, w_max, samples, seed, tasks)

    def one_n(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for n in (int(n) for pdf in batches for n in pdf["n"].unique()):
            for w, mass in enumerate(N.law_by_conditioning(n, min(w_max, n))):
                if w:
                    yield _rows(n, w, None, mass, "exact", None)

    def one_w(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        count = N.law_by_product if method == "product" else N.law_by_memo
        for n, w in ((int(a), int(b)) for pdf in batches for a, b in zip(pdf["n"], pdf["w"])):
            ways, all_ways = count(n, w), math.comb(n, w)
            yield _rows(n, w, ways, np.array([x / all_ways for x in ways]), method, None)

    if method == "exact":
        return spark.createDataFrame([(n,) for n in lengths], "n int").repartition(len(lengths), "n").mapInPandas(one_n, schema.NULL_LAW)
    pairs = [(n, w) for n in lengths for w in range(1, min(w_max, n) + 1)]
    return spark.createDataFrame(pairs, "n int, w int").repartition(min(len(pairs), 64), "n", "w").mapInPandas(one_w, schema.NULL_LAW)


def law_by_sampling(spark: SparkSession, lengths: list[int], w_max: int, samples: int, seed: int = 42, tasks: int = 16) -> DataFrame:
    """Shares of the draws are tallied in tasks of their own and summed; shares are seeded by their number."""
    share = -(-samples // tasks)

    def draw(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for k in (int(k) for pdf in batches for k in pdf["id"]):
            mine = min(share, samples - k * share)
            for n in lengths if mine > 0 else []:
                for w, counts in enumerate(N.sampled_counts(n, min(w_max, n), mine, np.random.default_rng([seed, k, n]))):
                    if w and len(at := np.flatnonzero(counts)):
                        yield pd.DataFrame({"n": n, "w": w, "phi": at + N.least_sum(w), "hits": counts[at]})

    tallies = spark.range(0, tasks, 1, tasks).mapInPandas(draw, "n int, w int, phi bigint, hits bigint").groupBy("n", "w", "phi").agg(F.sum("hits").alias("hits"))
    return with_tails(tallies.withColumn("mass", F.col("hits") / samples)).select(
        "n", "w", "phi", F.lit(None).cast("decimal(38,0)").alias("ways"), F.log10("mass").alias("log10_mass"), F.log10("lower").alias("log10_lower"), F.log10("upper").alias("log10_upper"), F.lit("mc").alias("method"), F.lit(samples).cast("bigint").alias("samples")
    )


def with_tails(law: DataFrame) -> DataFrame:
    """Adds lower, upper, tail and two-sided probabilities to (n, w, phi, mass), each summed from its small end."""
    order = Window.partitionBy("n", "w")
    rows = law.withColumn("lower", F.least(F.sum("mass").over(order.orderBy("phi")), F.lit(1.0))).withColumn("upper", F.least(F.sum("mass").over(order.orderBy(F.desc("phi"))), F.lit(1.0)))
    return rows.withColumn("tail", F.least("lower", "upper")).withColumn("two_sided", F.least(F.lit(1.0), 2 * F.col("tail")))


def law_by_steps(spark: SparkSession, n: int, w_max: int, cut_every: int = 10) -> DataFrame:
    """Counts by DataFrame steps alone: each number of 1..n is taken or left (n shuffles of at most the law's size)."""
    from rankscan.sources.tables import cut

    now = spark.createDataFrame([(0, 0, 1)], "w int, phi bigint, ways bigint").select("w", "phi", F.col("ways").cast("decimal(38,0)").alias("ways"))
    for i in range(1, n + 1):
        both = F.array(F.struct("w", "phi", "ways"), F.struct((F.col("w") + 1).alias("w"), (F.col("phi") + i).alias("phi"), "ways"))
        now = now.select(F.explode(both).alias("x")).select("x.*").where(F.col("w") <= w_max).groupBy("w", "phi").agg(F.sum("ways").cast("decimal(38,0)").alias("ways"))
        if i % cut_every == 0:
            now = cut(now)
    return now.where("w > 0").select(F.lit(n).alias("n"), "w", "phi", "ways")


def law_by_hash_sampling(spark: SparkSession, n: int, w_max: int, draws: int, seed: int = 42) -> DataFrame:
    """Draws whose order of 1..n is that of a digest, so any engine can repeat them: (n, w, phi, hits)."""
    grid = spark.range(draws).select(F.col("id").alias("draw"), F.explode(F.sequence(F.lit(1), F.lit(n))).alias("i"))
    order = Window.partitionBy("draw").orderBy(F.md5(F.concat_ws("|", F.lit(str(seed)), F.col("draw").cast("string"), F.col("i").cast("string"))), "i")
    sums = grid.select("draw", F.row_number().over(order).alias("w"), F.sum("i").over(order.rowsBetween(Window.unboundedPreceding, 0)).alias("phi"))
    return sums.where(F.col("w") <= w_max).groupBy(F.lit(n).alias("n"), "w", "phi").agg(F.count("*").alias("hits"))


def law_error(sampled: DataFrame, exact: DataFrame, alpha: float) -> DataFrame:
    """Relative error of sampled masses where the exact mass is at least alpha; sums that were not drawn count as -1.

    Both: (n, w, phi, mass). Unseen sums are censored: the law knows only that they are rarer than one in the samples.
    """
    m = sampled.select("n", "w", "phi", F.col("mass").alias("sampled"))
    both = exact.where(F.col("mass") >= alpha).join(m, ["n", "w", "phi"], "left")
    return both.select("n", "w", "phi", "mass", F.col("sampled").isNull().alias("censored"), (F.coalesce("sampled", F.lit(0.0)) / F.col("mass") - 1).alias("error"))


def decision_flips(law_a: DataFrame, law_b: DataFrame, alpha: float) -> DataFrame:
    """Sums that one law (n, w, phi, tail) calls significant and the other does not."""
    a, b = (x.select("n", "w", "phi", (F.col("tail") <= alpha).alias(c)) for x, c in ((law_a, "in_a"), (law_b, "in_b")))
    return a.join(b, ["n", "w", "phi"], "full").where(F.coalesce("in_a", F.lit(True)) != F.coalesce("in_b", F.lit(True)))


#: Tables held by this worker (or driver), the latest last, and the most bytes of them that it keeps besides the one in use.
_HELD: dict[str, N.LawTables] = {}
HELD_BYTES = 128 << 20


class LawFiles:
    """Score tables in the shared folder, a file per segment length, read by the workers that meet that length.

    A table is made once and for all series, sessions and queries that share the folder: by ``prepare`` in tasks of its
    own for lengths known beforehand, else by the first worker that needs it. Nothing is built on, or passes, the driver.
    """

    def __init__(self, spark: SparkSession, w_max: int, mode: str = "tail", law: str = "exact", samples: int = 100_000, seed: int = 42):
        self.how = {"w_max": w_max, "mode": mode, "law": law, "samples": samples, "seed": seed}
        drawn = f"-{samples}-{seed}" if law != "exact" else ""
        self.base = f"{shared_dir(spark)}/law-tables/{law}{drawn}-{mode}-{w_max}"

    def uri(self, n: int) -> str:
        return f"{self.base}-{n}.npy"

    def _read(self, n: int) -> N.LawTables | None:
        import pyarrow.fs

        fs, path = pyarrow.fs.FileSystem.from_uri(self.uri(n))
        try:
            with fs.open_input_file(path) as file:
                flat = np.load(io.BytesIO(file.read()))
        except FileNotFoundError:
            return None
        exact = self.how["law"] == "exact"
        return N.LawTables(n, self.how["w_max"], flat, exact and self.how["mode"] in N.SYMMETRIC, None if exact else self.how["samples"])

    def _write(self, n: int) -> N.LawTables:
        import pyarrow.fs

        made = N.LawTables.build(n, **self.how)
        fs, path = pyarrow.fs.FileSystem.from_uri(self.uri(n))
        fs.create_dir(path.rpartition("/")[0], recursive=True)
        part, data = f"{path}.{uuid.uuid4().hex}", io.BytesIO()
        np.save(data, made.flat)
        with fs.open_output_stream(part) as file:
            file.write(data.getvalue())
        fs.move(part, path)  # whoever is last leaves the same bytes
        return made

    def get(self, n: int) -> N.LawTables:
        n, uri = int(n), self.uri(int(n))
        if uri in _HELD:
            _HELD[uri] = _HELD.pop(uri)
        else:
            _HELD[uri] = self._read(n) or self._write(n)
            while len(_HELD) > 1 and sum(x.flat.nbytes for x in _HELD.values()) > HELD_BYTES:
                del _HELD[next(iter(_HELD))]
        return _HELD[uri]

    def prepare(self, spark: SparkSession, lengths: list[int]) -> LawFiles:
        """Makes the tables that are not there yet, a task each."""
        files = self

        def make(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
            for pdf in batches:
                yield pdf.assign(made=[files._read(n) is None and files._write(n) is not None for n in pdf["n"].tolist()])

        if lengths:
            asked = spark.createDataFrame([(int(n),) for n in sorted(set(lengths))], "n int").repartition(len(set(lengths)), "n")
            asked.mapInPandas(make, "n int, made boolean").collect()
        return self


class LawStore:
    """Laws on disk, partitioned by n and method; a law is computed only if the store has none for its n and width."""

    def __init__(self, spark: SparkSession, path: str | None = None):
        self.spark, self.path = spark, path or shared_path(spark, "laws")

    def put(self, law: DataFrame) -> None:
        law.write.mode("append").partitionBy("n", "method").parquet(self.path)

    def _stored(self) -> DataFrame | None:
        from pyspark.errors import AnalysisException

        try:
            return self.spark.read.schema(schema.NULL_LAW).parquet(self.path)
        except AnalysisException:
            return None

    def get(self, lengths: list[int], w_max: int, method: str = "exact", **how) -> DataFrame:
        held = self._stored()
        have = {} if held is None else {r[0]: r[1] for r in held.where((F.col("method") == method) & F.col("n").isin(lengths)).groupBy("n").agg(F.max("w")).collect()}
        for n in lengths:
            if have.get(n, 0) < min(w_max, n):
                fresh = build_null_law(self.spark, [n], w_max, method, **how)
                self.put(fresh.where(F.col("w") > have.get(n, 0)))
        columns = [c.split()[0] for c in schema.NULL_LAW.split(", ")]
        return self._stored().where((F.col("method") == method) & F.col("n").isin(lengths) & (F.col("w") <= w_max)).select(*columns)


def union(frames: list[DataFrame]) -> DataFrame:
    return reduce(DataFrame.unionByName, frames)
