"""Mixing sources to target weights: temperature mixing and budgeted block permutations, DataFrame functions only.

A source's weight is its token share to a power, normalised. The exponent is found by bisection on a dyadic grid: the
largest in [0, 1] whose weights reach the wanted entropy, raised where a source would otherwise be repeated more often
than allowed. Each pass evaluates a whole fan of exponents in one aggregate over the sources, so it takes several levels
of the bisection at once and collects one number.

A source's share of the token budget is met by whole passes over its documents and a last, partial one. Every pass
has its own permutation (order of a seeded digest); positions in it come from two levels of prefix sums, within ranges of
digests and over ranges, so a source of any size is spread over many tasks. The stream of each source is cut in
proportion to its weight, so that every block of the output has the target weights.

Defined cases: null and empty texts have no tokens and follow their source; a null source counts as ""; sources without
tokens get no weight and are left out; repeated rows are documents of their own; an empty table has no mix. A document
may appear several times or, if its source is sampled down, not at all. Columns other than id, text and source are not
read.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window

from .common import cut, maybe_broadcast

#: The grid of exponents has 2 ** GRID_BITS steps; each pass settles FAN_BITS of them.
GRID_BITS, FAN_BITS = 20, 5


def token_count(text: Column) -> Column:
    """Words between ASCII white space."""
    return F.coalesce(F.size(F.array_remove(F.split(text, r"[\x20\x09-\x0D]+"), "")), F.lit(0)).cast("long")


def _slim(docs: DataFrame, id_col: str, text_col: str, source_col: str) -> DataFrame:
    return docs.select(F.col(id_col).alias("doc_id"), F.xxhash64(text_col).alias("text_key"), F.coalesce(F.col(source_col).cast("string"), F.lit("")).alias("source"), F.greatest(token_count(F.col(text_col)), F.lit(0)).alias("n_tokens"))


def _first_failing(shares: DataFrame, holds: Column) -> int:
    """The greatest grid point up to which ``holds`` (an aggregate of s, a, ln s) is true, by bisection in fans; -1 if not even at 0."""
    lo, hi = -1, (1 << GRID_BITS) + 1
    while hi - lo > 1:
        step = max(1, (hi - lo) >> FAN_BITS)
        points = list(range(lo + step, hi, step))
        fan = shares.withColumn("g", F.explode(F.array(*map(F.lit, points)))).withColumn("a", F.col("g") / (1 << GRID_BITS))
        good = fan.groupBy("g").agg(holds.alias("ok")).where("ok").agg(F.max("g")).first()[0]
        lo, hi = (lo, points[0]) if good is None else (good, min(hi, good + step))
    return lo


def mixing_weights(slim: DataFrame, entropy_share: float, max_repeat: float, budget: int | None) -> DataFrame:
    """Per source: source, tokens, weight, exponent, quota (tokens of the budget), passes (whole ones), rest."""
    totals = cut(slim.groupBy("source").agg(F.sum("n_tokens").alias("tokens")).where("tokens > 0"))
    n, total = totals.agg(F.count("*"), F.coalesce(F.sum("tokens"), F.lit(0))).first()
    budget = total if budget is None else budget
    shares = totals.withColumn("s", F.col("tokens") / max(total, 1))
    exponent = 1 << GRID_BITS
    if n > 1:
        mass, slope = F.sum(F.pow("s", "a")), F.sum(F.pow("s", "a") * F.ln("s"))
        entropy = F.ln(mass) - F.max("a") * slope / mass
        by_entropy = max(0, _first_failing(shares, entropy >= entropy_share * math.log(n) - 1e-12))
        worst = F.max(F.pow("s", F.col("a") - 1)) / mass * (budget / max(total, 1))
        by_repeat = min(1 << GRID_BITS, _first_failing(shares, worst > max_repeat) + 1)
        exponent = max(by_entropy, by_repeat)
    alpha = exponent / (1 << GRID_BITS)
    raised = shares.withColumn("raised", F.pow("s", F.lit(alpha)))
    mass = raised.agg(F.sum("raised")).first()[0] or 1.0
    weighted = raised.withColumn("weight", F.round(F.col("raised") / mass, 12)).withColumn("quota", F.floor(F.col("weight") * budget).cast("long"))
    passes = F.floor(F.col("quota") / F.col("tokens")).cast("int")
    return weighted.select("source", "tokens", "weight", F.lit(alpha).alias("exponent"), "quota", passes.alias("passes"), (F.col("quota") - passes * F.col("tokens")).alias("rest"))


def mix(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", source_col: str = "source", entropy_share: float = 0.9, max_repeat: float = 4.0, budget: int | None = None, block_tokens: int = 1 << 20, seed: int = 42, ranges: int = 4096) -> DataFrame:
    """Per copy of a document in the mix: id, text_key, source, epoch, block, n_tokens.

    ``budget`` is the mix's tokens (None: as many as there are); ``entropy_share`` the wanted entropy as a share of the
    greatest possible one; a source is passed over at most ``max_repeat`` times if the budget allows it at all.
    """
    slim = cut(_slim(docs, id_col, text_col, source_col))
    weights = mixing_weights(slim, entropy_share, max_repeat, budget)
    weights = cut(weights)
    # a row per source: sent to all tasks, so that rows of a hot source stay where they are
    copies = slim.join(maybe_broadcast(weights, weights.count()), "source").withColumn("epoch", F.explode(F.sequence(F.lit(0), F.col("passes"))))
    key = F.md5(F.concat_ws("|", F.lit(str(seed)), F.col("epoch").cast("string"), F.coalesce(F.col("doc_id").cast("string"), F.lit("null"))))
    copies = copies.withColumn("order_key", key).withColumn("range", F.pmod(F.conv(F.substring("order_key", 1, 8), 16, 10).cast("long"), F.lit(1 << 32)) * ranges / (1 << 32))
    copies = copies.withColumn("range", F.floor("range").cast("int"))
    sums = copies.groupBy("source", "epoch", "range").agg(F.sum("n_tokens").alias("held"))
    before = Window.partitionBy("source", "epoch").orderBy("range").rowsBetween(Window.unboundedPreceding, -1)
    sums = sums.withColumn("base", F.coalesce(F.sum("held").over(before), F.lit(0))).drop("held")
    placed = copies.join(sums, ["source", "epoch", "range"])
    order = Window.partitionBy("source", "epoch", "range").orderBy("order_key", "doc_id", "text_key").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    placed = placed.withColumn("end", F.col("base") + F.sum("n_tokens").over(order))
    kept = placed.where((F.col("epoch") < F.col("passes")) | (F.col("end") <= F.col("rest")))
    start = F.col("epoch") * F.col("tokens") + F.col("end") - F.col("n_tokens")
    block = F.floor(start / (F.col("weight") * block_tokens)).cast("long")
    return kept.select(F.col("doc_id").alias(id_col), "text_key", "source", "epoch", block.alias("block"), "n_tokens")


def mixed_documents(docs: DataFrame, mixed: DataFrame, id_col: str = "doc_id", text_col: str = "text", source_col: str = "source", broadcast_rows: int = 1_000_000) -> DataFrame:
    """The documents as often as the mix has them, with their own columns. Rows equal in id, text and source are told
    apart by nothing that the mix reads: one of them brings the copies of them all."""
    own = {"_i": F.col(id_col), "_k": F.xxhash64(text_col), "_s": F.coalesce(F.col(source_col).cast("string"), F.lit(""))}
    times = mixed.groupBy(F.col(id_col).alias("_id"), F.col("text_key").alias("_key"), F.col("source").alias("_source")).agg(F.count("*").cast("int").alias("_copies"))
    times = cut(times)
    docs, columns = docs.withColumns(own), docs.columns
    same = cut(docs.groupBy(*own).agg(F.count("*").alias("_rows")).where("_rows > 1").select(*[F.col(c).alias(f"{c}2") for c in own]))
    if not same.isEmpty():
        equal = F.col("_i").eqNullSafe(F.col("_i2")) & (F.col("_k") == F.col("_k2")) & (F.col("_s") == F.col("_s2"))
        docs = docs.join(same, equal, "left_anti").unionAll(docs.join(same, equal, "left_semi").dropDuplicates(["_i", "_k", "_s"]))
    side = maybe_broadcast(times, times.count(), broadcast_rows)
    joined = docs.join(side, F.col("_i").eqNullSafe(F.col("_id")) & (F.col("_k") == F.col("_key")) & (F.col("_s") == F.col("_source")))
    return joined.withColumn("_copy", F.explode(F.sequence(F.lit(1), F.col("_copies")))).select(*columns)
