"""Benchmark decontamination: a prefix-filtered set join between documents and item-sized windows, DataFrame functions only.

A window (13 consecutive item words, or a shorter item whole) occurs in a document only if its rarest shingle does, so
that one shingle is the window's necessary prefix. Shingle counts over the whole corpus give the rarity order; windows
with a shingle that the corpus lacks are dropped as they cannot occur. A document's shingle that equals a prefix fixes
the only place where the window can start (positional bound); it must fit in the document (length bound), and there its
words are compared one by one, so hash collisions do no harm.

Defined cases: null or wordless texts have no words, no hits and are not contaminated; wordless items have no window;
items of the same id count once; an item without id is named "null"; repeated document rows are judged row by row; no
items or no documents give no hits or no rows. Columns other than id and text are not read.
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window

from .common import ascii_lower, cut

BREAKS = r"[\x00-\x2F\x3A-\x60\x7B-\x7F]+"
#: Rows of the prefix table that one pass broadcasts; more rows make more passes.
PASS_ROWS = 250_000
SHINGLE = 3


def words_of(text: Column) -> Column:
    return F.coalesce(F.array_remove(F.split(ascii_lower(text), BREAKS), ""), F.array().cast("array<string>"))


def _shingle(words: Column, pos: Column, k: int) -> Column:
    return F.xxhash64(F.lit(k), *[F.get(words, pos + j) for j in range(k)])


def windows_of(items: DataFrame, item_col: str, text_col: str, width: int) -> DataFrame:
    """Distinct windows with their length, shingle length and the ids of their items."""
    words = items.select(F.coalesce(F.col(item_col).cast("string"), F.lit("null")).alias("item"), words_of(F.col(text_col)).alias("words")).where(F.size("words") > 0)
    starts = words.withColumn("start", F.explode(F.expr(f"sequence(1, greatest(size(words) - {width} + 1, 1))")))
    each = starts.select("item", F.slice("words", F.col("start"), width).alias("window")).groupBy("window").agg(F.array_sort(F.collect_set("item")).alias("items"))
    return each.select(F.xxhash64("window").alias("window_key"), "window", "items", F.size("window").alias("len"), F.least(F.lit(SHINGLE), F.size("window")).alias("k"))


def _shingles(windows: DataFrame) -> DataFrame:
    at = windows.select("window_key", "window", "items", "len", "k", F.explode(F.expr("sequence(0, len - k)")).alias("offset"))
    hashed = reduce(lambda rest, k: F.when(F.col("k") == k, _shingle(F.col("window"), F.col("offset"), k)).otherwise(rest), range(1, SHINGLE + 1), F.lit(None).cast("long"))
    return at.withColumn("shingle", hashed)


def _positions(docs: DataFrame, ks: list[int], first: int) -> DataFrame:
    """A row for each document position (from ``first``) and shingle length; position -1 stands for the document itself."""
    at = docs.withColumn("pos", F.explode(F.expr(f"sequence({first}, greatest(size(words) - 1, {first}))")))
    if len(ks) == 1:
        return at.withColumn("shingle", F.when(F.col("pos") >= 0, _shingle(F.col("words"), F.col("pos"), ks[0])))
    hashes = F.array(*[F.when(F.col("pos") >= 0, _shingle(F.col("words"), F.col("pos"), k)) for k in ks])
    return at.withColumn("shingle", F.explode(F.when(F.col("pos") >= 0, hashes).otherwise(F.array(F.lit(None).cast("long")))))


def _passes(df: DataFrame, key: str, rows: int) -> list[DataFrame]:
    n = max(1, -(-rows // PASS_ROWS))
    return [df if n == 1 else df.where(F.pmod(F.hash(key), F.lit(n)) == i) for i in range(n)]


def prefixes(docs: DataFrame, windows: DataFrame, text_col: str, ks: list[int]) -> DataFrame:
    """Each window that may occur with its rarest shingle and that shingle's offset in it."""
    shingles = cut(_shingles(windows))
    wanted = shingles.select("shingle").distinct()
    seen = _positions(docs.select(words_of(F.col(text_col)).alias("words")), ks, 0).select("shingle")
    counted = [seen.join(F.broadcast(part), "shingle", "left_semi") for part in _passes(wanted, "shingle", wanted.count())]
    counts = cut(reduce(DataFrame.unionAll, counted).groupBy("shingle").agg(F.count("*").alias("n")))
    ranked = shingles.join(counts, "shingle", "left").groupBy("window_key", "window", "items", "len")
    least = ranked.agg(F.min(F.struct(F.coalesce("n", F.lit(0)).alias("n"), "offset", "shingle")).alias("rarest"))
    return least.where("rarest.n > 0").select(F.col("rarest.shingle").alias("prefix"), F.col("rarest.offset").alias("offset"), "len", "window", "items")


def contamination(docs: DataFrame, items: DataFrame, id_col: str = "doc_id", text_col: str = "text", item_col: str = "item_id", item_text: str = "text", width: int = 13, share: int = 20) -> DataFrame:
    """Per document row: id, n_words, n_hit, n_items, items_sha256, contaminated, items (sorted ids), text_key.

    contaminated: some word is hit and ``share`` * n_hit >= n_words.
    """
    windows = cut(windows_of(items, item_col, item_text, width))
    ks = sorted(r[0] for r in windows.select("k").distinct().collect()) or [SHINGLE]
    found = cut(prefixes(docs, windows, text_col, ks))
    base = docs.select(F.monotonically_increasing_id().alias("row"), F.col(id_col).alias("doc_id"), F.xxhash64(text_col).alias("text_key"), words_of(F.col(text_col)).alias("words"))
    parts = []
    for i, part in enumerate(_passes(found, "prefix", found.count())):
        rows = _positions(base, ks, -1 if i == 0 else 0)
        start = F.col("pos") - F.col("offset")
        fits = (start >= 0) & (start + F.col("len") <= F.size("words")) & (F.slice("words", start + 1, F.col("len")) == F.col("window"))
        hits = rows.join(F.broadcast(part), rows["shingle"] == part["prefix"], "left").where((F.col("pos") == -1) | (F.col("prefix").isNotNull() & fits))
        parts.append(hits.select("row", "doc_id", "text_key", F.size("words").cast("long").alias("n_words"), start.alias("a"), (start + F.col("len")).alias("b"), "items"))
    order = Window.partitionBy("row").orderBy(F.col("a").asc_nulls_first(), "b").rowsBetween(Window.unboundedPreceding, -1)
    swept = reduce(DataFrame.unionAll, parts).withColumn("until", F.max("b").over(order))
    new = F.greatest(F.col("b") - F.greatest("a", F.coalesce("until", F.lit(0))), F.lit(0))
    out = swept.groupBy("row").agg(
        F.first("doc_id").alias(id_col), F.max("n_words").alias("n_words"), F.coalesce(F.sum(new), F.lit(0)).cast("long").alias("n_hit"),
        F.array_sort(F.array_distinct(F.flatten(F.collect_set("items")))).alias("items"), F.first("text_key").alias("text_key"),
    )
    return out.select(
        id_col, "n_words", "n_hit", F.size("items").cast("long").alias("n_items"), F.sha2(F.array_join("items", ","), 256).alias("items_sha256"),
        ((F.col("n_hit") > 0) & (share * F.col("n_hit") >= F.col("n_words"))).alias("contaminated"), "items", "text_key",
    )
