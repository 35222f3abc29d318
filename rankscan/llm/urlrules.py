"""URL filter as a sort-merge range join between urls and prefix rules.

A host's labels in reverse order, each closed by a dot, make a key for which "this host and all its subdomains" is one
interval: the keys that begin with the rule's. Rules and urls are sorted together by key; a sweep keeps the stack of
rules whose interval holds the present key, leaves those that have ended, and looks up the url's path among each open
host's rules. The longest rule (host and path) wins, then the longer host, then block.

Urls are dealt out evenly by position, not by key, so a hot host is spread; each part gets the rules. Rules of more than
RULES_A_PART rows are cut into ranges of keys instead, with the rules that enclose a range's ends repeated, so a task's
share of the rules is bounded; within a task only the stack is in memory.

Defined cases: a null url or one without "://" has empty host and path and fits no rule; a host's case counts for nothing in A-Z;
port and user belong to the host as written; repeated rules count once and block goes before allow; null rules and rules without host
are ignored; no rules leave every url to the default verdict. Columns other than id and url are not read.
"""

from __future__ import annotations

from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import ascii_lower, cut, lean

RULES_A_PART = 100_000
#: The rules of the query, as (verdict, host and path); fixed values.
RULES = [("allow", "org/"), ("block", "example.org/es/"), ("block", "example.org/en/1"), ("allow", "com/fr/"), ("block", "com/de/")]


def host_of(url: Column) -> Column:
    found = F.regexp_extract(url, r"^(?s:.*?)://([^/?#]*)", 1)
    return F.coalesce(ascii_lower(found), F.lit(""))


def path_of(url: Column) -> Column:
    return F.coalesce(F.regexp_extract(url, r"^(?s:.*?)://[^/?#]*([^?#]*)", 1), F.lit(""))


def host_key(host: Column) -> Column:
    """"a.example.org" -> "org.example.a."; empty stays empty and lies in no rule's interval."""
    return F.when(host == "", host).otherwise(F.concat(F.array_join(F.reverse(F.split(host, r"\.")), "."), F.lit(".")))


def rules_frame(spark: SparkSession, rules: list[tuple[str, str]]) -> DataFrame:
    return spark.createDataFrame([(v, r.partition("/")[0], "/" + r.partition("/")[2]) for v, r in rules], "verdict string, host string, path string")


class _Stack:
    """Open hosts, outermost first; each with its rule paths and their distinct lengths."""

    def __init__(self):
        self.open: list[tuple[str, str, dict[str, str], list[int]]] = []

    def leave(self, key: str) -> None:
        while self.open and not key.startswith(self.open[-1][0]):
            self.open.pop()

    def enter(self, key: str, host: str, path: str, verdict: str) -> None:
        self.leave(key)
        if not self.open or self.open[-1][0] != key:
            self.open.append((key, host, {}, []))
        _, _, paths, lengths = self.open[-1]
        if paths.get(path) != "block":
            paths[path] = verdict
        if len(path) not in lengths:
            lengths.append(len(path))
            lengths.sort(reverse=True)

    def best(self, key: str, path: str) -> tuple[str | None, str | None]:
        self.leave(key)
        found, size = (None, None), -1
        for _, host, paths, lengths in reversed(self.open):
            for n in lengths:
                if n <= len(path) and len(host) + n > size and path[:n] in paths:
                    found, size = (host + path[:n], paths[path[:n]]), len(host) + n
                    break
        return found


def _sweep(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    stack, part_now = _Stack(), None
    for batch in batches:
        rule, verdict, keep = [], [], []
        cols = [batch.column(x).to_pylist() for x in ("part", "key", "url_row", "host", "path", "verdict")]
        for i, (part, key, is_url, host, path, says) in enumerate(zip(*cols)):
            if part != part_now:
                stack, part_now = _Stack(), part
            if is_url:
                found = stack.best(key, path) if key else (None, None)
                rule.append(found[0])
                verdict.append(found[1])
                keep.append(i)
            else:
                stack.enter(key, host, path, says)
        rows = batch.take(pa.array(keep, pa.int64()))
        yield pa.RecordBatch.from_arrays([rows.column("id"), rows.column("host"), rows.column("path"), pa.array(rule, pa.string()), pa.array(verdict, pa.string())], ["id", "host", "path", "rule", "verdict"])


def judge(urls: DataFrame, rules: DataFrame, id_col: str = "page_id", url_col: str = "url", default: str = "allow", rules_a_part: int = RULES_A_PART) -> DataFrame:
    """Per row: id, host, path, rule (host and path, or null), verdict (the rule's, else ``default``)."""
    spark = urls.sparkSession
    rules = rules.select(F.lower("verdict").alias("verdict"), ascii_lower(F.col("host")).alias("host"), F.coalesce("path", F.lit("/")).alias("path"))
    rules = cut(rules.where("host <> '' and verdict in ('allow', 'block')").distinct().withColumn("key", host_key(F.col("host"))))
    n_rules = rules.count()
    bounds = []
    if n_rules > rules_a_part:
        ranges = -(-n_rules // rules_a_part)
        bounds = sorted({r[0] for r in rules.select("key").distinct().repartitionByRange(ranges, "key").groupBy(F.spark_partition_id()).agg(F.min("key")).select("min(key)").collect()})[1:]
    salts = max(1, int(spark.conf.get("spark.sql.shuffle.partitions")))
    # a key's range is the number of bounds at or below it
    of = lambda key: sum((F.when(key >= b, 1).otherwise(0) for b in bounds), F.lit(0))
    last = F.concat(F.expr("substring(key, 1, length(key) - 1)"), F.lit("/"))
    page = urls.select(F.col(id_col).alias("id"), host_of(F.col(url_col)).alias("host"), path_of(F.col(url_col)).alias("path"))
    page = page.withColumn("key", host_key(F.col("host"))).withColumn("salt", F.pmod(F.monotonically_increasing_id(), F.lit(salts)))
    page = page.select(of(F.col("key")).alias("range"), "salt", "key", F.lit(True).alias("url_row"), "id", "host", "path", F.lit(None).cast("string").alias("verdict"))
    held = rules.withColumn("range", F.explode(F.sequence(of(F.col("key")), of(last)))).withColumn("salt", F.explode(F.sequence(F.lit(0), F.lit(salts - 1))))
    none = F.lit(None).cast(urls.schema[id_col].dataType)
    held = held.select("range", F.col("salt").cast("long"), "key", F.lit(False).alias("url_row"), none.alias("id"), "host", "path", "verdict")
    both = page.unionAll(held).withColumn("part", F.col("range") * salts + F.col("salt")).drop("range", "salt")
    dealt = both.repartition(salts * (len(bounds) + 1), "part").sortWithinPartitions("part", "key", "url_row", F.length("path"), "path")
    kind = urls.schema[id_col].dataType.simpleString()
    out = dealt.mapInArrow(lean(_sweep), f"id {kind}, host string, path string, rule string, verdict string")
    return out.select(F.col("id").alias(id_col), "host", "path", "rule", F.coalesce("verdict", F.lit(default)).alias("verdict"))
