"""WARC fixity audit with Merkle trees.

Records are hashed, ordered by offset within their file, and sixteen neighbours at a time are hashed together level by
level: ranges of offsets in a file, whole files, ranges of files, up to one root. A node's digest covers its file and range
of offsets, so replicas whose roots agree hold the same records at the same places; otherwise the audit compares children only of nodes that differ and so reaches the corrupt records. Nodes
are rows (level, node), children of a node are those with its number as ``node div 16``; a level's shuffle groups at most
sixteen rows, whatever the archive's size. A file holds a bounded range of page ids and identical records of an id are
stored once, so no file grows with the archive.

Defined cases: a null url or body is an empty one; records without id go to file -1 in order of their digest; repeated equal records count
once (``copies`` says how many there are); no records give no tree, and two empty archives agree; a record on one side
only is a mismatch. Columns other than id, url and body are not read.
"""

from __future__ import annotations

import gzip
import re
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import Window

from .common import cut

FAN, FILE_IDS = 16, 256
_HEAD = "WARC/1.0\r\nWARC-Type: resource\r\nWARC-Target-URI: "


def record_text(url: Column, body: Column) -> Column:
    """A record of WARC 1.0, as text."""
    body = F.coalesce(body, F.lit(""))
    return F.concat(F.lit(_HEAD), F.coalesce(url, F.lit("")), F.lit("\r\nContent-Type: text/html\r\nContent-Length: "), F.octet_length(body).cast("string"), F.lit("\r\n\r\n"), body, F.lit("\r\n\r\n"))


def records(pages: DataFrame, id_col: str = "page_id", url_col: str = "url", body_col: str = "html") -> DataFrame:
    """Per distinct record: file, pos, offset, length, digest, page_id, copies."""
    text = record_text(F.col(url_col), F.col(body_col))
    each = pages.select(F.col(id_col).cast("long").alias("page_id"), F.sha2(text, 256).alias("digest"), F.octet_length(text).cast("long").alias("length"))
    each = each.groupBy("page_id", "digest", "length").agg(F.count("*").alias("copies"))
    each = each.withColumn("file", F.coalesce(F.floor(F.col("page_id") / FILE_IDS), F.lit(-1)).cast("long"))
    order = Window.partitionBy("file").orderBy("page_id", "digest", "length")
    before = order.rowsBetween(Window.unboundedPreceding, -1)
    return each.select("file", (F.row_number().over(order) - 1).cast("long").alias("pos"), F.coalesce(F.sum("length").over(before), F.lit(0)).alias("offset"), "length", "digest", "page_id", "copies")


def tree(leaves: DataFrame) -> DataFrame:
    """All inner nodes (level, file, node, first, last, digest); levels in files first, then over files (file is null)."""
    levels = []
    now = leaves.select("file", F.col("pos").alias("node"), F.col("offset").alias("first"), (F.col("offset") + F.col("length")).alias("last"), "digest")
    level, of_files = 0, False
    while True:
        level += 1
        up = now.groupBy("file", F.floor(F.col("node") / FAN).alias("node")).agg(F.min("first").alias("first"), F.max("last").alias("last"), F.array_sort(F.collect_list(F.struct("node", "digest"))).alias("below"))
        # a node's digest binds where it is: file, range of offsets, and each child's number with its digest
        place = F.concat_ws("|", F.coalesce(F.col("file").cast("string"), F.lit("files")), "node", "first", "last")
        held = F.array_join(F.transform("below", lambda x: F.concat(x["node"].cast("string"), F.lit(":"), x["digest"])), ",")
        up = up.select("file", "node", "first", "last", F.sha2(F.concat(place, F.lit("|"), held), 256).alias("digest"))
        up = cut(up)
        levels.append(up.select(F.lit(level).alias("level"), F.lit(of_files).alias("of_files"), "file", "node", "first", "last", "digest"))
        n, most = up.agg(F.count("*"), F.max("node")).first()
        if n <= 1 and (of_files or n == 0):
            break
        if not of_files and most == 0:
            of_files = True
            now = up.select(F.lit(None).cast("long").alias("file"), (F.col("file") + 1).alias("node"), F.col("file").alias("first"), F.col("file").alias("last"), "digest")
        else:
            now = up
    out = levels[0]
    for x in levels[1:]:
        out = out.unionAll(x)
    return out


def audit(leaves: DataFrame, replica: DataFrame) -> DataFrame:
    """Positions (file, pos) whose records differ between two archives, found from the roots down."""
    nodes = [cut(tree(x)) for x in (leaves, replica)]
    # the smaller archive's top may be lower: its missing levels differ as a whole, which only costs comparisons
    tops = [x.agg(F.max("level"), F.max(F.when(~F.col("of_files"), F.col("level")))).first() for x in nodes]
    top, of_file = max((t[0] or 0 for t in tops)), max((t[1] or 0 for t in tops))
    agreeing_shape = tops[0] == tops[1]
    marked = None
    for level in range(top, 0, -1):
        a, b = (x.where(F.col("level") == level).select("of_files", "file", "node", "digest") for x in nodes)
        if marked is not None and agreeing_shape:
            a, b = (_below(x, marked, level == of_file) for x in (a, b))
        marked = cut(_differing(a, b))
        if agreeing_shape and marked.isEmpty():
            break
    a, b = (x.select("file", F.col("pos").alias("node"), "digest", "length") for x in (leaves, replica))
    if marked is not None:
        a, b = (_below(x, marked, False) for x in (a, b))
    return _differing(*(x.select(F.lit(False).alias("of_files"), "file", "node", "digest") for x in (a, b))).withColumnRenamed("node", "pos")


def _differing(a: DataFrame, b: DataFrame) -> DataFrame:
    """(file, node) of rows whose digests differ or that one side lacks."""
    b = b.select(*[F.col(c).alias(f"_{c}") for c in ("of_files", "file", "node", "digest")])
    same = F.col("of_files").eqNullSafe(F.col("_of_files")) & F.col("file").eqNullSafe(F.col("_file")) & F.col("node").eqNullSafe(F.col("_node"))
    differ = a.join(b, same, "full").where(~F.col("digest").eqNullSafe(F.col("_digest")))
    return differ.select(F.coalesce("file", "_file").alias("file"), F.coalesce("node", "_node").alias("node"))


def _below(children: DataFrame, marked: DataFrame, files: bool) -> DataFrame:
    """Children of marked nodes; at the seam, a file's own root is the child of a range of files."""
    m = marked.select(F.col("file").alias("_file"), F.col("node").alias("_node"))
    if files:
        return children.join(m, F.floor((F.col("file") + 1) / FAN) == F.col("_node"), "left_semi")
    return children.join(m, F.col("file").eqNullSafe(F.col("_file")) & (F.floor(F.col("node") / FAN) == F.col("_node")), "left_semi")


def corrupted(pages: DataFrame, every: int = 97) -> DataFrame:
    """A replica in which the body of each page whose id's crc32 is divisible by ``every`` has lost its last character."""
    hit = F.crc32(F.col("page_id").cast("string").cast("binary")) % every == 0
    return pages.withColumn("html", F.when(hit & (F.length("html") > 0), F.expr("substring(html, 1, length(html) - 1)")).otherwise(F.col("html")))


def parse_warc(data: bytes) -> Iterator[tuple[int, int, dict[str, str], bytes]]:
    """(offset, length, headers, body) of each record; gzip members are opened first."""
    if data[:2] == b"\x1f\x8b":
        data = gzip.decompress(data)
    at = 0
    while (begin := data.find(b"WARC/", at)) >= 0:
        end = data.index(b"\r\n\r\n", begin) + 4
        headers = dict(re.findall(r"([\w-]+): ?([^\r\n]*)", data[begin:end].decode("utf-8", "replace")))
        size = int(headers.get("Content-Length", 0))
        at = end + size
        stop = at + 4 if data[at : at + 4] == b"\r\n\r\n" else at
        yield begin, stop - begin, headers, data[end:at]
        at = stop


def read_warc(spark: SparkSession, path: str) -> DataFrame:
    """Records of the WARC files at ``path``: file_path, offset, length, url, body. A file is read by one task."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for where, content in zip(batch.column(0).to_pylist(), batch.column(1)):
                rows = [(where, o, n, h.get("WARC-Target-URI"), b) for o, n, h, b in parse_warc(content.as_py())]
                cols = list(zip(*rows)) or [[]] * 5
                kinds = (pa.string(), pa.int64(), pa.int64(), pa.string(), pa.binary())
                yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(cols, kinds)], ["file_path", "offset", "length", "url", "body"])

    return spark.read.format("binaryFile").load(path).select("path", "content").mapInArrow(run, "file_path string, offset bigint, length bigint, url string, body binary")
