"""Exact top-k inner products with a bit-sliced index.

Components are quantised to integers. A block of rows keeps, for each attribute, one bitmap over its rows per binary
slice (values less the block's least, so none is negative). For a query, the slices of attributes with a negative
weight are complemented and all slices enter columns by their power of two; carry-save adders of bitwise operations
turn the columns into the bit slices of a sum that orders rows as the inner product does. From the most significant
slice downward rows are kept or set aside until k are left; rows equal in every slice are the boundary and go by id.
Exact scores come from the slices of the sum and a constant of the query.

Rows are dealt to blocks by position, never by value. Each block is one task's stream: index rows first, then the
queries, which are repeated once a block. A task holds one block's slices.

Defined cases: null vectors, and vectors with a null or non-finite component, with a component of 2^45 or more, or of
another length than ``width`` (by default the commonest, of equally common ones the greatest), take no part; scores
beyond a long are held at its ends; a query leaves out all rows of its own id; repeated rows are candidates of their own,
and each of several query rows of one id is answered for itself; fewer than k candidates are
all returned; rows without id are neither queries nor candidates. Columns other than id and vector are not read.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window

from .common import cut, lean

BLOCK_ROWS = 16_384


#: Quantised components of this size or more are not whole numbers of a double any more.
MOST = 1 << 53


def quantised(vector: Column, scale: int = 256) -> Column:
    return F.transform(vector, lambda x: F.floor(F.lit(scale) * x.cast("double")).cast("long"))


class SliceIndex:
    """Bitmaps of one block's attribute slices."""

    def __init__(self, ids: np.ndarray, values: np.ndarray):
        order = np.argsort(ids, kind="stable")
        self.ids, values = ids[order], values[order].astype(np.int64)
        self.n = len(ids)
        self.low = values.min(0)
        shifted = values - self.low
        self.bits = [int(x).bit_length() for x in shifted.max(0)]
        self.full = self._pack(np.ones(self.n, bool))
        self.slices = [[self._pack((shifted[:, d] >> b) & 1) for b in range(n)] for d, n in enumerate(self.bits)]
        self.flipped = [[~x & self.full for x in row] for row in self.slices]

    def _pack(self, flags: np.ndarray) -> np.ndarray:
        packed = np.packbits(flags.astype(bool), bitorder="little")
        return np.pad(packed, (0, -len(packed) % 8)).view(np.uint64)

    def total(self, weights: np.ndarray) -> tuple[list[np.ndarray], int]:
        """Bit slices of each row's weighted sum, and what to add to get the inner product."""
        columns: list[list[np.ndarray]] = []
        constant = sum(a * b for a, b in zip(weights.tolist(), self.low.tolist()))
        for d, w in enumerate(weights.tolist()):
            if not w or not self.bits[d]:
                continue
            rows = self.slices[d] if w > 0 else self.flipped[d]
            if w < 0:
                constant -= -w * ((1 << self.bits[d]) - 1)
            size = abs(w)
            for c in range(size.bit_length()):
                if size >> c & 1:
                    while len(columns) < c + len(rows):
                        columns.append([])
                    for b, x in enumerate(rows):
                        columns[b + c].append(x)
        out, at = [], 0
        while at < len(columns):
            col = columns[at]
            carry = []
            while len(col) >= 3:
                x, y, z = col.pop(), col.pop(), col.pop()
                t = x ^ y
                col.insert(0, t ^ z)
                carry.append((x & y) | (t & z))
            if len(col) == 2:
                x, y = col
                col = [x ^ y]
                carry.append(x & y)
            out.append(col[0] if col else np.zeros_like(self.full))
            if carry:
                if at + 1 == len(columns):
                    columns.append([])
                columns[at + 1].extend(carry)
            at += 1
        return out, constant

    def top(self, own: int, weights: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray]:
        """Ids and exact scores of the k best rows, own id left out; ties by id."""
        total, constant = self.total(weights)
        sure, edge = np.zeros_like(self.full), self.full.copy()
        a, b = np.searchsorted(self.ids, [own, own + 1])
        for i in range(a, b):
            edge[i >> 6] &= ~(np.uint64(1) << np.uint64(i & 63))
        have = 0
        for x in reversed(total):
            ahead = edge & x
            n = int(np.bitwise_count(ahead).sum())
            if have + n > k:
                edge = ahead
            else:
                sure |= ahead
                have += n
                edge = edge & ~x
                if have == k:
                    edge[:] = 0
                    break
        rows = self._rows(sure)
        rows = np.concatenate([rows, self._rows(edge)[: k - len(rows)]])
        wide = len(total) > 61 or abs(constant) >= 1 << 61  # whole numbers of any size, held at the ends of a long
        score = np.full(len(rows), constant, object if wide else np.int64)
        for b, x in enumerate(total):
            bit = ((x[rows >> 6] >> (rows & 63).astype(np.uint64)) & np.uint64(1)).astype(np.int64)
            score += bit.astype(object) * (1 << b) if wide else bit << b
        return self.ids[rows], np.clip(score, -(1 << 63), (1 << 63) - 1).astype(np.int64)

    @staticmethod
    def _rows(bitmap: np.ndarray) -> np.ndarray:
        return np.flatnonzero(np.unpackbits(bitmap.view(np.uint8), bitorder="little"))


def _search(k: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        now, ids, values, indexes = None, [], [], []

        def seal() -> None:
            if ids:
                indexes.append(SliceIndex(np.concatenate(ids), np.concatenate(values)))
                ids.clear()
                values.clear()

        for batch in batches:
            block, query, rows, asked = (batch.column(x).to_numpy() for x in ("block", "query", "vec_id", "row"))
            flat = batch.column("q").flatten().to_numpy().reshape(len(rows), -1) if len(rows) else np.zeros((0, 0))
            out: list[list[np.ndarray]] = [[], [], [], []]
            cuts = np.flatnonzero(np.append(True, (block[1:] != block[:-1]) | (query[1:] != query[:-1]))) if len(rows) else np.zeros(0, int)
            for a, b in zip(cuts.tolist(), [*cuts[1:].tolist(), len(rows)]):
                if block[a] != now:
                    now, indexes = block[a], []
                    ids.clear()
                    values.clear()
                if query[a] == 0:
                    ids.append(rows[a:b])
                    values.append(flat[a:b])
                    if sum(map(len, ids)) >= 4 * BLOCK_ROWS:
                        seal()
                    continue
                seal()
                for i in range(a, b):
                    for index in indexes:
                        found, score = index.top(int(rows[i]), flat[i].astype(np.int64), k)
                        for to, x in zip(out, (np.full(len(found), asked[i]), np.full(len(found), rows[i]), found, score)):
                            to.append(x)
            if out[0]:
                yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(x), pa.int64()) for x in out], ["row", "query_id", "vec_id", "score"])

    return run


def top_k(vectors: DataFrame, id_col: str = "vec_id", vector_col: str = "embedding", k: int = 5, query_every: int = 50, width: int | None = None, block_rows: int = BLOCK_ROWS) -> DataFrame:
    """Per query (ids divisible by ``query_every``): query_id, rank, vec_id, score of its k best rows."""
    all_rows = vectors.select(F.col(id_col).cast("long").alias("vec_id"), F.col(vector_col).alias("v")).where("vec_id is not null and v is not null")
    if width is None:
        sizes = all_rows.where(F.size("v") > 0).groupBy(F.size("v").alias("width")).agg(F.count("*").alias("n"))
        width = (sizes.agg(F.max_by("width", F.struct("n", "width"))).first() or [0])[0] or 0
    bad = F.exists("v", lambda x: x.isNull() | F.isnan(x) | (F.abs(x.cast("double")) * 256 >= MOST))
    good = all_rows.where((F.size("v") == width) & ~F.coalesce(bad, F.lit(True)))
    rows = cut(good.select(F.monotonically_increasing_id().alias("row"), "vec_id", quantised(F.col("v")).alias("q")))
    blocks = max(1, -(-rows.count() // block_rows))
    index = rows.select(F.pmod(F.xxhash64("row"), F.lit(blocks)).cast("int").alias("block"), F.lit(0).alias("query"), "row", "vec_id", "q")
    asked = rows.where(F.pmod("vec_id", F.lit(query_every)) == 0)
    asked = asked.select(F.explode(F.sequence(F.lit(0), F.lit(blocks - 1))).alias("block"), F.lit(1).alias("query"), "row", "vec_id", "q")
    # a block is a partition of its own: hashing block numbers would put several into one task and leave others idle
    dealt = index.unionAll(asked).repartitionById(blocks, F.col("block")).sortWithinPartitions("block", "query", "vec_id", "row")
    found = cut(dealt.mapInArrow(lean(_search(k)), "row bigint, query_id bigint, vec_id bigint, score bigint"))
    order = Window.partitionBy("row").orderBy(F.col("score").desc(), "vec_id")
    return found.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k).select("query_id", F.col("rank").cast("int"), "vec_id", "score")
