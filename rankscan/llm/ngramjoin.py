"""N-gram Jaccard join: rare-first prefix filtering, then each candidate pair verified once.

1. Each text becomes its set of k-word shingle hashes. A fixed-size table of shingle counts over the whole corpus (hashed
   buckets, summed exactly) gives the rarity order; any total order keeps the join exact, a good one keeps it small.
2. Texts of equal sets form a class; one representative goes on, so copies never meet each other.
3. Two sets of Jaccard similarity t share a shingle among the n - ceil(t n) + 1 rarest of each. Prefix shingles held by
   one representative alone end here.
4. The holders of a shingle are dealt into blocks of bounded size, pairs of blocks into tiles. A tile streams through a
   task that keeps one block. A first round without the sets applies the length, position and suffix (histogram) bounds
   and returns the members that some partner passes with; groups left with the same members become one. A second round
   brings the members' sets, gives each pair to the first group it shares and counts the exact overlap. A tile returns at most a row per member and no pairs.
5. Links give components; representatives carry their classes along.

Defined cases: null, empty and wordless texts have no shingles, link with nothing and are their own component; texts of
fewer than k words have one shingle, the whole sequence; repeated rows are one class, each row is returned; rows without
id take part and a component's id is the least non-null one. Columns other than id and text are not read.
"""

from __future__ import annotations

import math
import zlib
from collections.abc import Iterator
from fractions import Fraction

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import BROADCAST_ROWS, cut, lean, small_batches, tidy
from .components import components
from .textkernel import mix, shingle_set, texts

#: The count table has 2 ** BITS buckets of a byte (counts on a logarithmic scale) whatever the corpus' size.
BITS, CHUNK = 24, 1 << 16
#: A block's members and shingles, about.
BLOCK_ROWS, BLOCK_SHINGLES = 1024, 1_000_000
BINS = 64
#: Rows of a batch that goes to a worker, and bytes of sets in one that comes back.
BATCH_ROWS, BATCH_BYTES = 512, 1 << 22
_MERGE = 1 << 20


def _bucket(tokens: np.ndarray) -> np.ndarray:
    return (tokens >> np.uint64(64 - BITS)).astype(np.int64)


def shingle_counts(docs: DataFrame, text_col: str, k: int) -> np.ndarray:
    """How common the shingles of each bucket are; only the table of fixed size comes to the driver."""

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros(1 << BITS, np.uint8)  # a task's counts end at 255, their sum does not
        held, size = [], 0

        def add() -> None:
            at, times = np.unique(_bucket(np.concatenate([*held, np.zeros(0, np.uint64)])), return_counts=True)
            total[at] = np.minimum(total[at] + times, 255)
            held.clear()

        for batch in batches:
            for buf in texts(batch.column(0)):
                held.append(shingle_set(buf, k))
                size += len(held[-1])
                if size >= _MERGE:
                    add()
                    size = 0
        add()
        for c in range(0, 1 << BITS, CHUNK):
            if total[c : c + CHUNK].any():
                yield pa.RecordBatch.from_arrays([pa.array([c], pa.int32()), pa.array([zlib.compress(total[c : c + CHUNK].tobytes(), 1)], pa.binary())], ["chunk", "counts"])

    def add_up(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        sums: dict[int, np.ndarray] = {}
        for batch in batches:
            for c, x in zip(batch.column(0).to_pylist(), batch.column(1)):
                sums[c] = sums.get(c, 0) + np.frombuffer(zlib.decompress(x.as_py()), np.uint8).astype(np.uint32)
        for c, x in sums.items():
            scaled = np.minimum(np.rint(8 * np.log2(1.0 + x)), 255).astype(np.uint8)
            yield pa.RecordBatch.from_arrays([pa.array([c], pa.int32()), pa.array([zlib.compress(scaled.tobytes(), 1)], pa.binary())], ["chunk", "counts"])

    kind = "chunk int, counts binary"
    parts = docs.select(text_col).mapInArrow(lean(count), kind).repartition(8, "chunk").mapInArrow(lean(add_up), kind)
    out = np.zeros(1 << BITS, np.uint8)
    for c, x in parts.collect():
        out[c : c + CHUNK] = np.frombuffer(zlib.decompress(bytes(x)), np.uint8)
    return out


def _rare_first(tokens: np.ndarray, counts: np.ndarray) -> np.ndarray:
    """Tokens by bucket count, ties by hash."""
    return tokens[np.argsort(counts[_bucket(tokens)], kind="stable")]


def _lists(rows: list[np.ndarray]) -> pa.Array:
    at = np.zeros(len(rows) + 1, np.int32)
    np.cumsum([len(x) for x in rows], out=at[1:])
    return pa.ListArray.from_arrays(pa.array(at), pa.array(np.concatenate([*rows, np.zeros(0, np.uint64)]).astype(np.uint64).view(np.int64)))


def _needs(na, nb, t: Fraction):
    """The least overlap of sets of these sizes that makes a link."""
    return -((-t.numerator * (na + nb)) // (t.numerator + t.denominator))


class _Block:
    """Members of one block, and an index from shingle to members built when many pairs need it."""

    def __init__(self):
        self.rid, self.n, self.at, self.bins, self.weight, self.sets, self.before = [], [], [], [], [], [], []
        self.index = None

    def add(self, rid, n, at, bins, weight, tokens, before) -> None:
        for to, x in zip((self.rid, self.n, self.at, self.bins, self.weight, self.sets, self.before), (rid, n, at, bins, weight, tokens, before)):
            to.append(x)

    def freeze(self) -> None:
        self.sizes, self.places, self.histograms = np.array(self.n), np.array(self.at), np.array(self.bins).reshape(-1, BINS).astype(np.int32)

    def possible(self, n: int, at: int, bins: np.ndarray, upto: int, t: Fraction) -> tuple[np.ndarray, np.ndarray]:
        """Members before ``upto`` that may link by length, position and histogram, and the overlap that each needs."""
        sizes, places = self.sizes[:upto], self.places[:upto]
        need = _needs(sizes, n, t)
        most = np.minimum(places, at) + np.minimum(sizes - places, n - at)
        which = np.flatnonzero((need <= np.minimum(sizes, n)) & (most >= need))
        if len(which):
            apart = np.abs(self.histograms[which] - bins).sum(1)
            which = which[apart <= sizes[which] + n - 2 * need[which]]
        return which, need[which]

    def overlaps(self, tokens: np.ndarray, which: np.ndarray) -> np.ndarray:
        if len(which) <= 8:
            return np.array([len(np.intersect1d(tokens, self.sets[j], assume_unique=True)) for j in which])
        if self.index is None:
            flat = np.concatenate(self.sets)
            order = np.argsort(flat, kind="stable")
            owner = np.repeat(np.arange(len(self.sets)), [len(x) for x in self.sets])[order]
            unique, first = np.unique(flat[order], return_index=True)
            self.index = unique, np.append(first, len(flat)), owner
        unique, first, owner = self.index
        at = np.searchsorted(unique, tokens)
        at = at[(at < len(unique)) & (unique[np.minimum(at, len(unique) - 1)] == tokens)]
        lo, lengths = first[at], first[at + 1] - first[at]
        picks = np.repeat(lo - np.append(0, np.cumsum(lengths)[:-1]), lengths) + np.arange(lengths.sum())
        return np.bincount(owner[picks], minlength=len(self.sets))[which]


def _by_tile(batches: Iterator[pa.RecordBatch], names: list[str]):
    """(tile, side, row) in order; a row that repeats its predecessor's member is left out."""
    last = None
    for batch in batches:
        for tile, side, rid, row in zip(zip(*(batch.column(x).to_pylist() for x in ("bucket", "ti", "tj"))), batch.column("side").to_pylist(), batch.column("rid").to_pylist(), zip(*(batch.column(x) for x in names))):
            if last != (tile, side, rid):
                yield tile, side, rid, row
            last = tile, side, rid


def _meet(rows, make, probe, close):
    """Keeps side 0 of each tile and probes it with side 1; a tile of one block meets itself."""
    now, block, met = None, None, False

    def end():
        if block is not None and now[1] == now[2]:
            block.freeze()
            for i in range(1, len(block.rid)):
                probe(block, now, i, (block.rid[i], block.n[i], block.at[i], block.bins[i], block.weight[i], block.sets[i], block.before[i]))
        return close(now)

    for tile, side, rid, row in rows:
        if tile != now:
            if now is not None and (out := end()) is not None:
                yield out
            now, block, met = tile, _Block(), False
        one = make(tile, rid, row)
        if side == 0:
            block.add(*one)
        else:
            if not met:
                block.freeze()
                met = True
            probe(block, now, len(block.rid), one)
    if now is not None and (out := end()) is not None:
        yield out


def _sift(t: Fraction):
    """First round: members of a shingle group that pass all bounds with some partner."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        passed: dict[int, int] = {}

        def make(tile, rid, row):
            n, at, bins = row
            return rid, n.as_py(), at.as_py(), np.frombuffer(bins.as_buffer(), np.uint16), 0, None, None

        def probe(block, tile, upto, one):
            if upto:
                which, _ = block.possible(one[1], one[2], one[3].astype(np.int32), upto, t)
                if len(which):
                    passed[one[0]] = one[2]
                    passed.update((block.rid[j], block.at[j]) for j in which.tolist())

        def close(tile):
            if not passed:
                return None
            out = pa.RecordBatch.from_arrays([pa.array([tile[0]] * len(passed), pa.int64()), pa.array(list(passed), pa.int64()), pa.array(list(passed.values()), pa.int32())], ["bucket", "rid", "at"])
            passed.clear()
            return out

        yield from _meet(_by_tile(batches, ["n", "at", "bins"]), make, probe, close)

    return run


def _verify(t: Fraction):
    """Second round: exact overlaps; each member with links, a peer of the same cluster and its number of links."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        root: dict[int, int] = {}
        links: dict[int, int] = {}

        def find(x):
            while root[x] != x:
                root[x] = root[root[x]]
                x = root[x]
            return x

        def make(tile, rid, row):
            n, at, bins, weight, tokens, groups = row
            held = groups.values.to_numpy()
            return rid, n.as_py(), at.as_py(), np.frombuffer(bins.as_buffer(), np.uint16), weight.as_py(), np.frombuffer(tokens.as_buffer(), np.uint64), set(held[held < tile[0]].tolist())

        def probe(block, tile, upto, one):
            if not upto:
                return
            rid, n, at, bins, weight, tokens, before = one
            which, need = block.possible(n, at, bins.astype(np.int32), upto, t)
            if before and len(which):
                own = np.array([before.isdisjoint(block.before[j]) for j in which])
                which, need = which[own], need[own]
            if not len(which):
                return
            for j in which[block.overlaps(tokens, which) >= need].tolist():
                other = block.rid[j]
                for x, w in ((rid, block.weight[j]), (other, weight)):
                    root.setdefault(x, x)
                    links[x] = links.get(x, 0) + w
                a, b = find(rid), find(other)
                root[max(a, b)] = min(a, b)

        def close(tile):
            if not links:
                return None
            out = pa.RecordBatch.from_arrays([pa.array(list(links), pa.int64()), pa.array([find(x) for x in links], pa.int64()), pa.array(list(links.values()), pa.int64())], ["rid", "peer", "links"])
            links.clear()
            root.clear()
            return out

        yield from _meet(_by_tile(batches, ["n", "at", "bins", "weight", "tokens", "buckets"]), make, probe, close)

    return run


def _dealt(members: DataFrame) -> DataFrame:
    """Each member once for every tile of its shingle group that its block is in."""
    each = members.withColumn("block", F.pmod(F.xxhash64("rid", F.lit(7)), "blocks").cast("int")).withColumn("other", F.explode(F.expr("sequence(0, blocks - 1)")))
    return each.withColumns({"ti": F.least("block", "other"), "tj": F.greatest("block", "other"), "side": (F.col("other") < F.col("block")).cast("int")}).drop("block", "other")


def _sorted(tiles: DataFrame) -> DataFrame:
    keys = ["bucket", "ti", "tj"]
    return tiles.repartition(*keys).sortWithinPartitions(*keys, "side", "n", "rid")


def _not_within(members: DataFrame) -> DataFrame:
    """Members of groups that do not lie within a greater one that every member of theirs has as its greatest.

    A member's greatest group (by size, then bucket) is never left out, as that member itself names it; so each pair of
    a group left out is met in a group that stays.
    """
    greatest = members.groupBy("rid").agg(F.max(F.struct("c", "bucket")).getField("bucket").alias("greatest"))
    named = members.join(greatest, "rid").groupBy("bucket").agg(F.min("greatest").alias("lo"), F.max("greatest").alias("hi"))
    return members.join(named.where("lo <> hi or lo = bucket").select("bucket"), "bucket")


def jaccard_join(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", k: int = 5, threshold: Fraction = Fraction(4, 5)) -> DataFrame:
    """Per row: id, n_shingles, component_id, n_links (rows it links with), text_key, leads (True for one row of each component)."""
    with small_batches(docs.sparkSession, BATCH_ROWS):
        return _joined(docs, id_col, text_col, k, Fraction(threshold))


def _joined(docs: DataFrame, id_col: str, text_col: str, k: int, t: Fraction) -> DataFrame:
    """All that runs Python is executed here; what is returned only joins its results."""
    spark = docs.sparkSession
    docs = docs.select(F.col(id_col).alias("doc_id"), F.col(text_col).alias("text"))
    counts = spark.sparkContext.broadcast(shingle_counts(docs, "text", k))

    def prefixes(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            sizes, heads, sign, bins = [], [], ([], []), []
            for buf in texts(batch.column("text")):
                tokens = shingle_set(buf, k)
                n = len(tokens)
                sizes.append(n)
                heads.append(_rare_first(tokens, counts.value)[: n - math.ceil(t * n) + 1] if n else tokens)
                sign[0].append(int(np.bitwise_xor.reduce(tokens)) if n else 0)
                mixed = mix(tokens ^ np.uint64(0xA5A5A5A5))
                sign[1].append(int(mixed.sum()) if n else 0)
                bins.append(np.minimum(np.bincount((mixed >> np.uint64(58)).astype(np.int64), minlength=BINS), 65535).astype(np.uint16).tobytes())
            signed = [pa.array(np.array(x, np.uint64).view(np.int64)) for x in sign]
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), batch.column("text_key"), pa.array(sizes, pa.int64()), *signed, _lists(heads), pa.array(bins, pa.binary())], ["doc_id", "text_key", "n", "s1", "s2", "head", "bins"])

    id_kind = docs.schema["doc_id"].dataType.simpleString()
    slim = docs.select("doc_id", F.xxhash64("text").alias("text_key"), "text").mapInArrow(lean(prefixes), f"doc_id {id_kind}, text_key bigint, n bigint, s1 bigint, s2 bigint, head array<bigint>, bins binary")
    rows = cut(slim.withColumn("rid", F.monotonically_increasing_id()))
    counts.destroy()  # nothing after the cut reads it
    classes = cut(rows.where("n > 0").groupBy("s1", "s2", "n").agg(F.min("rid").alias("rid"), F.count("*").alias("weight"), F.min("doc_id").alias("least_id")))
    heads = rows.where("n > 0").join(classes.select("rid", "weight"), "rid")
    posts = heads.select("rid", "n", F.posexplode("head").alias("at", "token"))
    held = posts.groupBy("token").agg(F.count("*").alias("c")).where("c > 1").select("token", F.ceil(F.col("c") / BLOCK_ROWS).cast("int").alias("blocks"))
    members = posts.join(held, "token").select("rid", "n", F.col("token").alias("bucket"), "at", "blocks")
    sifted = _sorted(_dealt(members.join(rows.select("rid", "bins"), "rid"))).mapInArrow(lean(_sift(t)), "bucket bigint, rid bigint, at int")
    sifted = cut(sifted.distinct())
    tidy(spark)
    mark = F.xxhash64("rid")
    sizes = sifted.groupBy("bucket").agg(F.count("*").alias("c"), F.bit_xor(mark).alias("x1"), F.sum(F.shiftright(mark, 20)).alias("x2"))
    groups = sizes.groupBy("c", "x1", "x2").agg(F.min("bucket").alias("bucket"))
    sifted = cut(_not_within(sifted.join(groups.select("bucket", "c"), "bucket")).withColumn("by_rows", F.ceil(F.col("c") / BLOCK_ROWS).cast("int")))
    live = cut(sifted.groupBy("rid").agg(F.array_sort(F.collect_list("bucket")).alias("buckets")).join(heads.select("rid", "n", "weight", "doc_id", "text_key", "bins"), "rid"))
    weighed = sifted.join(live.select("rid", F.col("n").alias("_n")), "rid").groupBy("bucket").agg(F.ceil(F.sum("_n") / BLOCK_SHINGLES).cast("int").alias("by_size"))
    left = sifted.join(weighed, "bucket").select("rid", "bucket", "at", F.greatest("by_rows", "by_size").alias("blocks"))

    def sets(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            rids, held, size = [], [], 0
            for rid, buf in zip(batch.column(0).to_pylist(), texts(batch.column(1))):
                rids.append(rid)
                held.append(shingle_set(buf, k).tobytes())
                size += len(held[-1])
                if size >= BATCH_BYTES:
                    yield pa.RecordBatch.from_arrays([pa.array(rids, pa.int64()), pa.array(held, pa.binary())], ["rid", "tokens"])
                    rids, held, size = [], [], 0
            if rids:
                yield pa.RecordBatch.from_arrays([pa.array(rids, pa.int64()), pa.array(held, pa.binary())], ["rid", "tokens"])

    tidy(spark)
    wanted = live.select("rid", F.col("doc_id").alias("_id"), F.col("text_key").alias("_key"))
    wanted = F.broadcast(wanted) if live.count() <= BROADCAST_ROWS else wanted
    full = docs.join(wanted, F.xxhash64("text").eqNullSafe(F.col("_key")) & F.col("doc_id").eqNullSafe(F.col("_id"))).select("rid", "text").mapInArrow(lean(sets), "rid bigint, tokens binary")
    tiles = _dealt(left).join(live.select("rid", "n", "weight", "buckets", "bins"), "rid").join(full, "rid")
    found = cut(_sorted(tiles).mapInArrow(lean(_verify(t)), "rid bigint, peer bigint, links bigint"))

    tidy(spark)
    labels = components(found.select(F.col("rid").alias("a"), F.col("peer").alias("b")))
    named = labels.join(classes, labels["vertex"] == classes["rid"]).select("vertex", "label", "least_id", "weight")
    least = named.groupBy("label").agg(F.min("least_id").alias("component_id"), F.min("vertex").alias("leader"))
    joined = named.select("vertex", "label").join(least, "label").select(F.col("vertex").alias("rid"), "component_id", "leader")
    linked = found.groupBy("rid").agg(F.sum("links").alias("links"))
    of_class = classes.join(joined, "rid", "left").join(linked, "rid", "left").select(
        "s1", "s2", "n", F.coalesce("component_id", "least_id").alias("component_id"), (F.coalesce("links", F.lit(0)) + F.col("weight") - 1).alias("n_links"), F.coalesce("leader", "rid").alias("leader")
    )
    some = rows.where("n > 0").drop("head", "bins").join(of_class, ["s1", "s2", "n"])
    none = rows.where("n = 0").drop("head", "bins").select("*", F.col("doc_id").alias("component_id"), F.lit(0).cast("long").alias("n_links"), F.col("rid").alias("leader"))
    cols = [F.col("doc_id").alias(id_col), F.col("n").alias("n_shingles"), "component_id", "n_links", "text_key", "rid", "leader"]
    return some.select(*cols).unionAll(none.select(*cols))


def one_of_each(joined: DataFrame, id_col: str = "doc_id") -> DataFrame:
    """The rows of ``jaccard_join`` that may go so that the row of the least id stays of each component (ids, text_key).

    Rows equal in id and text to one that stays are not named, as ids and texts could not tell them apart.
    """
    best = joined.groupBy("leader").agg(F.min(F.struct(F.col(id_col).isNull().alias("none"), F.col(id_col).alias("id"), F.col("text_key").alias("key"))).alias("best"))
    return joined.join(best, "leader").where(~(F.col(id_col).eqNullSafe(F.col("best.id")) & F.col("text_key").eqNullSafe(F.col("best.key")))).select(id_col, "text_key")
