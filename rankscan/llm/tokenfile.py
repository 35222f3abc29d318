"""Token ids in Arrow files of fixed-size lists: equal-length sequences with masks that are read without copying.

Documents go by range of id to shards; a shard is one Arrow file whose record batches hold ``ids`` (fixed_size_list of
``length``) and ``mask`` (the same of bool; False only pads a shard's last sequence), and beside it an index file
(doc_id, start, n_tokens). A memory map of a shard gives sequence i as a view. Task attempts write under names of
their own and only the manifest counts, so a lost executor leaves no wrong file.

Ids are uint16 where the vocabulary allows, else uint32. A byte-level tokenizer's word pattern parts a text at white
space whatever stands around it, so ids of such pieces, kept in caches of bounded size, make up the text's ids (see
``Encoder``).

Defined cases: null and empty texts are the end id alone; rows without id come first; rows of one id go by their text's
hash; no rows give no shard. Columns other than id and text are not read.
"""

from __future__ import annotations

import json
import os
import re
import struct
import uuid
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import pyarrow.fs
import pyarrow.ipc
import regex
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import cut, kept, lean, shared_path, small_batches

LENGTH, BATCH = 2048, 256
#: Documents of an Arrow batch.
PART = 2000
#: Entries of each half of an encoder's cache; bytes of text that are encoded at a time.
CACHE, STRETCH = 250_000, 8 << 20
#: Pieces that the library encodes as one row, and such rows at a time.
ROW, ROWS = 500, 20
#: Unicode white space, as the library's patterns have it; fixed values.
_WHITE = "\t-\r \x85\xa0\u1680\u2000-\u200a\u2028\u2029\u202f\u205f\u3000"
_PIECE = re.compile(f" ?[^{_WHITE}]+|[{_WHITE}]+(?![^{_WHITE}])|[{_WHITE}]")
_WHITE_RUN = f"[{_WHITE}] "
_WHITE_CHARS = frozenset(c for c in map(chr, range(0x3001)) if re.match(f"[{_WHITE}]", c))
#: The library's word pattern of byte-level models; fixed value.
_WORD = regex.compile(r"'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+")
#: Bytes stand for themselves where they are printable, else for the characters from 256 on.
_PLAIN = {*range(33, 127), *range(161, 173), *range(174, 256)}
_BYTE_CHARS = {b: 256 + i for i, b in enumerate(b for b in range(256) if b not in _PLAIN)}
_BLANK = chr(_BYTE_CHARS[32])


class Encoder:
    """Ids of whole texts as arrays, equal to those of the library's ``encode``.

    Of byte-level models with the usual word pattern, the words that a text is parted into before any blank that follows
    no white space are the same whatever stands around them. So a stretch of texts is parted there, only its distinct
    pieces are looked up in a bounded cache, and their ids are gathered for all places at once. New pieces that begin with
    a blank and do not end in white space are encoded by the library in rows of many, and parted again by the bytes that
    each id stands for. Any other piece is parted into words by the pattern where its characters' classes are beyond doubt
    (printable, up to U+024F), else by the library; the library's model encodes each word. Other texts go through the pattern piece by piece; texts with added tokens,
    and all texts of other models, are encoded whole.
    """

    def __init__(self, path: str):
        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_file(path)
        self.dtype = np.dtype("<u2" if self.tokenizer.get_vocab_size() <= 1 << 16 else "<u4")
        self.added = [x.content for x in self.tokenizer.get_added_tokens_decoder().values()]
        says = json.loads(self.tokenizer.to_str())
        cutter, usual = says["pre_tokenizer"] or {}, {"type": "ByteLevel", "add_prefix_space": False, "use_regex": True}
        self.byte_level = all(cutter.get(k) == v for k, v in usual.items()) and not (says["normalizer"] or says["truncation"] or says["padding"])
        self.byte_level &= says["model"]["type"] == "BPE" and not says["model"].get("dropout")
        self.rows = self.byte_level and not any(" " in x for x in self.added)
        self.bytes_of = np.zeros(self.tokenizer.get_vocab_size(), np.int32)
        for token, i in self.tokenizer.get_vocab().items():
            self.bytes_of[i] = len(token)
        self.young: dict[str, bytes] = {}
        self.old: dict[str, bytes] = {}

    def _pack(self, ids: list[int]) -> bytes:
        return struct.pack(f"<{len(ids)}{'H' if self.dtype.itemsize == 2 else 'I'}", *ids)

    def _word(self, word: str) -> bytes:
        # the model takes a character a byte; a blank is the one that printable ASCII does not keep
        plain = word.isascii() and word.isprintable()
        chars = word.replace(" ", _BLANK) if plain else word.encode().decode("latin-1").translate(_BYTE_CHARS)
        return self._pack([t.id for t in self.tokenizer.model.tokenize(chars)])

    def _words_of(self, piece: str) -> list[str]:
        if piece.isprintable() and (piece.isascii() or max(piece) < "\u0250"):
            return _WORD.findall(piece)
        if len(split := _PIECE.findall(piece)) > 1:
            return [w for x in split for w in self._words_of(x)]
        at = [b for _, (_, b) in self.tokenizer.pre_tokenizer.pre_tokenize_str(piece)]
        return [piece[a:b] for a, b in zip([0, *at], at)]

    def pieces(self, pieces: list[str]) -> list[bytes]:
        """Ids of each piece. The cache has two halves: when the younger is full it becomes the older, and what is still
        in use comes back from there."""
        if len(self.young) > CACHE:
            self.young, self.old = {}, self.young
        young, old = self.young, self.old
        new = []
        for x in pieces:
            if x not in young:
                if (ids := old.get(x)) is None:
                    new.append(x)
                else:
                    young[x] = ids
        parted, in_rows = {}, [x for x in new if x[:1] == " " and x[-1] not in _WHITE_CHARS] if self.rows else []
        for a in range(0, len(in_rows), ROWS * ROW):
            self._in_rows(in_rows[a : a + ROWS * ROW])
        for x in [x for x in new if x not in young] if len(in_rows) < len(new) or in_rows and in_rows[-1] not in young else []:
            # letters after at most one blank are one word, as is known without the pattern
            if x.isalpha() or (x[:1] == " " and x[1:].isalpha()):
                young[x] = self._word(x)
            else:
                parted[x] = self._words_of(x)
        for x, words in parted.items():
            for w in words:
                if w not in young:
                    young[w] = old[w] if w in old else self._word(w)
            young[x] = b"".join(map(young.__getitem__, words))
        return list(map(young.__getitem__, pieces))

    def _in_rows(self, pieces: list[str]) -> None:
        """Ids of pieces of which each begins with a blank and ends in no white space, so that they stay apart in a row."""
        rows = ["".join(pieces[a : a + ROW]) for a in range(0, len(pieces), ROW)]
        ids = np.concatenate([np.array(x.ids, self.dtype) for x in self.tokenizer.encode_batch_fast(rows, add_special_tokens=False)])
        ends, told = np.cumsum(pc.binary_length(pa.array(pieces, pa.string())).to_numpy()), np.cumsum(self.bytes_of[ids])
        stop = np.searchsorted(told, ends)
        if stop[-1] != len(ids) - 1 or (told[stop] != ends).any():
            return  # a model that does not give back every byte: pieces go word by word
        data, stop = ids.tobytes(), ((stop + 1) * self.dtype.itemsize).tolist()
        self.young.update((x, data[a:b]) for x, a, b in zip(pieces, [0, *stop], stop))

    def _whole(self, texts: list[str]) -> list[bytes]:
        return [self._pack(x.ids) for x in self.tokenizer.encode_batch_fast(texts, add_special_tokens=False)]

    def _odd(self, text: str) -> bytes:
        split = _PIECE.findall(text)
        unique = list(set(split))
        return b"".join(map(dict(zip(unique, self.pieces(unique))).__getitem__, split))

    def _plain(self, texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
        """Ids of all texts, and where each text's end."""
        lists = pc.split_pattern(texts, " ")
        ends = lists.offsets.to_numpy()[1:] - lists.offsets[0].as_py()
        first = ends - lists.value_lengths().to_numpy()
        coded = lists.flatten().dictionary_encode()
        at, heads = coded.indices.to_numpy().copy(), lists.flatten().take(pa.array(first)).dictionary_encode()
        at[first] = len(coded.dictionary) + heads.indices.to_numpy()
        parts = [" " + x for x in coded.dictionary.to_pylist()], heads.dictionary.to_pylist()
        del lists, coded, heads
        ids = [x for each in parts for x in self.pieces(each)]
        del parts
        # places within a stretch fit 32 bits unless one text alone is so long
        kind = np.int32 if len(ids) < 1 << 30 and texts.nbytes < 1 << 30 else np.int64
        size = np.fromiter(map(len, ids), kind, len(ids)) // self.dtype.itemsize
        start, flat = np.cumsum(size, dtype=kind) - size, np.frombuffer(b"".join(ids), self.dtype)
        del ids
        each = size[at]
        stop = np.cumsum(each, dtype=kind)
        place = np.repeat(start[at] - (stop - each), each)
        place += np.arange(stop[-1], dtype=kind)
        return flat[place], stop[ends - 1]

    def column(self, texts: pa.Array) -> list[bytes]:
        """Ids of each row; null counts as empty."""
        texts = pc.fill_null(texts, "")
        out: list[bytes] = [b""] * len(texts)
        whole = pa.array(np.full(len(texts), not self.byte_level))
        for x in self.added:
            whole = pc.or_(whole, pc.match_substring(texts, x))
        odd = pc.and_not(pc.match_substring_regex(texts, _WHITE_RUN), whole)
        plain = pc.and_not(pc.invert(whole), odd)
        at = np.flatnonzero(plain.to_numpy(zero_copy_only=False))
        sizes = np.cumsum(pc.binary_length(texts).to_numpy()[at])
        for a in np.flatnonzero(np.append(True, sizes[1:] // STRETCH != sizes[:-1] // STRETCH))[: len(at)].tolist():
            b = int(np.searchsorted(sizes // STRETCH, sizes[a] // STRETCH, "right"))
            ids, ends = self._plain(texts.take(pa.array(at[a:b])))
            for i, x in zip(at[a:b].tolist(), np.split(ids, ends[:-1])):
                out[i] = x.tobytes()
        for i in np.flatnonzero(odd.to_numpy(zero_copy_only=False)).tolist():
            out[i] = self._odd(texts[i].as_py())
        rest = np.flatnonzero(whole.to_numpy(zero_copy_only=False)).tolist()
        for i, x in zip(rest, self._whole([texts[i].as_py() for i in rest])):
            out[i] = x
        return out

    def __call__(self, texts: list[str]) -> list[bytes]:
        return self.column(pa.array(texts, pa.string()))


def encoder(path: str) -> Encoder:
    """The worker's encoder, kept while it serves this operator and tokenizer."""
    return kept(f"tokenfile {path}", lambda: Encoder(path))


def _open(uri: str):
    return pyarrow.fs.FileSystem.from_uri(uri)


class ShardWriter:
    """Packs ids into sequences of ``length`` and writes a batch whenever it is full."""

    def __init__(self, uri: str, length: int, dtype: np.dtype):
        self.length, self.dtype, self.tail, self.tokens = length, dtype, b"", 0
        kind = pa.from_numpy_dtype(dtype)
        self.schema = pa.schema([("ids", pa.list_(kind, length)), ("mask", pa.list_(pa.bool_(), length))])
        fs, path = _open(uri)
        fs.create_dir(path.rpartition("/")[0], recursive=True)
        self.file = fs.open_output_stream(path)
        self.writer = pa.ipc.new_file(self.file, self.schema)

    def _write(self, data: bytes, real: int) -> None:
        ids = pa.FixedSizeListArray.from_arrays(pa.Array.from_buffers(pa.from_numpy_dtype(self.dtype), len(data) // self.dtype.itemsize, [None, pa.py_buffer(data)]), self.length)
        mask = np.ones(len(data) // self.dtype.itemsize, bool)
        mask[real:] = False
        self.writer.write_batch(pa.record_batch([ids, pa.FixedSizeListArray.from_arrays(pa.array(mask), self.length)], schema=self.schema))

    def add(self, parts: list[bytes]) -> None:
        data = b"".join([self.tail, *parts])
        step = self.length * BATCH * self.dtype.itemsize
        self.tokens += sum(map(len, parts)) // self.dtype.itemsize
        full = len(data) // step * step
        for a in range(0, full, step):
            self._write(data[a : a + step], self.length * BATCH)
        self.tail = data[full:]

    def close(self) -> None:
        if self.tail:
            row = self.length * self.dtype.itemsize
            self._write(self.tail.ljust(-(-len(self.tail) // row) * row, b"\0"), len(self.tail) // self.dtype.itemsize)
        self.writer.close()
        self.file.close()


class Shard:
    """Random access to a shard's sequences; on a local path they are views of the memory map."""

    def __init__(self, uri: str):
        fs, path = _open(uri)
        self.source = pa.memory_map(path) if isinstance(fs, pyarrow.fs.LocalFileSystem) else fs.open_input_file(path)
        self.reader = pa.ipc.open_file(self.source)
        self.length = self.reader.schema.field("ids").type.list_size
        self.held: tuple[int, pa.RecordBatch] | None = None

    def batch(self, k: int) -> pa.RecordBatch:
        if self.held is None or self.held[0] != k:
            self.held = k, self.reader.get_batch(k)
        return self.held[1]

    def __len__(self) -> int:
        n = self.reader.num_record_batches
        return (n - 1) * BATCH + self.batch(n - 1).num_rows if n else 0

    def __getitem__(self, i: int) -> tuple[np.ndarray, pa.Array]:
        k, j = divmod(i, BATCH)
        ids, mask = self.batch(k).columns
        return ids.values.to_numpy()[j * self.length : (j + 1) * self.length], mask.values.slice(j * self.length, self.length)

    def stream(self) -> Iterator[np.ndarray]:
        """The ids that are no padding, a batch at a time."""
        for k in range(self.reader.num_record_batches):
            ids, mask = self.reader.get_batch(k).columns
            yield ids.values.to_numpy()[: mask.values.true_count]


def write(docs: DataFrame, tokenizer: str, id_col: str = "doc_id", text_col: str = "text", end_id: int | None = 2, out: str | None = None, length: int = LENGTH) -> DataFrame:
    """Writes the shards and returns the manifest: shard, path, index, n_docs, n_tokens, base (ids of all shards before)."""
    spark = docs.sparkSession
    out = out or shared_path(spark, "tokens")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encode, writer, index, docs_seen = encoder(tokenizer), None, None, 0
        shard = TaskContext.get().partitionId()
        end = b"" if end_id is None else np.array([end_id], encode.dtype).tobytes()
        name = f"{out}/shard-{shard:06d}-{uuid.uuid4().hex}"
        for batch in batches:
            if writer is None:
                writer = ShardWriter(f"{name}.arrow", length, encode.dtype)
                index_file = (where := _open(f"{name}.index.arrow"))[0].open_output_stream(where[1])
                kinds = pa.schema([("doc_id", batch.schema.field(0).type), ("start", pa.int64()), ("n_tokens", pa.int64())])
                index = pa.ipc.new_file(index_file, kinds)
            for a in range(0, batch.num_rows, PART):
                part = batch.slice(a, PART)
                ids = [x + end for x in encode.column(part.column(1))]
                sizes = np.array([len(x) // encode.dtype.itemsize for x in ids], np.int64)
                starts = writer.tokens + np.cumsum(sizes) - sizes
                writer.add(ids)
                index.write_batch(pa.record_batch([part.column(0), pa.array(starts), pa.array(sizes)], schema=kinds))
            docs_seen += batch.num_rows
        if writer is not None:
            writer.close()
            index.close()
            index_file.close()
            yield pa.RecordBatch.from_pylist([{"shard": shard, "path": f"{name}.arrow", "index": f"{name}.index.arrow", "n_docs": docs_seen, "n_tokens": writer.tokens}])

    keys = [F.col(id_col).asc_nulls_first(), F.xxhash64(text_col)]
    dealt = docs.select(id_col, text_col).repartitionByRange(*keys).sortWithinPartitions(*keys)
    with small_batches(spark, PART):  # a batch is held by the JVM and by the worker
        shards = sorted(cut(dealt.mapInArrow(lean(run, f"tokenfile {tokenizer}"), "shard bigint, path string, index string, n_docs bigint, n_tokens bigint")).collect())
    rows, base = [], 0
    for r in shards:
        rows.append((*r, base))
        base += r["n_tokens"]
    manifest = spark.createDataFrame(rows, "shard bigint, path string, index string, n_docs bigint, n_tokens bigint, base bigint")
    return manifest.repartition(max(1, len(rows)), "shard") if rows else manifest


def read(manifest: DataFrame, id_kind: str = "bigint", id_col: str = "doc_id") -> DataFrame:
    """Per document, from the files: id, start, n_tokens, ids_crc32 (of the ids as little-endian 32-bit integers)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for row in batch.to_pylist():
                stream = Shard(row["path"]).stream()
                fs, path = _open(row["index"])
                held = np.zeros(0, "<u4")
                with fs.open_input_file(path) as file:
                    reader = pa.ipc.open_file(file)
                    for k in range(reader.num_record_batches):
                        part = reader.get_batch(k)
                        sums = []
                        for n in part.column(2).to_pylist():
                            while len(held) < n:
                                held = np.concatenate([held, next(stream).astype("<u4")])
                            sums.append(zlib.crc32(held[:n]))
                            held = held[n:]
                        start = pa.array(part.column(1).to_numpy() + row["base"])
                        yield pa.RecordBatch.from_arrays([part.column(0), start, part.column(2), pa.array(sums, pa.int64())], [id_col, "start", "n_tokens", "ids_crc32"])

    return manifest.mapInArrow(lean(run), f"`{id_col}` {id_kind}, start bigint, n_tokens bigint, ids_crc32 bigint")


def encode_and_check(docs: DataFrame, tokenizer: str, end_id: int = 2, **more) -> DataFrame:
    """Writes all documents and reads the files back."""
    return read(write(docs, tokenizer, end_id=end_id, **more), docs.schema["doc_id"].dataType.simpleString())


def sequences(spark: SparkSession, manifest: DataFrame) -> DataFrame:
    """The equal-length sequences: shard, sequence, ids, n_real."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for row in batch.to_pylist():
                shard = Shard(row["path"])
                for i in range(len(shard)):
                    ids, mask = shard[i]
                    yield pa.RecordBatch.from_arrays([pa.array([row["shard"]]), pa.array([i], pa.int64()), pa.array([ids.astype(np.int64)], pa.list_(pa.int64())), pa.array([mask.true_count], pa.int64())], ["shard", "sequence", "ids", "n_real"])

    return manifest.mapInArrow(lean(run), "shard bigint, sequence bigint, ids array<bigint>, n_real bigint")
