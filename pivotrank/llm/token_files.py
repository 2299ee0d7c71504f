"""Token ids in compressed binary files, in order of doc_id.

Documents are dealt by ranges of doc_id and sorted; a task encodes its texts and closes a file after
every ``file_ids`` ids. Files lie in one folder, on any store that Spark can write, and are put there
whole, by renaming; a task that runs again puts the same files. A name says which part of the documents
a file belongs to, how many ids of the part come before it and how many it has.

A file, all little-endian: a head (magic, version, documents, blocks: 32 bits each; ids: 64 bits), an
entry for each document (doc_id, ids: 64 bits each), an entry for each block (ids, bytes, bytes of the
largest id, crc32 of its ids as unsigned 32-bit integers: 32 bits each), then the blocks. Blocks have
``block_ids`` ids of up to 32 bits. Each is coded on its own by the context-mixing range coder of
``java/TokenFiles.java`` and checked against its crc32 on reading, so a damaged block is found.

A text of a byte-level tokenizer with the usual pattern can be cut before every space that follows no
other white space, as pieces never run over such a place, and a segment again before marks that follow a Latin letter; a
worker encodes each distinct part once, as long as its bounded cache holds it. Texts with other spaces, with one of the tokenizer's special strings, or of other
tokenizers are encoded whole.

Null texts are empty; every document ends with ``end_id``. Null doc_ids come first; ties in doc_id are
in order of the text. An empty table gives an empty folder.
"""

from __future__ import annotations

import json
import os
import re
import zlib
from array import array

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .jvm import register
from .memory import trimmed
from .session import cut, parts_for, small_batches, text_bytes

_NULL = np.iinfo(np.int64).min
BLOCK_IDS, FILE_IDS, PART_BYTES = 1 << 17, 2_000_000, 32 << 20
CACHE_BYTES, SLICE_BYTES, LONG, JOINED = 192 << 20, 4 << 20, 64, 16
_FUNCTIONS = {
    "token_file_pack": ("Pack", "binary"),
    "token_file_unpack": ("Unpack", "array<struct<doc_id: bigint, before: bigint, n_tokens: bigint, ids: binary>>"),
    "token_file_put": ("Put", "bigint"),
}
_LOOSE = r"[\s\v\x1c-\x1f\x{85}\pZ] "  # all white space of Unicode, and a space
_MARKS = "!\"#$%&()*+,-./:;<=>?@[\\]^_`{|}~"  # of ASCII, but not the apostrophe, which may open a piece with letters
_LETTER = np.zeros(256, bool)
_LETTER[[*range(65, 91), *range(97, 123)]] = True


class Encoder:
    """Ids of texts with a tokenizer of the tokenizers library, by distinct segments."""

    def __init__(self, spec: str):
        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        from tokenizers import Tokenizer

        self.tool = Tokenizer.from_str(spec)
        cut = json.loads(spec).get("pre_tokenizer") or {}
        self.segmented = cut.get("type") == "ByteLevel" and cut.get("use_regex", True) and not cut.get("add_prefix_space") and not json.loads(spec).get("normalizer")
        special = [t.content for t in self.tool.get_added_tokens_decoder().values()]
        self.segmented = self.segmented and not any(" " in t for t in special)
        vocab = self.tool.get_vocab()
        self.opens = np.zeros(max(vocab.values(), default=0) + 1, bool)  # ids of pieces that begin with a space
        self.opens[[i for piece, i in vocab.items() if piece.startswith("\u0120")]] = True
        self.uncut = "|".join([_LOOSE, *map(re.escape, special)])  # what a text has that is encoded whole
        self.held: dict[str, bytes] = {}  # segments without the space before them
        self.size = 0

    def _ids(self, texts: list[str]) -> list[bytes]:
        return [array("I", e.ids).tobytes() for e in self.tool.encode_batch_fast(texts, add_special_tokens=False)]

    def _segments(self, segments: list[str]) -> list[bytes]:
        """Ids of segments with the space before them, several in one text: a piece that begins with a space opens the next."""
        out: list[bytes | None] = [None] * len(segments)
        some = [i for i, s in enumerate(segments) if s and len(s) <= LONG and not s[-1].isspace()]
        for a in range(0, len(some), 256 * JOINED):
            own = some[a : a + 256 * JOINED]
            groups = [own[b : b + JOINED] for b in range(0, len(own), JOINED)]
            flat, ends = array("I"), []
            for e in self.tool.encode_batch_fast([" " + " ".join([segments[i] for i in g]) for g in groups], add_special_tokens=False):
                flat.extend(e.ids)
                ends.append(len(flat))
            at = np.flatnonzero(self.opens[np.frombuffer(flat, np.uint32)])
            stops, raw = np.append(at[1:], len(flat)), flat.tobytes()
            bounds = np.searchsorted(at, [0, *ends])
            for g, begin, end, lo, hi in zip(groups, [0, *ends], ends, bounds.tolist(), bounds[1:].tolist(), strict=False):
                if hi - lo == len(g) and at[lo] == begin and stops[hi - 1] == end:
                    for i, x, y in zip(g, (at[lo:hi] * 4).tolist(), (stops[lo:hi] * 4).tolist(), strict=True):
                        out[i] = raw[x:y]
        rest = [i for i, x in enumerate(out) if x is None]
        for i, x in zip(rest, self._ids([" " + segments[i] for i in rest]), strict=True):
            out[i] = x
        return out

    def _known(self, segments: list[str]) -> list[bytes]:
        """The same by way of the cache, for distinct segments."""
        if self.size > CACHE_BYTES:
            self.held.clear()
            self.size = 0
        got = list(map(self.held.get, segments))
        lacks = [i for i, x in enumerate(got) if x is None]
        new = [segments[i] for i in lacks]
        made = self._segments(new)
        for i, x in zip(lacks, made, strict=True):
            got[i] = x
        self.held.update((s, x) for s, x in zip(new, made, strict=True) if len(s) <= LONG)
        self.size += 200 * len(new)  # about what an entry takes
        return got

    def _pieces(self, segments: pa.Array) -> pa.Array:
        """Ids of distinct segments as a column: marks that follow a Latin letter are parted from it, as no piece has both, and stems made distinct."""
        stems = pc.ascii_rtrim(segments, characters=_MARKS)
        sizes = pc.binary_length(stems).to_numpy()
        marks = pc.binary_length(segments).to_numpy() - sizes
        raw = np.concatenate((np.zeros(2, np.uint8), np.frombuffer(stems.buffers()[2] or b"", np.uint8)))
        ends = np.cumsum(sizes, dtype=np.int64)
        last, before = raw[ends + 1], raw[ends]
        cut = (marks > 0) & (sizes > 0) & (_LETTER[last] | (before >= 0xC3) & (before <= 0xC8) & (last >= 0x80) & ((before != 0xC3) | (last & 0xDF != 0x97)))
        keys = pc.if_else(pa.array(cut), stems, segments).dictionary_encode()
        tails = [s[-n:] for s, n in zip(_strings(segments.filter(pa.array(cut))), marks[cut].tolist(), strict=True)]
        kinds = dict(zip(dict.fromkeys(tails), range(len(tails)), strict=False))
        known = self._known(_strings(keys.dictionary))
        parts = pa.array(known + self._ids(list(kinds)) + [b""], pa.large_binary())
        order = np.full((len(segments), 2), len(parts) - 1, np.int32)
        order[:, 0] = keys.indices.to_numpy()
        order[cut, 1] = [len(known) + kinds[t] for t in tails]
        placed = parts.take(pa.array(order.ravel()))
        _, at, data = placed.buffers()
        at = np.frombuffer(at, np.int64)[: 2 * len(segments) + 1 : 2].copy()
        return pa.LargeBinaryArray.from_buffers(pa.large_binary(), len(segments), [None, pa.py_buffer(at), data])

    def encode(self, texts: pa.Array, end_id: int) -> tuple[memoryview, np.ndarray]:
        """Ids of all texts one after another, each with the end id, as little-endian unsigned 32-bit integers; and how many each has.

        Texts are cut, and their distinct segments found and put back in place, by Arrow; Python meets each distinct segment once.
        """
        whole = pc.match_substring_regex(texts, self.uncut) if self.segmented else pa.array([True] * len(texts))
        lists = pc.split_pattern(pc.if_else(whole, pa.scalar("", texts.type), texts), " ")
        firsts = pc.if_else(whole, texts, pc.list_element(lists, 0))
        coded = lists.flatten().dictionary_encode()
        others = self._ids(_strings(firsts)) + [array("I", [end_id]).tobytes()]
        pieces = pa.concat_arrays([self._pieces(coded.dictionary), pa.array(others, pa.large_binary())])
        sizes = pc.list_value_length(lists).to_numpy().astype(np.int64)
        ends = np.cumsum(sizes + 1) - 1  # where the end ids come
        order, inner = np.full(len(coded) + len(texts), len(pieces) - 1, np.int32), np.ones(len(coded) + len(texts), bool)
        inner[ends] = False
        order[inner] = coded.indices.to_numpy()
        order[ends - sizes] = len(coded.dictionary) + np.arange(len(texts))
        placed = pieces.take(pa.array(order))
        _, at, data = placed.buffers()
        at = np.frombuffer(at, np.int64)[: len(order) + 1]
        return memoryview(data)[: at[-1]], np.diff(at[ends + 1], prepend=0) // 4


def _strings(column: pa.Array) -> list[str]:
    return column.to_numpy(zero_copy_only=False).tolist()


def _slices(texts: pa.Array, size: int):
    """Parts of a column of about ``size`` bytes each; a longer text comes alone."""
    ends, a = np.cumsum(pc.binary_length(texts).to_numpy(zero_copy_only=False)), 0
    while a < len(texts):
        b = max(a + 1, int(np.searchsorted(ends, size + (ends[a - 1] if a else 0), "right")))
        yield a, texts.slice(a, b - a)
        a = b


_encoders: dict[int, Encoder] = {}  # of a Python worker, which outlives a task
_FILE = pa.schema([("part", pa.int32()), ("before", pa.int64()), ("documents", pa.int64()), ("n_ids", pa.int64()), ("docs", pa.binary()), ("ids", pa.binary())])


def _encoder(tokenizer: str) -> Encoder:
    key = zlib.crc32(tokenizer.encode())
    if key not in _encoders:
        _encoders.clear()
        _encoders[key] = Encoder(tokenizer)
    return _encoders[key]


def write_files(docs: DataFrame, folder: str, tokenizer: str, end_id: int = 0, file_ids: int = FILE_IDS, block_ids: int = BLOCK_IDS, part_bytes: int = PART_BYTES) -> DataFrame:
    """Writes the files into a new folder; returns a row for each (path, part, before, documents, n_ids, bytes).

    tokenizer: a tokenizer file's content. Raises ValueError if the folder exists.
    """
    spark = docs.sparkSession
    target = spark._jvm.org.apache.hadoop.fs.Path(folder)
    store = target.getFileSystem(spark._jsc.hadoopConfiguration())
    if store.exists(target):
        raise ValueError(f"{folder} exists")
    store.mkdirs(target)

    def pack(source):
        tool = _encoder(tokenizer)
        keys, counts, parts, size, before, part = [], [], [], 0, 0, None

        def close():
            nonlocal keys, counts, parts, size, before
            own = np.empty((len(keys), 2), np.int64)
            own[:, 0], own[:, 1] = keys, counts
            row = [[part], [before], [len(keys)], [size], [own.tobytes()], [b"".join(parts)]]
            out = pa.RecordBatch.from_arrays([pa.array(x, f.type) for x, f in zip(row, _FILE, strict=True)], schema=_FILE)
            keys, counts, parts, size, before = [], [], [], 0, before + size
            return out

        for batch in source:
            part = batch.column(2)[0].as_py() if len(batch) else part
            ids = batch.column(0).fill_null(_NULL).to_pylist()
            for a, texts in _slices(batch.column(1).fill_null(""), SLICE_BYTES):
                data, sizes = tool.encode(texts, end_id)
                begin = end = 0
                for key, n in zip(ids[a : a + len(texts)], sizes.tolist(), strict=True):
                    keys.append(key)
                    counts.append(n)
                    size += n
                    end += 4 * n
                    if size >= file_ids:
                        parts.append(data[begin:end])
                        begin = end
                        yield close()
                parts.append(data[begin:end])
        if keys:
            yield close()

    register(spark, "TokenFiles", _FUNCTIONS)
    small_batches(docs)
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text")
    parts = parts_for(text_bytes(rows), part_bytes)
    dealt = rows.repartitionByRange(parts, "doc_id").withColumn("part", F.spark_partition_id()).sortWithinPartitions("doc_id", "text")
    packed = dealt.mapInArrow(trimmed(pack), "part int, before long, documents long, n_ids long, docs binary, ids binary")
    name = F.format_string("%s/part-%08d-%015d-%d.tids", F.lit(folder), "part", "before", "n_ids")
    put = packed.select(name.alias("path"), "part", "before", "documents", "n_ids", F.call_function("token_file_pack", "docs", "ids", F.lit(block_ids)).alias("content"))
    return cut(put.select("path", "part", "before", "documents", "n_ids", F.call_function("token_file_put", "path", "content").alias("bytes")))


def read_files(spark: SparkSession, folder: str) -> DataFrame:
    """(doc_id, start, n_tokens, ids) of every document of a folder of files.

    start: ids of all documents before it; ids: binary, little-endian unsigned 32-bit integers.
    """
    register(spark, "TokenFiles", _FUNCTIONS)
    files = spark.read.format("binaryFile").schema("path string, modificationTime timestamp, length long, content binary").option("pathGlobFilter", "*.tids").load(folder)
    said = lambda group: F.regexp_extract("path", r"part-(\d+)-(\d+)-(\d+)\.tids$", group).cast("long")
    sizes = files.select(said(1).alias("part"), said(3).alias("n")).groupBy("part").agg(F.sum("n").alias("n")).collect()  # a row for each part
    starts, total = [], 0
    for r in sorted(sizes, key=lambda r: r["part"]):
        starts.append((r["part"], total))
        total += r["n"]
    parts = spark.createDataFrame(starts, "part long, start long")
    placed = files.select(said(1).alias("part"), said(2).alias("before"), "content").join(F.broadcast(parts), "part")
    held = placed.select((F.col("start") + F.col("before")).alias("start"), F.explode(F.call_function("token_file_unpack", "content")).alias("d"))
    return held.select("d.doc_id", (F.col("start") + F.col("d.before")).alias("start"), "d.n_tokens", "d.ids")


def ids_array(ids: str) -> Column:
    """array<long> of an id column."""

    @F.pandas_udf("array<long>")
    def unpacked(values):
        return values.map(lambda x: np.frombuffer(x, np.uint32).astype(np.int64))

    return unpacked(F.col(ids))
