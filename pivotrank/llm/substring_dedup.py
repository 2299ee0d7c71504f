"""Removal of long repeats between documents, found by fixed-block anchors.

Every document is cut into non-overlapping blocks of half a window's words. The blocks form the
reference index; the rolling windows of a block's width, from every place of every document, probe
it. A window that repeats contains a whole block of either document, so a block without a second
occurrence rules all windows around it out. Around the blocks that are hit, hits are extended: each
full window there is compared with the others of the same words, and adjoining ones that occur in
an earlier document merge into maximal repeats.

Shape of the job: documents are dealt, by a hash of id and text, into parts of bounded bytes, by one
exchange that all three passes share; rows without an id, or of one id, spread by their texts. Each part sends every hash at most twice (blocks) or once (windows), so
neither a group of copies nor a passage that a third of all documents share fills one task.

Null text: no words. Null doc_id: counts as larger than any other. Rows that repeat a doc_id do not
remove each other. Fewer words than a window: nothing is removed. An empty table gives no rows.
Columns other than id and text come back only with ``carry=True``, in the struct column ``rest``.
"""

from __future__ import annotations

from itertools import compress

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.pandas.types import to_arrow_schema
from pyspark.sql.types import StringType, StructField, StructType

from . import packing as k
from .memory import trimmed_group, trimmed_pair
from .session import part_of, parts_for, small_batches, text_bytes
from .text import U, batches, pair_hash, rolling, splitmix, to_bytes, windows, words_of

WINDOW = 50
PART_BYTES = 4 << 20
_LAST = np.iinfo(np.int64).max


def _ids(table: pa.Table) -> np.ndarray:
    return table["doc_id"].cast(pa.int64()).fill_null(_LAST).to_numpy()


def _block_places(words, block: int) -> np.ndarray:
    """Word numbers at which a whole block begins."""
    counts = np.diff(words.first) // block
    step = np.arange(counts.sum()) - np.repeat(np.cumsum(counts) - counts, counts)
    return np.repeat(words.first[:-1], counts) + step * block


def _probe(table: pa.Table, block: int, buckets: int) -> pa.Table:
    """The part's rolling block hashes, by bucket, and which of them are of its own blocks."""
    texts, probes, own = to_bytes(table["text"].to_pylist()), [], []
    for a, b in batches(texts):
        words = words_of(texts[a:b])
        h = rolling(words.hash, block)
        own.append(h[_block_places(words, block)])
        probes.append(h[words.doc[: len(h)] == words.doc[block - 1 :]] if len(h) else h)
    probes = k.at_most_two(np.sort(k.bucketed(np.concatenate(probes), buckets))) if probes else np.empty(0, U)
    own = np.unique(k.bucketed(np.concatenate(own), buckets)) if own else np.empty(0, U)
    part, rows = table["part"][0].as_py(), {"bucket": [], "part": [], "probes": [], "own": []}
    mine = dict(k.slices(own))
    for bucket, at in k.slices(probes):
        rows["bucket"].append(bucket)
        rows["part"].append(part)
        rows["probes"].append(k.pack(probes[at].astype(np.uint32)))
        rows["own"].append(k.pack(own[mine[bucket]].astype(np.uint32)) if bucket in mine else b"")
    return pa.table(rows, schema=pa.schema([("bucket", pa.int32()), ("part", pa.int32()), ("probes", pa.binary()), ("own", pa.binary())]))


def _hit(table: pa.Table) -> pa.Table:
    """For each part, which of its blocks occur at another place."""
    probes = [k.unpack(x.as_py(), np.uint32) for x in table["probes"]]
    live = k.twice(np.sort(np.concatenate(probes)))
    rows = {"part": [], "bucket": [], "live": []}
    for part, bucket, own in zip(table["part"].to_pylist(), table["bucket"].to_pylist(), table["own"], strict=True):
        own = k.unpack(own.as_py(), np.uint32)
        own = own[k.within(own, live)]
        if len(own):
            rows["part"].append(part)
            rows["bucket"].append(bucket)
            rows["live"].append(k.pack(own))
    return pa.table(rows, schema=pa.schema([("part", pa.int32()), ("bucket", pa.int32()), ("live", pa.binary())]))


def _window_hashes(words, width: int) -> tuple[np.ndarray, np.ndarray]:
    """Starts of the windows, and 64-bit hashes."""
    return windows(words, width)


def _second(words, at: np.ndarray, width: int) -> np.ndarray:
    """Independent 32-bit hashes of the windows that start at ``at``."""
    return (rolling(splitmix(words.hash ^ U(0x5851F42D4C957F2D)), width)[at] >> U(32)).astype(np.uint32)


def _extend(docs: pa.Table, hits: pa.Table, width: int, block: int, buckets: int) -> pa.Table:
    """The part's windows around hit blocks, each once, with the smallest doc_id, by bucket."""
    schema = pa.schema([("bucket", pa.int32()), ("part", pa.int32()), ("h", pa.binary()), ("second", pa.binary()), ("doc", pa.binary())])
    if not len(docs) or not len(hits):
        return schema.empty_table()
    live = np.sort(np.concatenate([(U(b) << U(32)) | k.unpack(x.as_py(), np.uint32) for b, x in zip(hits["bucket"].to_pylist(), hits["live"], strict=True)]))
    texts, ids, found = to_bytes(docs["text"].to_pylist()), _ids(docs), []
    for a, b in batches(texts):
        words = words_of(texts[a:b])
        places = _block_places(words, block)
        if not len(places):
            continue
        h = rolling(words.hash, block)
        places = places[k.within(k.bucketed(h[places], buckets), live)]
        if not len(places):
            continue
        n = len(words.hash)
        around = np.zeros(n + 2, np.int32)
        np.add.at(around, np.maximum(places - (width - block), words.first[words.doc[places]]), 1)
        np.add.at(around, places + 1, -1)
        at, h = _window_hashes(words, width)
        near = np.cumsum(around)[at] > 0
        at, h = at[near], h[near]
        found.append((h, _second(words, at, width), ids[a:b][words.doc[at]]))
    if not found:
        return schema.empty_table()
    h, second, doc = (np.concatenate(x) for x in zip(*found, strict=True))
    order = np.lexsort((doc, second, h))
    h, second, doc = h[order], second[order], doc[order]
    once = np.concatenate(([True], (h[1:] != h[:-1]) | (second[1:] != second[:-1])))
    h, second, doc = h[once], second[once], doc[once]
    part, rows = docs["part"][0].as_py(), {"bucket": [], "part": [], "h": [], "second": [], "doc": []}
    for bucket, at in k.slices(((h >> U(32)) * U(buckets)) & U(0xFFFFFFFF00000000)):
        rows["bucket"].append(bucket)
        rows["part"].append(part)
        rows["h"].append(k.pack(h[at]))
        rows["second"].append(second[at].tobytes())
        rows["doc"].append(k.pack_any(doc[at]))
    return pa.table(rows, schema=schema)


def _earliest(table: pa.Table) -> pa.Table:
    """For each part, its windows that another part has in a smaller doc_id, with that doc_id."""
    held = [(k.unpack(h.as_py(), np.uint64), np.frombuffer(s.as_py(), np.uint32), k.unpack_any(d.as_py(), np.int64)) for h, s, d in zip(table["h"], table["second"], table["doc"], strict=True)]
    which = np.repeat(np.arange(len(held)), [len(x[0]) for x in held])
    h, second, doc = (np.concatenate(x) for x in zip(*held, strict=True))
    order = np.lexsort((doc, second, h))
    h, second, doc, which = h[order], second[order], doc[order], which[order]
    new = np.concatenate(([True], (h[1:] != h[:-1]) | (second[1:] != second[:-1])))
    least = doc[np.flatnonzero(new)][np.cumsum(new) - 1]
    late = least < doc
    h, second, least, which = h[late], second[late], least[late], which[late]
    order = np.argsort(which, kind="stable")
    h, second, least, which = h[order], second[order], least[order], which[order]
    ends, rows = np.searchsorted(which, np.arange(len(held) + 1)), {"part": [], "h": [], "second": [], "doc": []}
    for i, part in enumerate(table["part"].to_pylist()):
        if ends[i] < ends[i + 1]:
            at = slice(ends[i], ends[i + 1])
            rows["part"].append(part)
            rows["h"].append(k.pack(h[at]))
            rows["second"].append(second[at].tobytes())
            rows["doc"].append(k.pack_any(least[at]))
    return pa.table(rows, schema=pa.schema([("part", pa.int32()), ("h", pa.binary()), ("second", pa.binary()), ("doc", pa.binary())]))


def _repeated(parts: list, ids: np.ndarray, replies: pa.Table, width: int) -> list[np.ndarray]:
    """For each batch of words, the starts of the windows that an earlier document has."""
    hashed = [_window_hashes(words, width) for _, _, words in parts]
    every = np.sort(np.concatenate([h for _, h in hashed])) if hashed else np.empty(0, U)
    local = k.twice(every)
    del every
    if len(replies):
        there = [np.concatenate(x) for x in zip(*((k.unpack(h.as_py(), np.uint64), np.frombuffer(s.as_py(), np.uint32), k.unpack_any(d.as_py(), np.int64)) for h, s, d in zip(replies["h"], replies["second"], replies["doc"], strict=True)), strict=True)]
    else:
        there = [np.empty(0, U), np.empty(0, np.uint32), np.empty(0, np.int64)]
    held = np.union1d(local, there[0])
    rows = []
    for i, ((a, _, words), (at, h)) in enumerate(zip(parts, hashed, strict=True)):
        near = k.within(h, held)
        if near.any():
            at = at[near]
            rows.append((h[near], _second(words, at, width), ids[a + words.doc[at]], np.full(len(at), i), at))
    out = [np.empty(0, np.int64) for _ in parts]
    if not rows:
        return out
    h, second, doc, batch, at = (np.concatenate(x) for x in zip(*rows, strict=True))
    h, second, doc = (np.concatenate(x) for x in zip((h, second, doc), there, strict=True))
    order = np.lexsort((doc, second, h))
    h, second, doc = h[order], second[order], doc[order]
    new = np.concatenate(([True], (h[1:] != h[:-1]) | (second[1:] != second[:-1])))
    late = doc[np.flatnonzero(new)][np.cumsum(new) - 1] < doc
    own = order[late & (order < len(at))]
    for i in range(len(parts)):
        out[i] = np.sort(at[own[batch[own] == i]])
    return out


def _remove(docs: pa.Table, replies: pa.Table, width: int, schema: pa.Schema) -> pa.Table:
    if not len(docs):
        return schema.empty_table()
    texts, ids = to_bytes(docs["text"].to_pylist()), _ids(docs)
    parts = [(a, b, words_of(texts[a:b])) for a, b in batches(texts)]
    n_words, n_removed, kept, spans = [], [], [], []
    for (a, b, words), starts in zip(parts, _repeated(parts, ids, replies, width), strict=True):
        cover = np.zeros(len(words.hash) + 1, np.int64)
        np.add.at(cover, starts, 1)
        np.add.at(cover, starts + width, -1)
        gone = np.cumsum(cover[:-1]) > 0
        lost = np.concatenate(([0], np.cumsum(gone)))[words.first]
        for i, (s, e) in enumerate(zip(words.first[:-1], words.first[1:], strict=True)):
            own = texts[a + i].split()
            n_words.append(len(own))
            n_removed.append(int(lost[i + 1] - lost[i]))
            if n_removed[-1]:
                cut = gone[s:e]
                kept.append(b" ".join(compress(own, ~cut)))
                edge = np.flatnonzero(np.diff(np.concatenate(([0], cut.view(np.int8), [0]))))
                spans.append([{"first": int(x), "words": int(y - x)} for x, y in zip(edge[0::2], edge[1::2], strict=True)])
            else:
                kept.append(b" ".join(own))
                spans.append([])
    columns = {"doc_id": docs["doc_id"], "n_words": n_words, "n_removed": n_removed, "kept": pa.array(kept, pa.binary()).cast(pa.string()), "spans": spans}
    if "rest" in schema.names:
        columns |= {"text": docs["text"], "rest": docs["rest"]}
    return pa.table(columns, schema=schema)


def remove_repeats(docs: DataFrame, window: int = WINDOW, part_bytes: int = PART_BYTES, carry: bool = False) -> DataFrame:
    """Each document without the words that lie in a ``window`` of words which an earlier document has.

    docs: doc_id long, text string. Returns for every row: doc_id, n_words, n_removed, kept (the
    words that stay, joined by a space), spans (first word and length of each maximal removed
    repeat); with ``carry`` also text and rest, a struct of all other columns. ``window`` is even.
    """
    if window % 2:
        raise ValueError("the window must have an even number of words")
    block = window // 2
    small_batches(docs)
    parts = parts_for(text_bytes(docs), part_bytes)
    columns = [part_of(parts, "doc_id", "text").alias("part"), F.col("doc_id").cast("long").alias("doc_id"), F.col("text")]
    if carry:
        columns.append(F.struct(F.lit(True).alias("_row"), *[F.col(f"`{c}`") for c in docs.columns if c not in ("doc_id", "text")]).alias("rest"))
    dealt = docs.select(*columns)
    by = dealt.groupBy("part")
    probes = by.applyInArrow(trimmed_group(lambda t: _probe(t, block, parts)), "bucket int, part int, probes binary, own binary")
    hits = probes.groupBy("bucket").applyInArrow(trimmed_group(_hit), "part int, bucket int, live binary")
    near = by.cogroup(hits.groupBy("part")).applyInArrow(trimmed_pair(lambda a, b: _extend(a, b, window, block, parts)), "bucket int, part int, h binary, second binary, doc binary")
    replies = near.groupBy("bucket").applyInArrow(trimmed_group(_earliest), "part int, h binary, second binary, doc binary")
    kind = StructType.fromDDL("doc_id long, n_words long, n_removed long, kept string, spans array<struct<first: long, words: long>>")
    if carry:
        kind = StructType([*kind.fields, StructField("text", StringType()), dealt.schema["rest"]])
    schema = to_arrow_schema(kind)
    return by.cogroup(replies.groupBy("part")).applyInArrow(trimmed_pair(lambda a, b: _remove(a, b, window, schema)), kind)
