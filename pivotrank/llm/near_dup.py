"""Near-duplicate classes of documents: BagMinHash signatures, bands, verified multiset overlap.

A document is the multiset of its shingles of five words (a shorter text is one shingle). Documents of
the same word sequence are one class at once, by a hash of the sequence; only one of each goes on.
Their signatures are cut into bands; texts that agree in a band share a bucket, and candidates are
pairs of a bucket. A link is a candidate pair whose weighted Jaccard similarity, counted on the whole
shingle multisets, is at least ``similarity``. Classes are the connected components of the links.

A bucket of at most ALL_PAIRS texts gives all its pairs; no larger one does. Of a larger one a leader is
drawn: each text is compared with the leader it shares most bands with, then, in some rounds, the
buckets that still hold texts of more than one class draw new leaders, and texts of another class than
the leader's are compared with it. What is mixed after that is compared block by block: a bucket's texts
lie in blocks of bounded size, and those outside its largest class visit each block, where one pass over
the block's shingles counts what they share with all its texts at once. So every pair of a bucket that
could still join two classes is looked at, and no row is made for a pair that is not a link.

Null doc_id, null text and a text without words: no class but its own (class_id is the doc_id). Rows
that repeat a doc_id are one document. An empty table gives no rows.
"""

from __future__ import annotations

from hashlib import blake2b

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import packing as k
from .bagminhash import signatures
from .components import stars
from .memory import release, trimmed
from .session import cut, small_batches
from .text import U, batches, pair_hash, rolling, splitmix, to_bytes, words_of

SIMILARITY = 0.8
SHINGLE = 5
BANDS, ROWS = 20, 4
ALL_PAIRS = 8
BLOCK = 256
BROADCAST_PAIRS = 100_000  # two rows of 25 bytes each


def shingles(texts: list[bytes], width: int = SHINGLE):
    """For batches of texts: first text, Words, and per distinct shingle its text, 48-bit hash and count."""
    for a, b in batches(texts):
        for c in range(a, b, 1 << 15):
            words = words_of(texts[c : min(b, c + (1 << 15))])
            h = rolling(words.hash, width)
            inside = words.doc[: len(h)] == words.doc[width - 1 :] if len(h) else np.empty(0, bool)
            doc, h = words.doc[: len(h)][inside], h[inside]
            counts = np.diff(words.first)
            short = np.flatnonzero((counts > 0) & (counts < width))
            if len(short):
                whole = [np.frombuffer(blake2b(words.hash[words.first[i] : words.first[i + 1]].tobytes(), digest_size=8).digest(), U)[0] for i in short]
                doc, h = np.concatenate((doc, short)), np.concatenate((h, np.array(whole, U)))
            keys = np.sort((doc.astype(U) << U(48)) | (h >> U(16)))
            new = np.flatnonzero(np.concatenate(([True], keys[1:] != keys[:-1]))) if len(keys) else np.empty(0, np.int64)
            yield c, words, (keys[new] >> U(48)).astype(np.int64), keys[new] & U((1 << 48) - 1), np.diff(np.append(new, len(keys)))


def _signed(bands: int, rows: int, width: int):
    schema = pa.schema([("doc_id", pa.int64()), ("key", pa.binary()), ("bands", pa.list_(pa.int64()))])

    def sign(source):
        for batch in source:
            ids, texts = batch.column(0), to_bytes(batch.column(1).to_pylist())
            for c, words, owner, element, weight in shingles(texts, width):
                n = len(words.first) - 1
                bits = signatures(element, weight, owner, n, bands * rows).view(U).reshape(n, bands, rows)
                mixed = np.repeat(splitmix(np.arange(bands, dtype=U))[None], n, 0)
                for r in range(rows):
                    mixed = pair_hash(mixed, bits[:, :, r])
                empty = np.diff(words.first) == 0
                keys = [None if e else blake2b(words.hash[i:j].tobytes(), digest_size=16).digest() for e, i, j in zip(empty, words.first[:-1], words.first[1:], strict=True)]
                held = [None if e else x for e, x in zip(empty, mixed.view(np.int64).tolist(), strict=True)]
                yield pa.RecordBatch.from_arrays([ids.slice(c, n), pa.array(keys, pa.binary()), pa.array(held, pa.list_(pa.int64()))], schema=schema)

    return sign


def _sets(width: int):
    """Each text's shingle multiset as a packed set of 32-bit hashes, one for every copy of a shingle."""
    schema = pa.schema([("id", pa.int64()), ("items", pa.binary())])

    def build(source):
        for batch in source:
            texts = to_bytes(batch.column(1).to_pylist())
            for c, words, owner, element, weight in shingles(texts, width):
                n = len(words.first) - 1
                number = np.arange(weight.sum()) - np.repeat(np.cumsum(weight) - weight, weight)
                each = splitmix(np.repeat(element, weight) ^ (number.astype(U) << U(48)))
                ends = np.searchsorted(np.repeat(owner, weight), np.arange(n + 1))
                items = [k.pack(np.sort((each[i:j] >> U(32)).astype(np.uint32))) for i, j in zip(ends[:-1], ends[1:], strict=True)]
                yield pa.RecordBatch.from_arrays([batch.column(0).slice(c, n), pa.array(items, pa.binary())], schema=schema)

    return build


def _compare(least: float):
    """Over rows in order of group, salt, leader first: the members with their similarity to the leader."""

    def run(source):
        leader, own = None, None
        for batch in source:
            out = {"a": [], "b": [], "similarity": []}
            for grp, salt, lead, id, items in zip(*(batch.column(i).to_pylist() for i in range(5)), strict=True):
                items = k.unpack(items, np.uint32)
                if lead:
                    leader, own = (grp, salt), items
                elif (grp, salt) == leader:
                    common = int(k.within(items, own).sum()) if min(len(items), len(own)) >= least * max(len(items), len(own)) else 0
                    out["a"].append(grp)
                    out["b"].append(id)
                    out["similarity"].append(common / max(1, len(items) + len(own) - common))
            yield pa.RecordBatch.from_pydict(out, schema=pa.schema([("a", pa.int64()), ("b", pa.int64()), ("similarity", pa.float64())]))

    return run


def verify(pairs: DataFrame, sets: DataFrame, similarity: float, salts: int = 64) -> DataFrame:
    """The pairs (a, b) whose sets overlap enough. A leader's set goes once to each salt it has members in.

    pairs: checkpointed. Few pairs go to the sets by broadcast, many by a shuffle of both.
    """
    salted = pairs.select("a", "b", F.pmod(F.xxhash64("b"), F.lit(salts)).cast("int").alias("salt"))
    roles = salted.select(F.col("a").alias("grp"), "salt", F.lit(False).alias("lead"), F.col("b").alias("id")).unionByName(
        salted.select(F.col("a").alias("grp"), "salt", F.lit(True).alias("lead"), F.col("a").alias("id")).distinct()
    )
    if pairs.count() <= BROADCAST_PAIRS:
        roles = F.broadcast(roles)
    rows = sets.join(roles, "id").select("grp", "salt", "lead", "id", "items")
    ordered = rows.repartition("grp", "salt").sortWithinPartitions("grp", "salt", F.desc("lead"))
    return ordered.mapInArrow(trimmed(_compare(similarity)), "a long, b long, similarity double").where(F.col("similarity") >= similarity).select("a", "b")


def _blocks(least: float):
    """Over rows in order of bucket, block, held first: links between a block's texts and those sent to it."""

    def run(source):
        now, held, ready = None, [], None
        for batch in source:
            out = {"a": [], "b": []}
            for bucket, block, probe, id, c, items in zip(*(batch.column(i).to_pylist() for i in range(6)), strict=True):
                if (bucket, block) != now:
                    now, held, ready = (bucket, block), [], None
                items = k.unpack(items, np.uint32)
                if not probe:
                    held.append((id, c, items))
                    continue
                if not held:
                    continue
                if ready is None:
                    values = np.concatenate([x[2] for x in held])
                    order = np.argsort(values, kind="stable")
                    sizes = np.array([len(x[2]) for x in held])
                    ready = values[order], np.repeat(np.arange(len(held)), sizes)[order], sizes, np.array([x[1] for x in held])
                values, owner, sizes, classes = ready
                lo, hi = np.searchsorted(values, items), np.searchsorted(values, items, side="right")
                counts = hi - lo
                at = np.repeat(lo - np.cumsum(counts) + counts, counts) + np.arange(counts.sum())
                common = np.bincount(owner[at], minlength=len(held))
                for i in np.flatnonzero((common >= least * (sizes + len(items) - common)) & (classes != c)):
                    out["a"].append(held[i][0])
                    out["b"].append(id)
            yield pa.RecordBatch.from_pydict(out, schema=pa.schema([("a", pa.int64()), ("b", pa.int64())]))

    return run


def _across(left: DataFrame, sets: DataFrame, similarity: float) -> DataFrame:
    """Links between texts of different classes in the buckets (bucket, rep, c).

    A bucket's texts lie in blocks of about BLOCK; all but those of its largest class visit every block.
    """
    sizes = left.groupBy("bucket", "c").agg(F.count("*").alias("n")).groupBy("bucket").agg(F.max(F.struct("n", "c"))["c"].alias("major"), F.ceil(F.sum("n") / BLOCK).cast("int").alias("blocks"))
    rows = left.join(sizes, "bucket")
    held = rows.select("bucket", F.pmod(F.xxhash64("rep"), "blocks").cast("int").alias("block"), F.lit(False).alias("probe"), "rep", "c")
    probes = rows.where("c <> major").select("bucket", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)).alias("block"), F.lit(True).alias("probe"), "rep", "c")
    met = sets.withColumnRenamed("id", "rep").join(held.unionByName(probes), "rep").select("bucket", "block", "probe", "rep", "c", "items")
    return met.repartition("bucket", "block").sortWithinPartitions("bucket", "block", "probe").mapInArrow(trimmed(_blocks(similarity)), "a long, b long")


def classes(docs: DataFrame, similarity: float = SIMILARITY, width: int = SHINGLE, bands: int = BANDS, rows: int = ROWS, leader_rounds: int = 2) -> DataFrame:
    """(doc_id, class_id, copy_of) for every distinct doc_id: class_id is the smallest doc_id of its class.

    copy_of is the smallest doc_id with the same words. Null doc_ids have a null class.
    """
    small_batches(docs)
    docs = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text")
    signed = cut(docs.mapInArrow(trimmed(_signed(bands, rows, width)), "doc_id long, key binary, bands array<long>"))
    keyed = signed.where(F.col("doc_id").isNotNull() & F.col("key").isNotNull())
    first = keyed.groupBy("key").agg(F.min("doc_id").alias("rep"))
    by_rep = keyed.join(first.select(F.col("rep").alias("doc_id"), "key"), ["doc_id", "key"]).select(F.col("doc_id").alias("rep"), "bands")
    exploded = by_rep.select("rep", F.explode("bands").alias("bucket")).distinct()
    shared = exploded.groupBy("bucket").agg(F.count("*").alias("n")).where("n > 1")
    members = cut(exploded.join(shared, "bucket").select("bucket", "rep", (F.col("n") <= ALL_PAIRS).alias("small")))
    candidates = members.select(F.col("rep").alias("id")).distinct()
    sets = cut(docs.mapInArrow(trimmed(_sets(width)), "id long, items binary").join(candidates, "id"))

    random = lambda seed: F.min(F.struct(F.xxhash64(F.lit(seed), "bucket", "rep").alias("h"), F.col("rep").alias("leader"))).alias("pick")
    few, many = members.where("small").select("bucket", "rep"), members.where("not small").select("bucket", "rep")
    within = few.select("bucket", F.col("rep").alias("a")).join(few.select("bucket", F.col("rep").alias("b")), "bucket").where("a < b").select("a", "b")
    leaders = many.groupBy("bucket").agg(random(0)).select("bucket", "pick.leader")
    votes = many.join(leaders, "bucket").where("rep <> leader").groupBy("rep", "leader").agg(F.count("*").alias("votes"))
    best = votes.groupBy("rep").agg(F.max(F.struct("votes", "leader")).alias("best")).select(F.col("best.leader").alias("a"), F.col("rep").alias("b"))
    tested = cut(within.unionByName(best.select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b"))).distinct())
    links = stars(verify(tested, sets, similarity))
    for turn in range(1, leader_rounds + 2):
        marked = many.join(links.select(F.col("b").alias("rep"), "a"), "rep", "left").select("bucket", "rep", F.coalesce("a", "rep").alias("c"))
        mixed = marked.groupBy("bucket").agg(F.min("c").alias("lo"), F.max("c").alias("hi")).where("lo < hi").select("bucket")
        left = cut(marked.join(mixed, "bucket"))
        if left.isEmpty():
            break
        if turn > leader_rounds:
            links = stars(links.unionByName(_across(left, sets, similarity)))
            break
        leaders = left.groupBy("bucket").agg(random(turn)).select("bucket", F.col("pick.leader").alias("rep")).join(left, ["bucket", "rep"]).select("bucket", F.col("rep").alias("leader"), F.col("c").alias("lc"))
        pairs = left.join(leaders, "bucket").where("c <> lc").select(F.least("leader", "rep").alias("a"), F.greatest("leader", "rep").alias("b"))
        pairs = cut(pairs.distinct().join(tested, ["a", "b"], "left_anti"))
        tested = tested.unionByName(pairs)
        links = stars(links.unionByName(verify(pairs, sets, similarity)))
    classed = first.join(links.select(F.col("b").alias("rep"), "a"), "rep", "left").select("key", F.col("rep").alias("copy_of"), F.coalesce("a", "rep").alias("class_id"))
    out = signed.select("doc_id", "key").join(classed, "key", "left")
    own = out.select("doc_id", F.coalesce("class_id", "doc_id").alias("class_id"), F.coalesce("copy_of", "doc_id").alias("copy_of"))
    release()
    return own.groupBy("doc_id").agg(F.min("class_id").alias("class_id"), F.min("copy_of").alias("copy_of"))
