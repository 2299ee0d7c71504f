"""Documents that contain benchmark passages, verbatim or reworded, by latent semantic retrieval.

Words (runs of letters, digits and non-ASCII characters, A-Z lower-cased) hash into ``2 ** bits``
features. Passages are TF-IDF vectors; the inverse document frequencies are counted over all documents.
A randomised SVD of one pass gives the latent space: each task adds up its passages' share of their
Gram matrix times a random orthonormal basis, and the sum's Nystrom form gives the right singular
vectors; ``rounds`` passes of subspace iteration may come before. Latent axes are scaled to equal
variance, so the few that only tell languages apart do not outweigh the rest. What a feature has outside
those axes, nearly all of a rare word, is projected at random into the same coordinates, weighed as REST
times the last axis, so that words too rare for an axis still tell passages apart.
Every passage of every document counts in the basis, and every one is searched.

Search: a document's words become running sums of latent vectors, from which windows of several
lengths, one every ``stride`` words, follow as differences. Each benchmark item is compared by cosine
with the windows of the length nearest above its own, and with those so much longer that one holds
the whole item wherever it begins. Beside this route, every run of ANCHOR words of an item (all its
words, if it has fewer) is looked up in the documents, so that no verbatim passage depends on a
cosine. Candidates above ``cosine`` and the places of anchors are checked exactly:
the longest common subsequence of the item's words with the words around the window, as a share of
the item, and the same for its last quarter, which stands for the answer. A leak has a share of at
least ``lcs`` with an answer share of at least ``answer``, or a share of at least ``verbatim``. Of an
item's places in a document the best leaking one is given, and its cosine is that of the place found.

Items are compared in blocks of ``block`` items; an item set of any size takes more blocks, not more
memory in a task. Null texts and texts without words have no leaks; items without words match
nothing. Items are as given: equal ones each count. Empty tables give no leaks.
"""

from __future__ import annotations

from collections import Counter
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .memory import release, trimmed
from .session import small_batches
from .text import U, batches, rolling, to_bytes, words_of

BITS, DIMS, OVER = 14, 128, 16
PASSAGE, STRIDE = 64, 8
WIDTHS = (8, 16, 24, 32, 40, 48, 64, 72)
ANCHOR = 8
REST = 0.5
COSINE, LCS, ANSWER, VERBATIM = 0.5, 0.6, 0.5, 0.8
GROUP, SUMS = 24, 256
_CUT = np.ones(256, bool)
_CUT[[*range(48, 58), *range(65, 91), *range(97, 123), *range(128, 256)]] = False


def _words(texts: list[bytes]):
    return words_of(texts, lower=True, space=_CUT)


def _features(hashes: np.ndarray, bits: int) -> np.ndarray:
    return (hashes >> U(64 - bits)).astype(np.int32)


def inverse_frequencies(docs: DataFrame, bits: int) -> np.ndarray:
    """log((1 + documents) / (1 + documents with the feature)), over all documents."""
    size, piece = 1 << bits, 2048

    def count(source):
        held, n = np.zeros(size, np.int64), 0
        for batch in source:
            texts = to_bytes(batch.column(0).to_pylist())
            for a, b in batches(texts):
                words = _words(texts[a:b])
                feature, docs_ = _features(words.hash, bits), b - a
                for c in range(0, docs_, 1024):  # presence by document, a thousand at a time
                    i, j = words.first[c], words.first[min(c + 1024, docs_)]
                    seen = np.zeros((min(c + 1024, docs_) - c, size), bool)
                    seen[words.doc[i:j] - c, feature[i:j]] = True
                    held += seen.sum(0)
                n += docs_
        blocks = held.reshape(-1, piece)
        yield pa.RecordBatch.from_pydict({"block": pa.array(range(len(blocks)), pa.int32()), "n": pa.array([n] * len(blocks), pa.int64()), "counts": pa.array([b.tobytes() for b in blocks], pa.binary())})

    n, held = _summed(docs.select("text").mapInArrow(trimmed(count), "block int, n long, counts binary"), np.int64, size // piece, piece)
    return np.log((1 + n) / (1 + held.ravel()))


def _summed(partial: DataFrame, dtype, blocks: int, piece: int) -> tuple[int, np.ndarray]:
    """Tasks' blocks of numbers added up block by block; only the sums go to the driver."""

    def add(table: pa.Table) -> pa.Table:
        total = sum((np.frombuffer(x.as_py(), dtype) for x in table["counts"]), np.zeros(piece, dtype))
        return pa.table({"block": table["block"][:1], "n": pa.array([sum(table["n"].to_pylist())], pa.int64()), "counts": pa.array([total.astype(dtype).tobytes()], pa.binary())})

    out, n, kind = np.zeros((blocks, piece), dtype), 0, "block int, n long, counts binary"
    some = partial.groupBy("block", F.pmod(F.spark_partition_id(), F.lit(64))).applyInArrow(add, kind)  # tasks are added up in 64 lots first
    for r in some.groupBy("block").applyInArrow(add, kind).collect():
        out[r["block"]], n = np.frombuffer(r["counts"], dtype), r["n"]
    return n, out


def _passages(hashes: np.ndarray, doc: np.ndarray, first: np.ndarray, idf: np.ndarray, bits: int):
    """Sparse rows of unit length: passage number, feature and value of each entry."""
    place = np.arange(len(hashes)) - first[doc]
    new = (place % PASSAGE == 0).astype(np.int64)
    passage = np.cumsum(new) - 1
    keys, times = np.unique(passage * (1 << bits) + _features(hashes, bits), return_counts=True)
    passage, feature = keys >> bits, (keys & ((1 << bits) - 1)).astype(np.int32)
    value = times * idf[feature]
    norm = np.sqrt(np.bincount(passage, weights=value * value))
    return passage, feature, value / np.maximum(norm, 1e-12)[passage]


def _gram(docs: DataFrame, basis: np.ndarray, idf: np.ndarray, bits: int) -> np.ndarray:
    """The passages' Gram matrix times a basis, added up over the tasks.

    A few passages at a time are made dense over the features they hold, small enough for the cache.
    """
    size, dims = basis.shape
    rows_a_block = 512

    def share(source):
        total = np.zeros((size, dims), np.float32)
        for batch in source:
            texts = to_bytes(batch.column(0).to_pylist())
            for a, b in batches(texts, 1 << 18):
                words = _words(texts[a:b])
                if not len(words.hash):
                    continue
                passage, feature, value = _passages(words.hash, words.doc, words.first, idf, bits)
                ends = np.searchsorted(passage, np.arange(0, passage[-1] + 1 + GROUP, GROUP))
                for k, (i, j) in enumerate(zip(ends[:-1], ends[1:], strict=True)):
                    held, at = np.unique(feature[i:j], return_inverse=True)
                    dense = np.zeros((GROUP, len(held)), np.float32)
                    dense[passage[i:j] - k * GROUP, at] = value[i:j]
                    total[held] += dense.T @ (dense @ basis.take(held, 0))
        blocks = total.reshape(-1, rows_a_block * dims)
        yield pa.RecordBatch.from_pydict({"block": pa.array(range(len(blocks)), pa.int32()), "n": pa.array([0] * len(blocks), pa.int64()), "counts": pa.array([b.tobytes() for b in blocks], pa.binary())})

    few = docs.select("text").coalesce(2 * docs.sparkSession.sparkContext.defaultParallelism)  # a task ships the whole matrix, however few its rows
    _, out = _summed(few.mapInArrow(trimmed(share), "block int, n long, counts binary"), np.float32, size // rows_a_block, rows_a_block * dims)
    return out.reshape(size, dims).astype(np.float64)


def _nystrom(image: np.ndarray, basis: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Eigenvalues, largest first, and eigenvectors of G, from G times an orthonormal basis.

    A small multiple of the identity is added to G and taken off the eigenvalues, as the core may lack full rank.
    """
    shift = 1e-6 * max(float(np.linalg.norm(image, 2)), 1e-9)
    image = image + shift * basis
    core, turn = np.linalg.eigh((basis.T @ image + image.T @ basis) / 2)
    vectors, values, _ = np.linalg.svd(image @ (turn / np.sqrt(np.maximum(core, shift / 2))), full_matrices=False)
    return np.maximum(values**2 - shift, 0), vectors


@dataclass
class LatentSpace:
    table: np.ndarray  # features by latent axes: idf times right singular vectors, scaled; a last row of zeros
    bits: int

    def vectors(self, hashes: np.ndarray) -> np.ndarray:
        return self.table[_features(hashes, self.bits)]


def fit(docs: DataFrame, bits: int = BITS, dims: int = DIMS, rounds: int = 0, seed: int = 5) -> LatentSpace:
    """The latent space of the documents' passages."""
    idf = inverse_frequencies(docs, bits)
    basis = np.linalg.qr(np.random.default_rng(seed).standard_normal((1 << bits, dims + OVER)))[0].astype(np.float32, order="C")
    for _ in range(rounds):
        image = _gram(docs, basis, idf, bits)
        if not image.any():
            break
        basis = np.linalg.qr(image)[0].astype(np.float32, order="C")
    image = _gram(docs, basis, idf, bits)
    values, vectors = _nystrom(image, basis.astype(np.float64))
    values, vectors = values[:dims], vectors[:, :dims]
    least = 1e-9 * max(values.max(), 1e-9)
    rest = np.random.default_rng(seed + 1).standard_normal(vectors.shape) / np.sqrt(dims)
    rest -= vectors @ (vectors.T @ rest)
    vectors = vectors / np.sqrt(np.maximum(values, least)) + REST * rest / np.sqrt(max(values[-1], least))
    del image, basis, rest
    release()
    return LatentSpace(np.vstack((idf[:, None] * vectors, np.zeros((1, vectors.shape[1])))).astype(np.float32, order="C"), bits)  # rows are gathered


def common(item: dict[int, int], full: int, words: list[int]) -> int:
    """Length of the longest common subsequence; item: for each word, the bits of its places."""
    state = full
    for w in words:
        if m := item.get(w):
            x = state & m
            state = ((state + x) | (state - x)) & full
    return full.bit_length() - state.bit_count()


@dataclass
class Items:
    """Benchmark items made ready: words as hashes, latent vectors, and the window width of each."""

    ids: list[int]
    words: list[list[int]]
    vectors: np.ndarray
    width: np.ndarray
    whole: list[int]  # one number for each item as given; its other numbers are more widths or stretches

    def __post_init__(self):
        self.longest = max(map(len, self.words), default=0)
        self.masks, self.answers, self.counts = [], [], [Counter(ws) for ws in self.words]
        for ws in self.words:
            tail = ws[-max(1, len(ws) // 4) :]
            self.masks.append(_masks(ws))
            self.answers.append(_masks(tail))
        runs: dict[int, list] = {}
        for number in self.whole:
            ws = np.array(self.words[number], U)
            size = min(ANCHOR, len(ws))
            h = rolling(ws, size)
            runs.setdefault(size, []).append((h, np.full(len(h), number), np.arange(len(h))))
        self.anchors = {}
        for size, parts in runs.items():
            h, number, place = map(np.concatenate, zip(*parts, strict=True))
            order = np.argsort(h, kind="stable")
            some = np.zeros(1 << 16, bool)
            some[h >> U(48)] = True
            self.anchors[size] = (h[order], number[order], place[order], some)


def _masks(words: list[int]) -> tuple[dict[int, int], int]:
    out: dict[int, int] = {}
    for i, w in enumerate(words):
        out[w] = out.get(w, 0) | (1 << i)
    return out, (1 << len(words)) - 1


def prepare(items: list[tuple[int, str]], space: LatentSpace) -> Items:
    """An item longer than the widest window is looked up by each of its stretches of that length."""
    ids, words, vectors, width, whole = [], [], [], [], []
    for id, text in items:
        held = _words([text.encode("utf-8", "surrogatepass")]).hash if text else np.empty(0, U)
        for a in range(0, max(1, len(held) - PASSAGE // 4), PASSAGE) if len(held) else ():
            piece = held[a : a + PASSAGE]
            v = space.vectors(piece).sum(0)
            if a == 0:
                whole.append(len(ids))
            for w in sorted({next(w for w in WIDTHS if w >= n) for n in (len(piece), len(piece) + STRIDE - 1)}):
                ids.append(id)
                words.append(held.tolist())
                vectors.append(v / (np.linalg.norm(v) or 1.0))
                width.append(w)
    return Items(ids, words, np.array(vectors, np.float32).reshape(len(ids), space.table.shape[1]), np.array(width, int), whole)


def search(texts: list[bytes], space: LatentSpace, items: Items, cosine=COSINE, lcs=LCS, answer=ANSWER, verbatim=VERBATIM, stride: int = STRIDE) -> list[list[dict]]:
    """For each text its leaks: item_id, cosine, lcs and answer shares, first word of the window."""
    out: list[list[dict]] = []
    for a, b in batches(texts, 1 << 18):  # windows' sums stay in the cache
        words = _words(texts[a:b])
        found: list[dict[int, dict]] = [{} for _ in range(b - a)]
        pad = WIDTHS[-1] // stride
        _anchored(words, space, items, found, lcs, answer, verbatim)
        begin, sums = _stride_sums(words, space, stride, pad)
        doc_of = np.repeat(np.arange(b - a), np.diff(begin))
        window, held = sums[: len(doc_of)].copy(), 1
        for width in WIDTHS:
            for extra in range(held, width // stride):
                window += sums[extra : extra + len(doc_of)]
            held = max(held, width // stride)
            mine = np.flatnonzero(items.width == width)
            for c in range(0, len(mine), 1024):
                vectors = items.vectors[mine[c : c + 1024]].T
                for d in range(0, len(window), 8192):
                    part = window[d : d + 8192]
                    least = cosine * np.maximum(np.sqrt(np.einsum("ij,ij->i", part, part)), 1e-9)
                    near = part @ vectors
                    rows, columns = np.divmod(np.flatnonzero(near >= least[:, None]), near.shape[1])
                    last, around = -1, set()
                    for w, i in zip(rows.tolist(), columns.tolist(), strict=True):
                        number, doc = int(mine[c + i]), doc_of[d + w]
                        at = int(d + w - begin[doc]) * stride
                        if w != last:  # words of the widest stretch that an item can be compared with here
                            last, around = w, set(words.hash[max(words.first[doc], words.first[doc] + at - items.longest) : min(words.first[doc + 1], words.first[doc] + at + width + items.longest)].tolist())
                        counts = items.counts[number]
                        if sum(map(counts.__getitem__, counts.keys() & around)) >= lcs * len(items.words[number]):  # else no subsequence is long enough
                            _check(words, doc, at, width, number, float(near[w, i] / least[w] * cosine), items, found, lcs, answer, verbatim)
        out += [sorted(({k: v for k, v in x.items() if k != "leak"} for x in f.values() if x["leak"]), key=lambda x: x["item_id"]) for f in found]
    return out


def _anchored(words, space: LatentSpace, items: Items, found, lcs, answer, verbatim) -> None:
    """Checks the places where a document has a run of an item's words."""
    for size, (hashes, numbers, places, some) in items.anchors.items():
        here = rolling(words.hash, size)
        at = np.flatnonzero(some[here >> U(48)])
        low, high = np.searchsorted(hashes, here[at], "left"), np.searchsorted(hashes, here[at], "right")
        hit = (high > low) & (words.doc[at] == words.doc[at + size - 1])
        done = set()
        for p, i, j in zip(at[hit].tolist(), low[hit].tolist(), high[hit].tolist(), strict=True):
            doc = int(words.doc[p])
            for number, place in zip(numbers[i:j].tolist(), places[i:j].tolist(), strict=True):
                begin, m = int(p - words.first[doc]) - place, len(items.words[number])
                if (doc, number, begin // size) in done or _settled(found[doc].get(items.ids[number])):
                    continue
                done.add((doc, number, begin // size))
                begin = max(0, begin)
                v = space.vectors(words.hash[words.first[doc] + begin : min(words.first[doc + 1], words.first[doc] + begin + m)]).sum(0)
                item = space.vectors(np.array(items.words[number], U)).sum(0)
                near = float(v @ item) / max(float(np.linalg.norm(v) * np.linalg.norm(item)), 1e-9)
                _check(words, doc, begin, m, number, near, items, found, lcs, answer, verbatim)


def _settled(known: dict | None) -> bool:
    """Whether no other place can be better."""
    return bool(known and known["leak"] and known["lcs"] == 1.0)


def _stride_sums(words, space: LatentSpace, stride: int, pad: int) -> tuple[np.ndarray, np.ndarray]:
    """Latent sums of every ``stride`` words of each text, ``pad`` empty ones after each; where each text begins."""
    counts = np.diff(words.first)
    blocks = -(-counts // stride) + pad
    begin = np.concatenate(([0], np.cumsum(blocks)))
    nothing = len(space.table) - 1  # a row of zeros
    feature = np.full((begin[-1] + pad) * stride, nothing, np.int32)
    feature[np.arange(len(words.hash)) + (begin[:-1] * stride - words.first[:-1])[words.doc]] = _features(words.hash, space.bits)
    out = np.empty((len(feature) // stride, space.table.shape[1]), np.float32)
    for a in range(0, len(out), SUMS):
        part = out[a : a + SUMS]
        space.table.take(feature[a * stride : (a + len(part)) * stride], 0).reshape(len(part), stride, -1).sum(1, out=part)
    return begin, out


def _check(words, doc, at, width, number, near, items, found, lcs, answer, verbatim) -> None:
    item, known = items.ids[number], found[doc].get(items.ids[number])
    if _settled(known):
        return
    m = len(items.words[number])
    first = words.first[doc]
    region = words.hash[max(first, first + at - m) : min(words.first[doc + 1], first + at + width + m)].tolist()
    mask, full = items.masks[number]
    share = common(mask, full, region) / m
    if known and known["leak"] and share <= known["lcs"]:
        return
    mask, full = items.answers[number]
    ends = common(mask, full, region) / full.bit_length()
    leak = share >= verbatim or share >= lcs and ends >= answer
    if known and (leak, share) <= (known["leak"], known["lcs"]):
        return
    found[doc][item] = {"item_id": item, "cosine": near, "lcs": share, "answer": ends, "first_word": at, "leak": leak}


LEAKS = "array<struct<item_id: long, cosine: double, lcs: double, answer: double, first_word: long>>"


def leaks(docs: DataFrame, benchmark: DataFrame, text: str = "text", block: int = 4096, space: LatentSpace | None = None, **limits) -> DataFrame:
    """Every row with ``leaks``, its leaked items. A column of that name is replaced."""
    rows = benchmark.select("item_id", "text").where(F.col("item_id").isNotNull()).orderBy("item_id", "text").toLocalIterator()
    small_batches(docs)
    space = space or fit(docs)
    held, out = [], docs.drop("leaks").withColumn("leaks", F.array().cast(LEAKS))
    for r in rows:
        held.append((r["item_id"], r["text"]))
        if len(held) == block:
            out, held = _add(out, prepare(held, space), space, text, limits), []
    return _add(out, prepare(held, space), space, text, limits) if held else out


def _add(docs: DataFrame, items: Items, space: LatentSpace, text: str, limits: dict) -> DataFrame:
    """The rows with one more block of items looked up; few texts at a time are held as Python objects."""

    def run(source):
        for batch in source:
            at, last = batch.schema.get_field_index(text), batch.num_columns - 1
            for a in range(0, len(batch), 256):
                part = batch.slice(a, 256)
                found = search(to_bytes(part.column(at).to_pylist()), space, items, **limits)
                both = [x + y for x, y in zip(part.column(last).to_pylist(), found, strict=True)]
                yield pa.RecordBatch.from_arrays([*part.columns[:last], pa.array(both, part.schema.field(last).type)], schema=part.schema)

    return docs.mapInArrow(trimmed(run), docs.schema)
