"""SentencePiece encoding and decoding on the tokenizers library.

The model's protobuf is read here, field by field; from it the normaliser, the marker for spaces, the
pieces with their scores and the byte fallback are rebuilt as a tokenizers pipeline (Unigram models
from their scores, BPE models from merges in the order of the merged pieces' scores). No piece of the
usual models has a space marker behind another character, so a text falls into segments, each a run of
markers with what follows, that encode on their own; a task encodes each distinct segment once, in
batches on ``threads`` threads. Other models have their texts encoded whole.

The ids are those of the rebuilt pipeline. Parity is measured: every distinct segment (or whole text) is
also encoded by the sentencepiece library, and ``parity`` says whether a row's ids are the same. Decoding is
checked the same way: ``round_trip`` says whether a row's ids give the text back.

Null and empty texts have no ids. Texts of any length are taken whole. Control and byte pieces written
out in a text are ordinary characters. A literal marker counts as a space, as in the original library.
"""

from __future__ import annotations

import os
import re
import struct
import zlib
from array import array
from dataclasses import dataclass
from itertools import chain

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql.types import ArrayType, BooleanType, IntegerType, StringType, StructField, StructType

from .memory import trimmed
from .session import small_batches

# Fixed values of the model format.
MARK = "▁"
UNIGRAM, BPE = 1, 2
NORMAL, UNKNOWN, CONTROL, USER, UNUSED, BYTE = 1, 2, 3, 4, 5, 6

CACHE_BYTES, LONG = 16 << 20, 64


def _varint(data: bytes, at: int) -> tuple[int, int]:
    value = shift = 0
    while True:
        byte = data[at]
        at += 1
        value |= (byte & 127) << shift
        shift += 7
        if byte < 128:
            return value, at


def read_fields(data: bytes):
    """(number, value) of a protobuf message's fields; bytes for those with a length."""
    at = 0
    while at < len(data):
        key, at = _varint(data, at)
        kind = key & 7
        if kind == 0:
            value, at = _varint(data, at)
        else:
            size = {1: 8, 5: 4}.get(kind)
            if size is None:
                size, at = _varint(data, at)
            value, at = data[at : at + size], at + size
        yield key >> 3, value


@dataclass
class Model:
    pieces: list[tuple[str, float, int]]
    kind: int = UNIGRAM
    byte_fallback: bool = False
    charsmap: bytes = b""
    dummy_prefix: bool = True
    trim: bool = True
    escape: bool = True
    unknown: int = 0

    @property
    def segmented(self) -> bool:
        """Whether no piece goes on over a marker."""
        return self.dummy_prefix and self.escape and not self.trim and not self.charsmap and not any(re.search(f"[^{MARK}]{MARK}", p) for p, _, k in self.pieces if k in (NORMAL, USER))


def parse(data: bytes) -> Model:
    model = Model([])
    for number, value in read_fields(data):
        if number == 1:
            piece, score, kind = "", 0.0, NORMAL
            for n, v in read_fields(value):
                if n == 1:
                    piece = v.decode("utf-8")
                elif n == 2:
                    score = struct.unpack("<f", v)[0]
                elif n == 3:
                    kind = v
            if kind == UNKNOWN:
                model.unknown = len(model.pieces)
            model.pieces.append((piece, score, kind))
        elif number == 2:
            for n, v in read_fields(value):
                if n == 3:
                    model.kind = v
                elif n == 35:
                    model.byte_fallback = bool(v)
        elif number == 3:
            for n, v in read_fields(value):
                if n == 2:
                    model.charsmap = v
                elif n in (3, 4, 5):
                    setattr(model, {3: "dummy_prefix", 4: "trim", 5: "escape"}[n], bool(v))
    return model


def merges(pieces: list[tuple[str, float, int]]) -> list[tuple[str, str]]:
    """Every way to join two pieces into a third, best third first."""
    usable = {p: (s, i) for i, (p, s, k) in enumerate(pieces) if k in (NORMAL, USER)}
    found = []
    for piece, (score, place) in usable.items():
        for cut in range(1, len(piece)):
            left, right = piece[:cut], piece[cut:]
            if left in usable and right in usable:
                found.append((-score, place, usable[left][1], usable[right][1], left, right))
    found.sort()
    return [(left, right) for *_, left, right in found]


def backend(model: Model):
    """The model as a tokenizers pipeline."""
    from tokenizers import Regex, Tokenizer, decoders, models, normalizers

    if model.kind == UNIGRAM:
        core = models.Unigram([(p, s) for p, s, _ in model.pieces], model.unknown, model.byte_fallback)
    elif model.kind == BPE:
        core = models.BPE({p: i for i, (p, _, _) in enumerate(model.pieces)}, merges(model.pieces), unk_token=model.pieces[model.unknown][0], fuse_unk=True, byte_fallback=model.byte_fallback)
    else:
        raise ValueError(f"models of kind {model.kind} are not supported")
    out, steps = Tokenizer(core), []
    if model.charsmap:
        steps.append(normalizers.Precompiled(model.charsmap))
    if model.trim:
        steps += [normalizers.Strip(), normalizers.Replace(Regex(" {2,}"), " ")]
    if model.dummy_prefix:
        steps.append(normalizers.Prepend(MARK if model.escape else " "))
    if model.escape:
        steps.append(normalizers.Replace(" ", MARK))
    out.normalizer = normalizers.Sequence(steps)
    back = [decoders.Replace(MARK, " "), *([decoders.ByteFallback()] if model.byte_fallback else []), decoders.Fuse()]
    out.decoder = decoders.Sequence([*back, decoders.Strip(" ", 1, 0)] if model.dummy_prefix else back)
    return out


_SEGMENT = re.compile(f"{MARK}+[^{MARK}]*")
_tools: dict[int, dict] = {}  # of a Python worker, which outlives a task


@dataclass
class SentencePieces:
    """Encodes and decodes with one model, given as the bytes of its file."""

    data: bytes
    threads: int = 2

    def tools(self) -> dict:
        key = zlib.crc32(self.data)
        if key not in _tools:
            os.environ["TOKENIZERS_PARALLELISM"] = "true" if self.threads > 1 else "false"
            os.environ.setdefault("RAYON_NUM_THREADS", str(self.threads))
            import sentencepiece
            from tokenizers import decoders

            model = parse(self.data)
            whole = backend(model)
            t = {"model": model, "whole": whole, "normalizer": whole.normalizer, "decoder": whole.decoder, "other": sentencepiece.SentencePieceProcessor(model_proto=self.data), "cache": {}, "odd": set(), "lost": set(), "held": 0}
            t["plain"] = decoders.Sequence([decoders.Replace(MARK, " "), *([decoders.ByteFallback()] if model.byte_fallback else []), decoders.Fuse()])
            _tools.clear()
            _tools[key] = t
        return _tools[key]

    def clear(self) -> None:
        """Forgets the segments met so far."""
        t = self.tools()
        t["held"] = 0
        for held in (t["cache"], t["odd"], t["lost"]):
            held.clear()

    def _learn(self, new: list[str]) -> list[str]:
        """Ids of segments, given without their first marker, into the cache; returns those too long to stay.

        It is noted where the libraries differ or decoding does not give a segment back.
        """
        t = self.tools()
        cache, odd, lost, tool = t["cache"], t["odd"], t["lost"], t["whole"]
        plain = [s.replace(MARK, " ") for s in new]
        tool.normalizer, tool.decoder = None, t["plain"]
        try:
            ours = [x.ids for x in tool.encode_batch_fast([MARK + s for s in new], add_special_tokens=False)]
            # a segment's first id holds its marker, so ids of bytes never run on from one segment into the next
            back = tool.decode_batch(ours, skip_special_tokens=False)
        finally:
            tool.normalizer, tool.decoder = t["normalizer"], t["decoder"]
        for s, p, a, b, c in zip(new, plain, ours, t["other"].encode(plain, num_threads=self.threads), back, strict=True):
            if a != b and s:  # nothing but the prefix is an empty text there
                odd.add(s)
            if " " + p != c:
                lost.add(s)
            cache[s] = array("i", a).tobytes()
        t["held"] += sum(map(len, new)) + 8 * len(new)
        return [s for s in new if len(s) > LONG]

    def encode(self, texts: list[str | None]) -> list[tuple[np.ndarray, bool, bool]]:
        """Ids of each text, whether the sentencepiece library gives the same, and whether decoding gives the text back."""
        t = self.tools()
        texts = [x or "" for x in texts]
        if not t["model"].segmented:
            ours = [x.ids for x in t["whole"].encode_batch_fast(texts, add_special_tokens=False)]
            theirs = t["other"].encode(texts, num_threads=self.threads)
            return [(np.array(a, np.int32), a == b, c == self.normal(x)) for a, b, c, x in zip(ours, theirs, self.decode(ours), texts, strict=True)]
        cache, odd, lost, out = t["cache"], t["odd"], t["lost"], []
        for a in range(0, len(texts), 256):
            # one space between words is the usual case, and much the fastest to cut at
            cut = [[] if not x else x.split(" ") if MARK not in x and "  " not in x and x[0] != " " and x[-1] != " " else [s[1:] for s in _SEGMENT.findall(MARK + x.replace(" ", MARK))] for x in texts[a : a + 256]]
            if t["held"] > CACHE_BYTES:
                self.clear()
            long = self._learn(list(set(chain.from_iterable(cut)).difference(cache)))
            for c in cut:
                out.append((np.frombuffer(b"".join(map(cache.__getitem__, c)), np.int32), not odd or odd.isdisjoint(c), not lost or lost.isdisjoint(c)))
            for s in long:
                t["held"] -= len(s) + 8
                del cache[s]
        return out

    def decode(self, ids: list) -> list[str]:
        return self.tools()["whole"].decode_batch([x.tolist() if hasattr(x, "tolist") else list(x) for x in ids], skip_special_tokens=False)

    def normal(self, text: str | None) -> str:
        """What decoding gives back for a text, for models that normalise nothing but spaces."""
        return (text or "").replace(MARK, " ")

    def encode_documents(self, docs: DataFrame, text: str = "text") -> DataFrame:
        """Every row with ``ids`` array<int>, ``parity`` and ``round_trip`` (decoding gives the text back).

        Columns of these names are replaced.
        """
        small_batches(docs)
        own, rows = self, docs.drop("ids", "parity", "round_trip")

        def run(source):
            try:
                for batch in source:
                    at = batch.schema.get_field_index(text)
                    for a in range(0, len(batch), 128):
                        part = batch.slice(a, 128)
                        held = own.encode(part.column(at).to_pylist())
                        ids = [x for x, _, _ in held]
                        ends = np.concatenate(([0], np.cumsum([len(x) for x in ids]))).astype(np.int32)
                        lists = pa.ListArray.from_arrays(pa.array(ends), pa.array(np.concatenate(ids)))
                        new = [lists, pa.array([p for _, p, _ in held], pa.bool_()), pa.array([r for _, _, r in held], pa.bool_())]
                        yield pa.RecordBatch.from_arrays([*part.columns, *new], names=[*part.schema.names, "ids", "parity", "round_trip"])
            finally:
                own.clear()  # a worker outlives its tasks

        schema = StructType([*rows.schema.fields, StructField("ids", ArrayType(IntegerType())), StructField("parity", BooleanType()), StructField("round_trip", BooleanType())])
        return rows.mapInArrow(trimmed(run), schema)

    def decode_documents(self, docs: DataFrame, ids: str = "ids") -> DataFrame:
        """Every row with ``text`` decoded from its ids; null ids give an empty text. A column of that name is replaced."""
        own, rows = self, docs.drop("text")

        def run(source):
            for batch in source:
                at = batch.schema.get_field_index(ids)
                for a in range(0, len(batch), 128):
                    part = batch.slice(a, 128)
                    texts = own.decode([x or [] for x in part.column(at).to_pylist()])
                    yield pa.RecordBatch.from_arrays([*part.columns, pa.array(texts, pa.string())], names=[*part.schema.names, "text"])

        return rows.mapInArrow(trimmed(run), StructType([*rows.schema.fields, StructField("text", StringType())]))
