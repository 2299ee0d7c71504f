"""The ten operators and the pipeline: against brute force, and on odd inputs."""

import collections
import zlib

import numpy as np
import pyarrow as pa
import pytest
from conftest import MIDDLE, SMALL, same  # noqa: I001
from pyspark.sql import functions as F

from pivotrank.llm import bagminhash, components, decontaminate, hnsw, language, license_scan, near_dup, packing, quality, registry, sentencepieces, sharding, substring_dedup, text, token_files

BASE = "alpha beta gamma delta epsilon zeta eta theta iota kappa lambda mu nu xi omicron pi rho sigma tau upsilon phi chi psi omega".split()


def words(seed, n):
    rng = np.random.default_rng(seed)
    return [BASE[i] + str(j) for i, j in zip(rng.integers(0, 24, n), rng.integers(0, 40, n), strict=True)]


@pytest.fixture(scope="module")
def odd(spark):
    """Null, empty, tiny and very long texts, copies, near copies, shared passages, repeated rows, a clashing column."""
    passage, long = words(1, 60), words(2, 30_000)
    near = words(3, 200)
    other = list(near)
    other[100] = "changed"
    texts = [None, "", "  \n ", "one", "one two three", " ".join(long), " ".join(long), " ".join(near), " ".join(other), " ".join(words(4, 40) + passage + words(5, 40)), "\n".join(words(6, 30) + passage), " ".join(passage), "Released under the MIT License.", "été ñandú " * 30, "\U0001f600 <s> <|endoftext|> ▁ x"]
    rows = [(i, t, "en" if i % 2 else None, "s", 0, 1.5) for i, t in enumerate(texts)] + [(7, " ".join(near), None, "s", 0, 1.5), (None, "no id", "en", None, None, None)]
    return spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long, found double").repartition(3).persist()


def brute_windows(docs, width):
    first = {}
    for i, t in sorted(docs):
        w = (t or "").encode().split()
        for p in range(len(w) - width + 1):
            first.setdefault(tuple(w[p : p + width]), i)
    out = {}
    for i, t in docs:
        w = (t or "").encode().split()
        gone = [False] * len(w)
        for p in range(len(w) - width + 1):
            if first[tuple(w[p : p + width])] < i:
                gone[p : p + width] = [True] * width
        out[i] = b" ".join(x for x, g in zip(w, gone, strict=True) if not g).decode()
    return out


@pytest.mark.parametrize("name", ["op1_substring_dedup", "op5_license_scan"])
def test_query_equals_sql(spark, duck, name):
    assert same(registry.queries()[name](spark, MIDDLE), duck.sql(registry.oracle_sql()[name]))


def test_substrings(spark, odd):
    for part_bytes in (2000, 1 << 20):
        got = {r.doc_id: r.kept for r in substring_dedup.remove_repeats(odd.where("doc_id IS NOT NULL"), part_bytes=part_bytes).collect()}
        assert got == brute_windows([(r.doc_id, r.text) for r in odd.where("doc_id IS NOT NULL").collect()], 50)
    full = substring_dedup.remove_repeats(odd, carry=True)
    assert full.count() == odd.count() and "found" in full.schema["rest"].dataType.names
    assert substring_dedup.remove_repeats(odd.limit(0)).count() == 0
    spans = {r.doc_id: r.spans for r in substring_dedup.remove_repeats(odd).collect()}
    assert [(s["first"], s["words"]) for s in spans[10]] == [(30, 60)]


def test_sharding(spark, odd):
    docs = spark.read.parquet(f"{SMALL}/documents.parquet")
    got = sharding.shuffle_into_shards(docs, 8, part_bytes=20_000).select("doc_id", "shard", "slot").collect()
    sizes = collections.Counter(r.shard for r in got)
    assert sorted(r.doc_id for r in got) == list(range(docs.count())) and max(sizes.values()) - min(sizes.values()) <= 1
    assert all(sorted(r.slot for r in got if r.shard == s) == list(range(n)) for s, n in sizes.items())
    again = sharding.shuffle_into_shards(docs.repartition(5), 8, part_bytes=20_000).select("doc_id", "shard", "slot").collect()
    assert sorted(got) == sorted(again)
    assert sharding.shuffle_into_shards(odd, 4).count() == odd.count() and sharding.shuffle_into_shards(odd.limit(0), 4).count() == 0


def test_matrix_has_exact_margins_and_law():
    counts, cells = np.array([5, 0, 7, 8]), sharding.cell_sizes(20, 3, 2)
    for seed in range(20):
        lines = np.array([sharding.matrix_line(counts, cells, p, seed) for p in range(4)])
        assert (lines.sum(0) == cells).all() and (lines.sum(1) == counts).all() and (lines >= 0).all()
    mean = np.mean([sharding.matrix_line(counts, cells, 2, s)[0] for s in range(2000)])
    assert abs(mean - 7 * cells[0] / 20) < 0.1


def test_quality(spark, odd):
    scored = registry.op3_quality(spark, MIDDLE).join(spark.read.parquet(f"{MIDDLE}/labels.parquet"), "doc_id").where("held_out").collect()
    good = [r.predicted for r in scored if r.quality == 1]
    bad = [r.predicted for r in scored if r.quality == 0]
    assert np.mean(good) > 0.95 and np.mean(bad) < 0.5
    none = spark.createDataFrame([], "doc_id long, quality int")
    model = quality.fit(odd, none)
    assert {r.s for r in odd.select(model.column("text").alias("s")).collect()} == {0.5}
    assert quality.fit(odd, spark.createDataFrame([(1, 1)], "doc_id long, quality int")).score(b"") > 0.99
    both = spark.createDataFrame([(0, 1), (1, 0), (2, 1), (3, 1)], "doc_id long, quality int")
    for texts in (odd.limit(0), odd.withColumn("text", F.lit(None).cast("string"))):
        assert abs(quality.fit(texts, both).score(b"any") - 0.75) < 1e-6


def test_quality_scores_equal_brute_force(spark):
    """The scores again, from fresh compressors: sizes with each dictionary, and the logistic curve over them."""
    import math

    import zstandard

    docs, labels = spark.read.parquet(f"{MIDDLE}/documents.parquet"), spark.read.parquet(f"{MIDDLE}/labels.parquet")
    known = {r.doc_id: r.quality for r in labels.collect() if zlib.crc32(str(r.doc_id).encode()) % 5}
    model = quality.fit(docs, labels, usable=F.pmod(F.crc32(F.col("doc_id").cast("string").cast("binary")), F.lit(5)) != 0)
    texts = {r.doc_id: (r.text or "").encode() for r in docs.collect()}
    assert not any(t in (model.good, model.bad) for t in texts.values())
    size = lambda t, d: len(zstandard.ZstdCompressor(level=model.level, dict_data=zstandard.ZstdCompressionDict(d)).compress(t))
    got = {r.doc_id: r.score for r in registry.op3_quality(spark, MIDDLE).collect()}
    assert set(got) == set(texts)
    for i in sorted(texts)[:150]:
        a, b, n = size(texts[i], model.good), size(texts[i], model.bad), len(texts[i]) + 1
        z = model.weights[2] + model.weights[0] * ((b - a) / n - model.centre[0]) / model.spread[0] + model.weights[1] * (math.log(min(a, b) / n) - model.centre[1]) / model.spread[1]
        assert abs(got[i] - 1 / (1 + math.exp(-z))) < 1e-9
    assert np.mean([got[i] for i, q in known.items() if q]) > np.mean([got[i] for i, q in known.items() if not q]) + 0.2


def test_bagminhash_is_unbiased():
    rng = np.random.default_rng(1)
    e = text.splitmix(np.arange(300, dtype=np.uint64))
    wa = rng.integers(0, 12, 300)
    wb = np.where(rng.random(300) < 0.6, wa, rng.integers(0, 40, 300))
    element, weight = np.concatenate((e[wa > 0], e[wb > 0])), np.concatenate((wa[wa > 0], wb[wb > 0]))
    owner = np.r_[np.zeros((wa > 0).sum(), int), np.ones((wb > 0).sum(), int)]
    s = bagminhash.signatures(element, weight, owner, 3, 8192)
    assert abs((s[0] == s[1]).mean() - np.minimum(wa, wb).sum() / np.maximum(wa, wb).sum()) < 0.02
    assert np.isinf(s[2]).all()


def brute_classes(docs, least=0.8):
    def bag(w):
        return collections.Counter(tuple(w[i : i + 5]) for i in range(len(w) - 4)) if len(w) >= 5 else collections.Counter([tuple(w)])

    bags = {i: bag(t.split()) for i, t in docs if t and t.split()}
    parent = {i: i for i, _ in docs}

    def find(x):
        while parent[x] != x:
            x = parent[x]
        return x

    holders = collections.defaultdict(list)
    for i, b in bags.items():
        for s in b:
            holders[s].append(i)
    for a, b in {(a, b) for v in holders.values() for a in v for b in v if a < b}:
        common = sum((bags[a] & bags[b]).values())
        if common >= least * (bags[a].total() + bags[b].total() - common):
            a, b = find(a), find(b)
            parent[max(a, b)] = min(a, b)
    return {i: find(i) for i in parent}


def test_near_duplicates(spark, odd):
    docs = spark.read.parquet(f"{SMALL}/documents.parquet")
    assert {r.doc_id: r.class_id for r in near_dup.classes(docs).collect()} == brute_classes([(r.doc_id, r.text) for r in docs.collect()])
    got = {r.doc_id: r.class_id for r in near_dup.classes(odd).collect()}
    assert got == brute_classes([(r.doc_id, r.text) for r in odd.where("doc_id IS NOT NULL").collect()]) | {None: None}
    assert near_dup.classes(odd.limit(0)).count() == 0


def test_near_duplicates_in_large_buckets(spark):
    """A group far beyond ALL_PAIRS whose members are near and not so near: blocks decide."""
    rng, base = np.random.default_rng(5), words(9, 80)
    docs = []
    for i in range(60):
        w = list(base)
        for p in rng.choice(80, 1 + i % 4, replace=False):
            w[p] = f"edit{i}"
        docs.append((i, " ".join(w)))
    got = {r.doc_id: r.class_id for r in near_dup.classes(spark.createDataFrame(docs, "doc_id long, text string"), leader_rounds=0).collect()}
    assert got == brute_classes(docs)


def test_components(spark):
    edges = [(1, 2), (2, 3), (9, 3), (5, 6), (7, 7), (8, 5)] + [(100 + i, 101 + i) for i in range(40)]
    got = {r.b: r.a for r in components.stars(spark.createDataFrame(edges, "a long, b long")).collect()}
    assert got == {2: 1, 3: 1, 9: 1, 6: 5, 8: 5} | {101 + i: 100 for i in range(40)}


def test_few_edges_take_one_checkpoint_and_many_the_same_stars(spark, monkeypatch):
    rng = np.random.default_rng(8)
    pairs = [(int(a), int(b)) for a, b in rng.integers(-300, 300, (260, 2))] + [(2000 - i, 1999 - i) for i in range(60)]
    edges, calls = spark.createDataFrame(pairs, "a long, b long"), []
    monkeypatch.setattr(components, "cut", lambda df, real=components.cut: calls.append(1) or real(df))
    few = {r.b: r.a for r in components.stars(edges).collect()}
    assert len(calls) == 1 and components.stars(edges.limit(0)).count() == 0
    monkeypatch.setattr(components, "FEW", 0)
    assert few == {r.b: r.a for r in components.stars(edges).collect()} and len(calls) > 4


def brute_licenses(text, templates, told, threshold=0.8):
    """Every block of twice a template's words, as a set, against every template."""
    import re

    ws = re.findall(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+", "".join(c.lower() if "A" <= c <= "Z" else c for c in text or ""))
    out = []
    for label in templates:
        t = templates[label].split()
        for a in range(0, len(ws), len(t)):
            block = set(ws[a : a + 2 * len(t)])
            if len(block & set(t)) >= threshold * len(set(t)) - 1e-9 and set(told.get(label, "").split()) <= block:
                out.append((label, a, round(len(block & set(t)) / len(set(t)), 9)))
    return sorted(out)


def test_licenses(spark, odd):
    got = {r.doc_id: r["found_"] for r in license_scan.scan(odd).collect()}
    assert {r["found"] for r in license_scan.scan(odd).collect()} == {1.5, None}
    assert got[12].places[0].label == "mit" and got[12].hits[0].label == "mit-notice" and got[0].n_words == 0
    assert not any("python" in x.lower() or "arrow" in x.lower() for x in license_scan.scan(odd)._jdf.queryExecution().executedPlan().toString().split("\n"))
    assert license_scan.scan(odd.limit(0)).count() == 0


def test_licenses_equal_brute_force(spark):
    rng = np.random.default_rng(4)
    vocabulary = sorted({w for t in license_scan.TEMPLATES.values() for w in t.split()})
    texts = ["released under the BSD license", "released under the apache license", "released under license by the publisher", "Released under the MIT license", "mit the under released", "license " * 30, None, ""]
    for label, t in license_scan.TEMPLATES.items():
        w = t.split()
        texts += [t.upper(), " ".join(w[: len(w) * 9 // 10]), " ".join(w[: len(w) * 7 // 10]), " ".join(words(len(texts), 37) + w + words(len(texts), 9)), " ".join(rng.permutation(w)), " ".join(rng.choice(vocabulary, 60))]
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string").repartition(4)
    got = {r.doc_id: sorted((h.label, h.first_word, round(h.containment, 9)) for h in r.found.hits) for r in license_scan.scan(docs).collect()}
    assert got == {i: brute_licenses(t, license_scan.TEMPLATES, license_scan.DISTINGUISHING) for i, t in enumerate(texts)}
    assert [got[i] for i in (0, 1, 2)] == [[], [], []] and got[3] == [("mit-notice", 0, 1.0)]
    counts = license_scan.filter_counts(docs).agg(*[F.sum(c).alias(c) for c in ("prefix", "length", "positional", "hits")]).first()
    assert counts["prefix"] > counts["length"] > counts["positional"] > counts["hits"] == sum(map(len, got.values()))
    own = {"x": "one two three four five"}
    held = license_scan.scan(spark.createDataFrame([(0, "five four three two"), (1, "one two")], "doc_id long, text string"), templates=own, phrases={}).orderBy("doc_id").collect()
    assert [[h.label for h in r.found.hits] for r in held] == [["x"], []]


def test_sentencepiece(spark, odd):
    tool = registry.sentence_pieces()
    held = tool.encode_documents(odd).collect()
    assert all(r.parity and r.round_trip for r in held) and len(held) == odd.count()
    other = tool.tools()["other"]
    assert all(list(r.ids) == other.encode(r.text or "") for r in held)
    back = tool.decode_documents(tool.encode_documents(odd).select("doc_id", "ids", F.col("text").alias("was")))
    assert all(r.text == (r.was or "").replace("▁", " ") for r in back.collect())
    assert tool.encode_documents(odd.limit(0)).count() == 0


def unigram_model(pieces, normalizer=b"", byte_fallback=False, trim=False):
    """A model's protobuf, written field by field."""

    def size(n):
        return bytes([n]) if n < 128 else bytes([n & 127 | 128]) + size(n >> 7)

    def field(n, kind, body):
        return size(n << 3 | kind) + body

    def block(n, body):
        return field(n, 2, size(len(body)) + body)

    def piece(s, score, kind=1):
        return block(1, block(1, s.encode()) + field(2, 5, np.float32(score).tobytes()) + field(3, 0, bytes([kind])))

    data = piece("<unk>", 0, 2) + b"".join(piece(s, -1 - 0.37 * i) for i, s in enumerate(pieces))
    data += b"".join(piece(f"<0x{i:02X}>", -90, 6) for i in range(256)) if byte_fallback else b""
    data += block(2, field(3, 0, b"\x01") + field(35, 0, bytes([byte_fallback])))
    return data + block(3, normalizer + field(3, 0, b"\x01") + field(4, 0, bytes([trim])) + field(5, 0, b"\x01"))


PIECES = ["▁", "▁the", "e", "t", "h", "a", "▁a", "b", "ab", "▁b", "bab", "he", "fi", "f", "i", "A", "▁A", "c", "1", "2", "é"]


def test_unigram_models_are_rebuilt():
    import sentencepiece

    rules = sentencepiece.SentencePieceNormalizer(rule_name="nmt_nfkc").serialized_model_proto()
    charsmap = next(v for n, v in ((n, v) for k, x in sentencepieces.read_fields(rules) if k == 3 for n, v in sentencepieces.read_fields(x)) if n == 2)

    def varint(n):
        return bytes([n]) if n < 128 else bytes([n & 127 | 128]) + varint(n >> 7)

    normalizer = b"\x12" + varint(len(charsmap)) + charsmap
    texts = ["ab", "a b", "", "bab aa", "the  the", " the", "the ", "ﬁfi", "ＡＢ ab", "①② the", "e\u0301 é", "x y", "日本 the", "\U0001f600", "a\tb\nc", "bab" * 50]
    for charsmapped in (False, True):
        for fallback in (False, True):
            data = unigram_model(PIECES, normalizer if charsmapped else b"", fallback, trim=charsmapped)
            tool, other = sentencepieces.SentencePieces(data), sentencepiece.SentencePieceProcessor(model_proto=data)
            assert tool.tools()["model"].segmented != charsmapped and bool(tool.tools()["model"].charsmap) == charsmapped
            for t, (ids, parity, _) in zip(texts, tool.encode(texts), strict=True):
                assert parity and list(ids) == other.encode(t), (charsmapped, fallback, t)
            plain = [t for t in texts if set(t) <= set("abthe ")]
            back = tool.decode([i for i, _, _ in tool.encode(plain)])
            assert back == [" ".join(t.split()) if charsmapped else t for t in plain]
    sentencepieces._tools.clear()


def test_parity_is_measured():
    """A library that answers otherwise changes the flag, not the ids."""
    tool = sentencepieces.SentencePieces(unigram_model(PIECES))
    before = [list(i) for i, _, _ in tool.encode(["the ab", "a b"])]

    class Other:
        def encode(self, texts, num_threads):
            return [[0] if "the" in t else own.encode(t) for t in texts]

    own = tool.tools()["other"]
    tool.clear()
    tool.tools()["other"] = Other()
    got = tool.encode(["the ab", "a b"])
    assert [list(i) for i, _, _ in got] == before and [p for _, p, _ in got] == [False, True]
    sentencepieces._tools.clear()


def packed(spark, blocks, block_ids):
    """Files of one document each, and what reading gives back."""
    from pivotrank.llm.jvm import register

    register(spark, "TokenFiles", token_files._FUNCTIONS)
    rows = [(i, bytearray(np.array([(i, len(b))], np.int64).tobytes()), bytearray(np.asarray(b, np.uint32).tobytes())) for i, b in enumerate(blocks)]
    files = spark.createDataFrame(rows, "i long, docs binary, ids binary").withColumn("file", F.call_function("token_file_pack", "docs", "ids", F.lit(block_ids))).persist()
    back = files.select(F.explode(F.call_function("token_file_unpack", "file")).alias("d")).select("d.*")
    return {r.i: bytes(r.file) for r in files.select("i", "file").collect()}, {r.doc_id: np.frombuffer(r.ids, np.uint32) for r in back.collect()}


@pytest.mark.parametrize("block_ids", [1, 100, 1 << 17])
def test_coder_round_trips(spark, block_ids):
    rng = np.random.default_rng(0)
    blocks = [rng.integers(0, 65_536, n) for n in (0, 1, 5, 300, 900)] + [np.full(700, 7), np.tile([1, 2, 3, 50_000], 100)]
    blocks += [rng.integers(0, 2**32, 500), np.array([2**32 - 1, 0, 2**31, 65_536]), rng.integers(0, 2**24, 300), np.full(50, 2**32 - 1), np.minimum(rng.geometric(0.001, 30_000), 300_000)]
    coded, back = packed(spark, blocks, block_ids)
    assert all((b == back[i]).all() and len(b) == len(back[i]) for i, b in enumerate(blocks))
    if block_ids > 100:
        assert len(coded[5]) < 100 and len(coded[6]) < 250


def test_coder_beats_general_compressors(spark):
    import zstandard
    from tokenizers import Tokenizer

    tool = Tokenizer.from_str(registry.byte_tokenizer())
    texts = [r.text or "" for r in spark.read.parquet(f"{MIDDLE}/documents.parquet").orderBy("doc_id").select("text").collect()]
    ids = np.concatenate([np.array(e.ids, np.uint32) for e in tool.encode_batch(texts, add_special_tokens=False)])
    coded, back = packed(spark, [ids], token_files.BLOCK_IDS)
    assert (back[0] == ids).all()
    blocks = [ids[a : a + token_files.BLOCK_IDS].astype(np.uint16).tobytes() for a in range(0, len(ids), token_files.BLOCK_IDS)]
    assert len(coded[0]) < 0.9 * sum(len(zstandard.ZstdCompressor().compress(b)) for b in blocks)
    assert len(coded[0]) < 0.9 * sum(len(zlib.compress(b)) for b in blocks)


def test_token_files(spark, odd, tmp_path):
    spec, folder = registry.byte_tokenizer(), f"file://{tmp_path}/files"
    texts = ["a  b", " lead", "tail ", "x\n \ny", "x \n y", "\u00a0 q", "tab\t z", "  ", " ", "it's  we'll", "a\u2003 b c", "\x1c d", "n\n\nm k"]
    more = odd.select("doc_id", "text").unionByName(spark.createDataFrame([(100 + i, t) for i, t in enumerate(texts)], "doc_id long, text string"))
    files = token_files.write_files(more, folder, spec, file_ids=2000, part_bytes=100_000)
    got = sorted(token_files.read_files(spark, folder).withColumn("list", token_files.ids_array("ids")).collect(), key=lambda r: r.start)
    from tokenizers import Tokenizer

    tool, start = Tokenizer.from_str(spec), 0
    held = sorted(((r.doc_id if r.doc_id is not None else -1, r.text is not None, r.text or "") for r in more.collect()))
    assert len(got) == len(held) and files.count() > 2
    for r, (i, _, t) in zip(got, held, strict=True):
        ids = tool.encode(t, add_special_tokens=False).ids + [0]
        assert ((r.doc_id if r.doc_id is not None else -1), r.start, r.n_tokens, r.list) == (i, start, len(ids), ids)
        start += len(ids)
    with pytest.raises(ValueError):
        token_files.write_files(odd, folder, spec)
    content = bytearray(open(files.orderBy("path").first()["path"].removeprefix("file://"), "rb").read())
    content[-20] ^= 255
    damaged = spark.createDataFrame([(content,)], "file binary").select(F.call_function("token_file_unpack", "file"))
    with pytest.raises(Exception, match="damaged"):
        damaged.collect()
    token_files.write_files(odd.limit(0), folder + "-empty", spec)
    assert token_files.read_files(spark, folder + "-empty").count() == 0


def test_encoder_meets_distinct_segments_once():
    class Counting(dict):
        asked = 0

        def get(self, key):
            self.asked += 1
            return super().get(key)

    tool = token_files.Encoder(registry.byte_tokenizer())
    tool.held = Counting()
    odd = ["", " ", "a ", "a  b", "x\n y", "\u3000 q", "\x85 z", "v\x0b w", "\x1f d", "m\n\nk \nn", "end<|endoftext|> it's", "d\u00e9j\u00e0 vu\n", "\u0120 \u0120", "y" * 99 + " " + "z" * 99]
    texts = odd + ["the cat and the dog and the end"] * 500
    data, sizes = tool.encode(pa.array(texts), 7)
    ids, at = np.frombuffer(data, np.uint32), np.concatenate(([0], np.cumsum(sizes)))
    for i, e in enumerate(tool.tool.encode_batch_fast(texts, add_special_tokens=False)):
        assert ids[at[i] : at[i + 1]].tolist() == e.ids + [7]
    assert at[-1] == len(ids) and tool.held.asked < 30
    parts = list(token_files._slices(pa.array(["ab", "", "c" * 50, "d", "e"]), 4))
    assert [(a, p.to_pylist()) for a, p in parts] == [(0, ["ab", ""]), (2, ["c" * 50]), (3, ["d", "e"])]
    assert list(token_files._slices(pa.array([], pa.string()), 4)) == []
    data, sizes = tool.encode(pa.array([""]), 7)
    assert np.frombuffer(data, np.uint32).tolist() == [7] and sizes.tolist() == [1]


def test_encoder_parts_marks_from_letters():
    tool = token_files.Encoder(registry.byte_tokenizer())
    texts = ["a erresten erresten. erresten,***", "a it's' it's. dogs'. 4.0. x\u00b2. \u65e5. \u00d7. \u00f7, \u00e9! \u024f? \u0250; \u2014. m\n\n. ... ?'s .'ll b"]
    data, sizes = tool.encode(pa.array(texts), 0)
    want = [i for t in texts for i in [*tool.tool.encode(t, add_special_tokens=False).ids, 0]]
    assert np.frombuffer(data, np.uint32).tolist() == want and sizes.sum() == len(want)
    assert "erresten" in tool.held and not {"erresten.", "erresten,***", "\u00e9!"} & set(tool.held) and {"4.0.", "\u00d7.", "dogs'."} <= set(tool.held)


def test_token_query(spark):
    from tokenizers import Tokenizer

    tool, start = Tokenizer.from_str(registry.byte_tokenizer()), 0
    docs = {r.doc_id: r.text or "" for r in spark.read.parquet(f"{SMALL}/documents.parquet").collect()}
    for r in sorted(registry.op7_token_files(spark, SMALL).collect()):
        ids = np.array(tool.encode(docs[r.doc_id], add_special_tokens=False).ids + [0], np.uint32)
        assert (r.start, r.n_tokens, r.ids_crc32) == (start, len(ids), zlib.crc32(ids.tobytes()))
        start += len(ids)


def test_language(spark, odd):
    got = registry.op8_language(spark, MIDDLE).join(spark.read.parquet(f"{MIDDLE}/documents.parquet").select("doc_id", "lang"), "doc_id").where("held_out").collect()
    assert np.mean([r.lang == r.lang_pred for r in got]) > 0.97
    model = language.fit(odd, sample_rows=20)
    assert model.predict(None) == ("und", 0.0) and model.predict("12 34!") == ("und", 0.0) and model.languages == ["en"]
    assert language.fit(odd.limit(0)).predict("words") == ("und", 0.0)


def test_language_gate(spark):
    import corpus_pipeline as c

    docs = spark.read.parquet(f"{MIDDLE}/documents.parquet").select(*c.COLUMNS)
    rng = np.random.default_rng(1)
    letters = ["".join(rng.choice(list("abcdefghijklmnopqrstuvwxyz   "), 300)) for _ in range(10)]
    mixed = ["".join(rng.choice(list("abcdefghijklmnopqrstuvwxyzABCDEFGHIJKLMNOPQRSTUVWXYZ0123456789+/"), 400)) for _ in range(10)]
    foreign = ["съешь ещё этих мягких французских булок, да выпей чаю", "これは日本語の文章です。言語を識別できません。", "Η γρήγορη καφέ αλεπού πηδάει πάνω από το σκυλί"]
    bad = [(10_000 + i, t, None, "s", len(t)) for i, t in enumerate(letters + mixed + foreign)]
    clean = docs.where("n_chars > 500 AND NOT text RLIKE '!!|%%%'").orderBy("doc_id").limit(200).withColumn("doc_id", F.col("doc_id") + 20_000).withColumn("lang", F.lit(None).cast("string"))
    kept = {r.doc_id for r in c.language(spark, docs.unionByName(spark.createDataFrame(bad, docs.schema)).unionByName(clean), MIDDLE).select("doc_id").collect()}
    assert not [i for i in kept if 10_000 <= i < 20_000]
    assert sum(i >= 20_000 for i in kept) >= 196 and sum(i < 10_000 for i in kept) >= 960


def test_decontamination(spark, odd):
    docs = spark.read.parquet(f"{MIDDLE}/documents.parquet").select("doc_id", "text")
    bench = spark.read.parquet(f"{MIDDLE}/benchmark.parquet")
    space = decontaminate.fit(docs)
    got = {(r.doc_id, x.item_id) for r in decontaminate.leaks(docs, bench, space=space).collect() for x in r.leaks}
    items = decontaminate._words([r.text.encode() for r in bench.orderBy("item_id").collect()])
    ids = [r.item_id for r in bench.orderBy("item_id").collect()]
    held = decontaminate._words([r.text.encode() for r in docs.orderBy("doc_id").collect()])
    expected = set()
    for i in range(len(ids)):  # brute force: every document against every item that shares enough words with it
        own = items.hash[items.first[i] : items.first[i + 1]].tolist()
        mask, full = decontaminate._masks(own)
        for d in range(len(held.first) - 1):
            at = held.hash[held.first[d] : held.first[d + 1]]
            if np.isin(own, at).mean() < 0.95:
                continue
            at = at.tolist()
            if any(decontaminate.common(mask, full, at[p : p + len(own) + 8]) >= 0.95 * len(own) for p in range(0, len(at), 4)):
                expected.add((d, ids[i]))
    assert len(expected & got) >= 0.9 * len(expected) and len(got - expected) <= 0.05 * len(got) + 1
    blocks = decontaminate.leaks(docs, bench, space=space, block=7)
    assert {(r.doc_id, x.item_id) for r in blocks.collect() for x in r.leaks} == got
    assert decontaminate.leaks(odd, bench.limit(0)).where(F.size("leaks") > 0).count() == 0
    assert decontaminate.leaks(odd.limit(0), bench).count() == 0


def test_latent_space_covers_all_documents(spark):
    rare = [[f"rare{i}x{j}" for j in range(30)] for i in range(10)]  # ten sources of one document each, among 20,000
    texts = [" ".join(words(i, 12)) for i in range(20_000)]
    texts[::2000] = [" ".join(words(i, 40) + w + words(i + 50, 40)) for i, w in enumerate(rare)]
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string").repartition(8)
    space = decontaminate.fit(docs)
    hashes = decontaminate._words([" ".join(w).encode() for w in rare]).hash
    assert (np.linalg.norm(space.vectors(hashes), axis=1) > 0).all()
    items = decontaminate.prepare([(i, " ".join("changed" if j % 6 == 1 else x for j, x in enumerate(w))) for i, w in enumerate(rare)], space)
    found = decontaminate.search([t.encode() for t in texts[::2000]], space, items)
    assert [[x["item_id"] for x in f] for f in found] == [[i] for i in range(10)]


def test_verbatim_passages_are_found_at_every_offset(spark):
    space = decontaminate.fit(spark.createDataFrame([(i, " ".join(words(i, 80))) for i in range(400)], "doc_id long, text string"))
    sizes = (1, 2, 3, 5, 7, 8, 9, 15, 16, 17, 24, 32, 48, 63, 64, 65, 100, 150)
    items = [(n, " ".join(f"own{n}" if i == n // 2 else w for i, w in enumerate(words(900 + n, n)))) for n in sizes]
    ready = decontaminate.prepare(items, space)
    texts = [" ".join(words(500 + o, 100 + o) + [t] + words(600 + o, 100)).encode() for _, t in items for o in range(8)]
    found = [{x["item_id"]: x["lcs"] for x in f} for f in decontaminate.search(texts, space, ready)]
    assert [n for n in sizes for _ in range(8)] == [n for n, f in zip(np.repeat(sizes, 8).tolist(), found, strict=True) if f.get(n) == 1.0]


def test_a_leaking_place_wins(spark):
    space = decontaminate.fit(spark.createDataFrame([(i, " ".join(words(i, 80))) for i in range(400)], "doc_id long, text string"))
    item = words(77, 40)
    no_answer = item[:30]  # a share of 0.75 without the answer
    answer = item[:6] + ["x"] * 2 + item[16:]  # a share of 0.75 less 2 words, with the answer
    answer.pop(8)
    text = " ".join(no_answer + words(78, 300) + answer)
    found = decontaminate.search([text.encode()], space, decontaminate.prepare([(1, " ".join(item))], space))
    assert [(x["item_id"], x["answer"]) for x in found[0]] == [(1, 1.0)]


def test_reworded_passages_are_found(spark):
    docs = spark.read.parquet(f"{MIDDLE}/documents.parquet").select("doc_id", "text")
    items = [(r.item_id, r.text) for r in spark.read.parquet(f"{MIDDLE}/benchmark.parquet").collect()]
    space = decontaminate.fit(docs)
    ready, rng = decontaminate.prepare(items, space), np.random.default_rng(3)
    host = docs.limit(100).collect()
    hits = 0
    for n in range(100):
        item, body = items[n % len(items)], host[n].text.split()
        w = [x if rng.random() > 0.15 else body[int(rng.integers(len(body)))] for x in item[1].split()]
        p = int(rng.integers(len(body)))
        hits += any(x["item_id"] == item[0] for x in decontaminate.search([" ".join(body[:p] + w + body[p:]).encode()], space, ready)[0])
    assert hits >= 90


def test_nearest(spark):
    rows = spark.read.parquet(f"{MIDDLE}/embeddings.parquet")
    got = registry.op10_nearest(spark, MIDDLE).collect()
    x = rows.orderBy("vec_id").toPandas()
    v, ids = np.stack(x.embedding).astype(float), x.vec_id.to_numpy()
    found = collections.defaultdict(dict)
    for r in got:
        found[r.query_id][r.rank] = (r.vec_id, r.score)
    recall = []
    for q in ids[ids % 20 == 0]:
        s = v @ v[ids == q][0]
        s[ids == q] = -9
        best = ids[np.lexsort((ids, -s))[:20]]
        assert sorted(found[q]) == list(range(1, 21))
        assert all(abs(s[ids == i][0] - sc) < 1e-12 for i, sc in found[q].values())
        recall.append(len({i for i, _ in found[q].values()} & set(best)) / 20)
    assert np.mean(recall) >= 0.95


def test_nearest_odd_vectors(spark):
    rows = [(1, [1.0, 0.0]), (2, [0.9, 0.1]), (2, [0.9, 0.1]), (3, None), (4, [0.0, 0.0]), (5, [float("nan"), 1.0]), (6, [None, 1.0]), (7, [1.0, 0.0]), (8, [1.0, 2.0, 3.0]), (9, [5.0, 5.0])]
    pts = spark.createDataFrame(rows, "id long, v array<double>")
    got = hnsw.nearest(hnsw.index(pts), pts.where("id IN (1, 3, 8)"), 5).orderBy("query_id", "rank").collect()
    assert [(r.query_id, r["rank"], r.id) for r in got] == [(1, 1, 9), (1, 2, 7), (1, 3, 2)]
    assert hnsw.nearest(hnsw.index(pts.limit(0)), pts, 5).count() == 0


def test_packing():
    x = np.sort(np.random.default_rng(0).integers(0, 2**63, 500).astype(np.uint64))
    assert (packing.unpack(packing.pack(x), np.uint64) == x).all() and len(packing.unpack(packing.pack(x[:0]), np.uint64)) == 0
    assert packing.at_most_two(np.array([1, 1, 1, 2, 3, 3], np.uint64)).tolist() == [1, 1, 2, 3, 3]
    assert packing.twice(np.array([1, 1, 1, 2, 3, 3], np.uint64)).tolist() == [1, 3]


def test_pipeline(spark, odd, tmp_path):
    import corpus_pipeline as c

    docs = spark.read.parquet(f"{SMALL}/documents.parquet")
    kept = {r.doc_id for r in docs.collect()}
    for name, stage in c.STAGES:
        out = stage(spark, docs, SMALL)
        out.write.parquet(str(tmp_path / name))
        docs = spark.read.parquet(str(tmp_path / name))
        now = {r.doc_id for r in docs.select("doc_id").collect()}
        assert now <= kept and len(now) == docs.count()
        if name != "tokens":
            assert docs.columns == c.COLUMNS
        kept = now
    assert docs.where("NOT parity OR NOT round_trip").count() == 0 and len(kept) > 150
    near = brute_classes([(r.doc_id, r.text) for r in spark.read.parquet(str(tmp_path / "language")).collect()])
    assert {r.doc_id for r in spark.read.parquet(str(tmp_path / "near_duplicates")).collect()} == set(near.values())
    empty = spark.read.parquet(f"{SMALL}/documents.parquet").limit(0)
    for _, stage in c.STAGES:
        assert stage(spark, empty, SMALL).count() == 0
