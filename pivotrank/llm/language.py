"""Language of a text: sparse multinomial logistic regression on TF-IDF character n-grams.

Lower-cased text is cut into n-grams of one to three characters, hashed into ``dims`` features. A
feature's weight is its count times the log inverse document frequency over all training rows; the
vector has length one. Weights are trained with follow-the-regularised-leader (per-coordinate rates,
elastic net: L1 makes them sparse, L2 keeps them small), then one temperature is fitted on a part of
the sample that training has not seen. The same part gives ``least``, the odds from which
a text counts as identified: the log odds of its best language against the second, which unlike scores
do not saturate, are reached by all but LOST of the rightly told texts there. Besides, its score lies at
least half way from chance to certainty. With one language only ``und`` can be turned away.

Document frequencies come from every training row. Training takes a bounded sample: at most
``sample_rows`` rows of each language, of texts of at most ``longest`` bytes.

A null text, or one without letters, gets ``und`` with score 0, as every text does when there is
nothing to learn from. Ties go to the language that sorts first.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pandas as pd
import pyarrow as pa
import regex
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .memory import release, trimmed
from .sampling import bounded
from .session import small_batches

SAMPLE_ROWS = 800
LONGEST = 64 << 10
BITS = 16
LOST = 0.02
_BLOCK = 4096
_LETTER = regex.compile(r"\p{L}")


def grams(text: str, bits: int = BITS) -> np.ndarray:
    """Counts of the hashed n-grams of a text."""
    c = np.frombuffer(text.lower().encode("utf-32-le", "surrogatepass"), np.uint32) + np.uint32(1)
    one = c * np.uint32(2654435761)
    shift = np.uint32(32 - bits)
    out = np.bincount(one >> shift, minlength=1 << bits)
    if len(c) > 1:
        two = (one[:-1] ^ np.uint32(0x5BD1E995)) * np.uint32(2246822519) + one[1:]
        out += np.bincount((two * np.uint32(3266489917)) >> shift, minlength=1 << bits)
        if len(c) > 2:
            three = (two[:-1] ^ (two[:-1] >> np.uint32(15))) * np.uint32(668265263) + one[2:]
            out += np.bincount((three * np.uint32(374761393)) >> shift, minlength=1 << bits)
    return out


def _softmax(z: np.ndarray) -> np.ndarray:
    e = np.exp(z - z.max())
    return e / e.sum()


def document_frequencies(docs: DataFrame, text: str, bits: int) -> tuple[int, np.ndarray]:
    """Texts, and in how many of them each feature occurs. Tasks send blocks of counts, not rows."""
    name = text

    def count(batches):
        held, n = np.zeros(1 << bits, np.int64), 0
        for batch in batches:
            for t in batch.column(0).to_pylist():
                if t:
                    held[np.flatnonzero(grams(t, bits))] += 1
                    n += 1
        blocks = held.reshape(-1, _BLOCK)
        yield pa.RecordBatch.from_pydict({"block": pa.array(range(len(blocks)), pa.int32()), "n": pa.array([n] + [0] * (len(blocks) - 1), pa.int64()), "counts": pa.array([b.tobytes() for b in blocks], pa.binary())})

    def add(table: pa.Table) -> pa.Table:
        total = np.zeros(_BLOCK, np.int64)
        for x in table["counts"]:
            total += np.frombuffer(x.as_py(), np.int64)
        return pa.table({"block": table["block"][:1], "n": pa.array([sum(table["n"].to_pylist())], pa.int64()), "counts": pa.array([total.tobytes()], pa.binary())})

    kind = "block int, n long, counts binary"
    few = docs.select(name).mapInArrow(trimmed(count), kind)
    some = few.groupBy("block", F.pmod(F.spark_partition_id(), F.lit(64))).applyInArrow(add, kind)  # tasks are added up in 64 lots first
    rows = some.groupBy("block").applyInArrow(add, kind).collect()  # 2 ** bits counts, whatever the input
    out = np.zeros(((1 << bits) // _BLOCK, _BLOCK), np.int64)
    for r in rows:
        out[r["block"]] = np.frombuffer(r["counts"], np.int64)
    return sum(r["n"] for r in rows), out.ravel()


@dataclass
class LanguageModel:
    languages: list[str]
    idf: np.ndarray
    weights: np.ndarray  # features by languages
    bias: np.ndarray
    temperature: float = 1.0
    bits: int = BITS
    least: float = 0.0

    def vector(self, text: str) -> tuple[np.ndarray, np.ndarray]:
        counts = grams(text, self.bits)
        at = np.flatnonzero(counts)
        x = counts[at] * self.idf[at]
        return at, x / (np.sqrt(x @ x) or 1.0)

    def predict(self, text: str | None) -> tuple[str, float]:
        if not text or not self.languages or not _LETTER.search(text):
            return "und", 0.0
        at, x = self.vector(text)
        p = _softmax((x @ self.weights[at] + self.bias) / self.temperature)
        best = int(np.argmax(p))
        return self.languages[best], float(p[best])

    def odds(self, text: str) -> float:
        """Calibrated log odds of the best language against the second; 0 where there is no second."""
        at, x = self.vector(text)
        z = np.sort(x @ self.weights[at] + self.bias)
        return float(z[-1] - z[-2]) / self.temperature if len(z) > 1 else 0.0

    def sure(self, text: str | None) -> bool:
        lang, score = self.predict(text)
        return lang != "und" and score >= (1 + 1 / len(self.languages)) / 2 and self.odds(text) >= self.least

    def identified(self, text: str) -> Column:
        """Whether the language of a text column can be told."""
        model = self

        @F.pandas_udf("boolean")
        def identified(texts: pd.Series) -> pd.Series:
            return pd.Series([model.sure(t) for t in texts], dtype=bool)

        return identified(F.col(text))

    def column(self, text: str) -> Column:
        """struct<lang, score> of a text column."""
        model = self

        @F.pandas_udf("lang string, score double")
        def identify(texts: pd.Series) -> pd.DataFrame:
            return pd.DataFrame([model.predict(t) for t in texts], columns=["lang", "score"])

        return identify(F.col(text))


def train(model: LanguageModel, texts: list[tuple[str, str]], epochs: int = 4, alpha: float = 1.0, beta: float = 1.0, l1: float = 0.02, l2: float = 0.02, seed: int = 3) -> None:
    """Follow-the-regularised-leader over the texts, shuffled by a seed in each epoch."""
    size = (len(model.idf), len(model.languages))
    z, n, zb, nb = np.zeros(size), np.zeros(size), np.zeros(size[1]), np.zeros(size[1])
    vectors = [(at.astype(np.int32), x.astype(np.float32), model.languages.index(lang)) for (at, x), lang in ((model.vector(t), lang) for t, lang in texts)]
    solve = lambda z, n, l1: np.where(np.abs(z) <= l1, 0.0, -(z - np.sign(z) * l1) / ((beta + np.sqrt(n)) / alpha + l2))
    rng = np.random.default_rng(seed)
    for _ in range(epochs):
        for i in rng.permutation(len(vectors)):
            at, x, y = vectors[i]
            w, b = solve(z[at], n[at], l1), solve(zb, nb, 0.0)
            error = _softmax(x @ w + b)
            error[y] -= 1
            for g, held, total, value, where in ((x[:, None] * error, z, n, w, at), (error, zb, nb, b, slice(None))):
                old = total[where]
                new = old + g * g
                held[where] += g - (np.sqrt(new) - np.sqrt(old)) / alpha * value
                total[where] = new
    model.weights, model.bias = solve(z, n, l1), solve(zb, nb, 0.0)


def fit_temperature(model: LanguageModel, texts: list[tuple[str, str]]) -> None:
    """The temperature of least log loss on texts that training has not seen."""
    if not texts:
        return
    logits = np.array([x @ model.weights[at] + model.bias for at, x in (model.vector(t) for t, _ in texts)])
    y = np.array([model.languages.index(lang) for _, lang in texts])

    def loss(t: float) -> float:
        z = logits / t
        z = z - z.max(1, keepdims=True)
        return float(np.mean(np.log(np.exp(z).sum(1)) - z[np.arange(len(y)), y]))

    model.temperature = min(np.geomspace(0.02, 5, 120), key=loss)


def fit_least(model: LanguageModel, texts: list[tuple[str, str]]) -> None:
    """The least odds of an identified text, from texts that training has not seen."""
    right = [model.odds(t) for t, lang in texts if model.predict(t)[0] == lang]
    model.least = float(np.quantile(right, LOST)) if right else 0.0


def fit(docs: DataFrame, usable: Column | None = None, sample_rows: int = SAMPLE_ROWS, longest: int = LONGEST, bits: int = BITS, most: int = 1000) -> LanguageModel:
    """A model from text and lang; ``usable`` says which rows may be learned from, ``most`` how many languages it tells apart at most (the most frequent)."""
    small_batches(docs)
    known = docs.where(F.col("lang").isNotNull() & F.col("text").isNotNull())
    if usable is not None:
        known = known.where(usable)
    languages = sorted(r["lang"] for r in known.groupBy("lang").count().orderBy(F.desc("count"), "lang").limit(most).select("lang").collect())
    empty = LanguageModel([], np.ones(1 << bits), np.zeros((1 << bits, 0)), np.zeros(0), bits=bits)
    if not languages:
        return empty
    n, held = document_frequencies(known, "text", bits)
    ids = bounded(known.where(F.octet_length("text") <= longest).select("doc_id", "lang"), "lang", languages, sample_rows).select("doc_id").distinct()
    rows = known.select("doc_id", "text", "lang").join(F.broadcast(ids), "doc_id").where(F.octet_length("text") <= longest)
    texts = {r["doc_id"]: (r["text"], r["lang"]) for r in rows.toLocalIterator()}
    texts = [texts[i] for i in sorted(texts) if _LETTER.search(texts[i][0])]
    model = LanguageModel(languages, np.log((1 + n) / (1 + held)) + 1, empty.weights, empty.bias, bits=bits)
    if not texts:
        return empty
    train(model, [t for i, t in enumerate(texts) if i % 5])
    fit_temperature(model, texts[::5])
    fit_least(model, texts[::5])
    texts.clear()
    release()
    return model
