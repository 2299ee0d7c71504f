"""Document quality by compression against two dictionaries.

One zstandard dictionary is trained on text labelled good, one on text labelled bad. A document is
compressed with each. The difference of the two sizes over the document's own size says which it
resembles; with the compressed size over the own size (text that repeats itself compresses too well
for its resemblance to count) it goes through a logistic calibration fitted on labelled rows that no
dictionary has seen.

Fitting takes a bounded sample: at most ``sample_rows`` rows of each class for the dictionaries and as
many again for the calibration, of texts of at most ``longest`` bytes. Scoring takes every whole text.

Null texts score as empty ones do. If a class has no labelled rows, or too few labelled texts to train
and calibrate on (``documents`` empty, say), every score is the share of good rows among the labelled, or
0.5 without any. Rows that repeat are scored alike; no order matters.
"""

from __future__ import annotations

import math
from dataclasses import dataclass, field

import numpy as np
import pandas as pd
import zstandard
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .sampling import bounded
from .session import small_batches

SAMPLE_ROWS = 1500
LONGEST = 64 << 10
DICTIONARY_BYTES = 112_640  # what zstandard's own trainer takes by default
LEVEL = 3


def _dictionary(samples: list[bytes], size: int) -> bytes:
    """A trained dictionary; with too little text to train on, the text itself."""
    try:
        return zstandard.train_dictionary(min(size, max(4096, sum(map(len, samples)) // 8)), samples).as_bytes()
    except zstandard.ZstdError:
        return b"\n".join(samples)[-size:]


def _compressor(data: bytes, level: int):
    if not data:
        return zstandard.ZstdCompressor(level=level)
    kind = zstandard.ZstdCompressionDict(data)
    kind.precompute_compress(level=level)
    return zstandard.ZstdCompressor(level=level, dict_data=kind)


@dataclass
class CompressionClassifier:
    good: bytes = b""
    bad: bytes = b""
    weights: list[float] = field(default_factory=lambda: [0.0, 0.0, 0.0])
    centre: list[float] = field(default_factory=lambda: [0.0, 0.0])
    spread: list[float] = field(default_factory=lambda: [1.0, 1.0])
    level: int = LEVEL

    def _tools(self):
        if "_held" not in self.__dict__:
            self._held = _compressor(self.good, self.level), _compressor(self.bad, self.level)
        return self._held

    def __getstate__(self):
        return {k: v for k, v in self.__dict__.items() if k != "_held"}

    def features(self, text: bytes) -> tuple[float, float]:
        """The normalised difference of compressed sizes, and the log of the better ratio."""
        good, bad = (len(x.compress(text)) for x in self._tools())
        own = len(text) + 1
        return (bad - good) / own, math.log(min(good, bad) / own)

    def fit_calibration(self, texts: list[bytes], labels: list[int]) -> None:
        x, y = np.array([self.features(t) for t in texts]), np.array(labels, float)
        centre, spread = x.mean(0), x.std(0) + 1e-9
        z, w = np.c_[(x - centre) / spread, np.ones(len(x))], np.zeros(3)
        w[2] = math.log((y.sum() + 1) / (len(y) - y.sum() + 1))
        for _ in range(50):
            p = 1 / (1 + np.exp(-np.clip(z @ w, -30, 30)))
            ridge = np.diag([0.1, 0.1, 1e-6])
            step = np.linalg.solve((z * (p * (1 - p))[:, None]).T @ z + ridge, z.T @ (y - p) - ridge @ w)
            w = w + np.clip(step, -2, 2)
            if np.abs(step).max() < 1e-8:
                break
        self.centre, self.spread, self.weights = centre.tolist(), spread.tolist(), w.tolist()

    def score(self, text: bytes) -> float:
        if not (self.good and self.bad):
            return 1 / (1 + math.exp(-self.weights[2]))
        x = self.features(text)
        z = self.weights[2] + sum(w * (v - c) / s for w, v, c, s in zip(self.weights, x, self.centre, self.spread, strict=False))
        return 1 / (1 + math.exp(-max(-30.0, min(30.0, z))))

    def column(self, text: str) -> Column:
        """The score of a text column, as a column."""
        model = self

        @F.pandas_udf("double")
        def score(texts: pd.Series) -> pd.Series:
            return pd.Series([model.score(b"" if t is None else t.encode("utf-8", "surrogatepass")) for t in texts], dtype="float64")

        return score(F.col(text))


def fit(docs: DataFrame, labels: DataFrame, usable: Column | None = None, label: str = "quality", sample_rows: int = SAMPLE_ROWS, longest: int = LONGEST, dictionary_bytes: int = DICTIONARY_BYTES) -> CompressionClassifier:
    """A classifier from the labelled rows; ``usable`` says which rows may be learned from."""
    small_batches(docs)
    known = labels.select("doc_id", label).where(F.col("doc_id").isNotNull())
    if usable is not None:
        known = known.where(usable)
    counts = {r[label]: r["n"] for r in known.groupBy(label).agg(F.count("*").alias("n")).collect() if r[label] in (0, 1)}
    model = CompressionClassifier()
    if len(counts) < 2:
        return _by_share(model, counts)
    chosen = bounded(known, label, [0, 1], 2 * sample_rows).dropDuplicates(["doc_id"])  # 4 * sample_rows rows at most
    rows = docs.where(F.octet_length("text") <= longest).select("doc_id", "text").join(F.broadcast(chosen), "doc_id")
    texts = {r["doc_id"]: (r["text"].encode("utf-8", "surrogatepass"), r[label]) for r in rows.collect()}
    halves: dict = {(k, v): [] for k in (0, 1) for v in (0, 1)}
    for n, (t, v) in enumerate(texts[i] for i in sorted(texts)):
        halves[n % 2, v].append(t)
    if not all(halves.values()):
        return _by_share(model, counts)
    model.good, model.bad = _dictionary(halves[0, 1], dictionary_bytes), _dictionary(halves[0, 0], dictionary_bytes)
    model.fit_calibration(halves[1, 1] + halves[1, 0], [1] * len(halves[1, 1]) + [0] * len(halves[1, 0]))
    model.weights[2] += _prior_shift(counts, len(halves[1, 1]), len(halves[1, 0]))
    return model


def _by_share(model: CompressionClassifier, counts: dict) -> CompressionClassifier:
    """The model that gives every text the share of good rows."""
    share = (counts.get(1, 0) / sum(counts.values())) if counts else 0.5
    model.weights[2] = max(-30.0, min(30.0, math.log((share + 1e-9) / (1 - share + 1e-9))))
    return model


def _prior_shift(counts: dict, good: int, bad: int) -> float:
    """From the classes' shares in the sample to those among all labelled rows, on the log odds."""
    return math.log(((counts[1] + 1) / (counts[0] + 1)) / ((good + 1) / (bad + 1)))
