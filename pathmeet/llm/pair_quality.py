"""Quality by Bradley-Terry pairwise ranking.

Preference pairs are a preferred and a rejected labelled text. The probability that one is
preferred is the logistic function of the difference of their scores, scores are linear in
surface features, and so the weights come from logistic loss on feature differences.
The cut is a quantile of the training scores, chosen for balanced accuracy; a
calibrated logistic curve puts scores in 0..1 with that quantile at ``threshold``.

Defined results: null text counts as empty; empty and blank texts are scored like others
from features that are all zero. Labels of held-out rows, language, source and id are never
read by a score. If the training rows lack a class, every score is the share of preferred
rows (0 without rows).
"""

from __future__ import annotations

import zlib
from collections import Counter

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from pathmeet.llm.labelled import fit_logistic, held_out, logit, sigmoid, training_sample

#: Byte classes whose shares are features: capitals, small letters, digits, sentence marks, bars, other signs, other bytes.
CLASSES = np.full(256, 6)
CLASSES[0x41:0x5B], CLASSES[0x61:0x7B], CLASSES[0x30:0x3A] = 0, 1, 2
for _byte in range(0x21, 0x7F):
    if CLASSES[_byte] == 6:
        CLASSES[_byte] = 3 if chr(_byte) in ".,;:?'\"-()" else 4 if chr(_byte) in "|!" else 5
CLASSES[[0x20, *range(0x09, 0x0E)]] = 7
FEATURES = 26


def features(text: str | None) -> list[float]:
    """Shares of byte classes, repetition of words and lines, lengths; roots spread out small shares."""
    raw = (text or "").encode()
    words = raw.split()
    if not words:
        return [0.0] * FEATURES
    n = len(words)
    share = np.bincount(CLASSES[np.frombuffer(raw, np.uint8)], minlength=8) / len(raw)
    counts = Counter(words)
    lines = raw.split(b"\n")
    repeats = sum(map(bytes.__eq__, words, words[1:])) / n
    lengths = np.fromiter(map(len, words), np.int64, n)
    shouted = sum(w.isupper() for w in counts) / len(counts)
    variety = len(counts) / n
    top = counts.most_common(1)[0][1] / n
    again = 1 - len(set(lines)) / len(lines)
    small = [*share[:6], repeats, shouted, top, again]
    return [
        *small, *(float(np.sqrt(x)) for x in small), variety, float(np.log1p(n)), float(lengths.mean()) / 10,
        float((lengths <= 3).mean()), float(np.log1p(n / len(lines))), float(share[6]),
    ]


class PairRanker:
    """Weights, scaling and calibration; plain data, so it ships to executors."""

    def __init__(self) -> None:
        self.mean = self.scale = self.weights = None
        self.slope, self.at, self.base = 1.0, 0.0, 0.0

    def raw(self, x: np.ndarray) -> np.ndarray:
        return np.clip((x - self.mean) / self.scale, -6, 6) @ self.weights

    def score(self, texts: list[str | None]) -> np.ndarray:
        if self.weights is None:
            return np.full(len(texts), self.base)
        return sigmoid(self.slope * self.raw(np.array([features(t) for t in texts]).reshape(len(texts), FEATURES)) + self.at)


def preference_pairs(y: np.ndarray, most: int) -> tuple[np.ndarray, np.ndarray]:
    """(preferred, rejected) rows: every row of both classes in turn, each time against another partner."""
    good, bad = np.flatnonzero(y == 1), np.flatnonzero(y == 0)
    k = np.arange(min(most, len(good) * len(bad)))
    return good[k % len(good)], bad[(k + k // max(len(good), len(bad))) % len(bad)]


def train(sample: list[tuple[str, int]], threshold: float = 0.7, most_pairs: int = 40_000) -> PairRanker:
    """Fits the ranker to (text, preferred) rows."""
    sample = sorted(sample, key=lambda r: zlib.crc32(r[0].encode()))
    y = np.array([q for _, q in sample])
    model = PairRanker()
    if set(y.tolist()) != {0, 1}:
        model.base = float(y.mean()) if len(y) else 0.0
        return model
    x = np.array([features(t) for t, _ in sample])
    model.mean, model.scale = x.mean(0), x.std(0) + 1e-6
    z = np.clip((x - model.mean) / model.scale, -6, 6)
    good, bad = preference_pairs(y, most_pairs)
    difference = z[good] - z[bad]
    both = np.concatenate([difference, -difference])
    model.weights = fit_logistic(both, np.repeat([1.0, 0.0], len(difference)), ridge=1.0)
    s = model.raw(x)
    model.slope = max(1e-3, float(fit_logistic(np.c_[s, np.ones(len(s))], y)[0]))
    cuts = np.unique(np.quantile(s, np.linspace(0.005, 0.995, 199)))
    balanced = [((s >= c)[y == 1].mean() + (s < c)[y == 0].mean()) for c in cuts]
    model.at = logit(threshold) - model.slope * float(cuts[int(np.argmax(balanced))])
    return model


def quality(model: PairRanker, text: Column) -> Column:
    @F.arrow_udf(T.DoubleType())
    def score(texts: pa.Array) -> pa.Array:
        return pa.array(model.score(texts.to_pylist()), pa.float64())

    return score(text)


def scored(
    spark: SparkSession, docs: DataFrame, labels: DataFrame, id_col: str = "doc_id", text_col: str = "text",
    threshold: float = 0.7, sample_rows: int = 2500, sample_chars: int = 20_000,
) -> DataFrame:
    """(id, held_out, score, predicted) of every document; ``sample_rows`` and ``sample_chars`` bound the fit."""
    model = train(training_sample(docs, labels, "quality", sample_rows, sample_chars, id_col, text_col), threshold)
    out = docs.select(F.col(id_col), held_out(F.col(id_col)).alias("held_out"), quality(model, F.col(text_col)).alias("score"))
    return out.withColumn("predicted", (F.col("score") >= threshold).cast("int"))


def op5_pair_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    return scored(spark, spark.read.parquet(f"{sf_dir}/documents.parquet"), spark.read.parquet(f"{sf_dir}/labels.parquet"))


QUERIES = {"op5_pair_quality": op5_pair_quality}
SQL: dict[str, str] = {}
