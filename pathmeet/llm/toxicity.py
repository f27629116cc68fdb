"""Toxicity by compression distance: windows of a text against two trained Zstandard dictionaries.

Both classes share a base dictionary, trained on a quarter of the ordinary training texts.
On top of it the ordinary dictionary is trained on windows of another quarter, and the
toxic one on windows of toxic texts. A window of a few words is compressed with both; the
bytes that the toxic dictionary saves are the window's distance.

Most windows of a toxic text are ordinary, so toxic windows are found by cross-fitting:
the toxic texts are split into parts, each part's windows are measured with a dictionary
trained on the windows of the other parts, and only those whose distance is beyond the
``RARE`` quantile of untouched ordinary windows train the next round's dictionaries. What
recurs across toxic texts is kept; what a dictionary has merely seen before is not.

A text's score comes from the distances of all its windows by a logistic calibration on the other
half of the ordinary texts and the toxic ones. These are dealt into ``FOLDS`` folds with a toxic
dictionary each, trained without the fold's texts. A fold's features come from its own dictionary, and the size of the
class dictionaries, the ridge and the cut (shifted to ``threshold``) are chosen on these out-of-fold
scores; other texts get the mean over the dictionaries. Held-out rows are never looked at.

Defined results: null, empty and blank texts get the score of a text whose windows save
nothing. Very long texts are scored whole. Labels of held-out rows, language, source and id
are never read by a score; equal texts get equal scores. If the training rows lack a class,
every score is the share of toxic rows (0 without rows). Empty tables give empty results.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterable

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from pathmeet.llm.labelled import fit_logistic, held_out, logit, sigmoid, training_sample

#: Words in a window, and the byte that stands around words.
WINDOW_WORDS, MARK = 4, b"~"
#: Bytes of the common base, and of the class dictionaries that are tried.
BASE_BYTES, CLASS_BYTES = 1 << 16, (1024, 2048)
#: Folds of the calibration, each with its own toxic dictionary.
FOLDS = 3
#: Parts and rounds of the cross-fitting, the quantile of ordinary distances that a toxic window exceeds, and most windows of a training.
PARTS, ROUNDS, RARE, MOST_WINDOWS = 4, 5, 0.99, 40_000
#: Ridges tried in the calibration.
RIDGES = (0.1, 1.0, 10.0, 100.0)
#: Bytes that separate words here: everything in ASCII but letters.
APART = bytes(b for b in range(128) if not (0x41 <= b <= 0x5A or 0x61 <= b <= 0x7A))
TO_SPACE = bytes.maketrans(APART, b" " * len(APART))
FEATURES = 7


def words_of(text: str) -> list[bytes]:
    return text.encode().lower().translate(TO_SPACE).split()


def windows(words: list[bytes]) -> list[bytes]:
    return [MARK + MARK.join(words[i : i + WINDOW_WORDS]) + MARK for i in range(0, len(words), WINDOW_WORDS)]


def shuffled(found: Iterable[bytes]) -> list[bytes]:
    """Distinct windows in the order of a checksum, at most ``MOST_WINDOWS``."""
    return sorted(set(found), key=lambda w: (zlib.crc32(w), w))[:MOST_WINDOWS]


def trained(samples: list[bytes], size: int) -> bytes:
    """A Zstandard dictionary of about ``size`` bytes for the samples; the samples themselves where they are too few to train on."""
    import zstandard

    if sum(map(len, samples)) > 2 * size:
        try:
            return zstandard.train_dictionary(size, samples, k=16, d=6).as_bytes()
        except zstandard.ZstdError:
            pass
    return b"".join(samples)[:size]


def compressor(content: bytes):
    """Compressor of short windows with a dictionary; matches shorter than six bytes are noise of common syllables."""
    import zstandard

    held = zstandard.ZstdCompressionDict(content, dict_type=zstandard.DICT_TYPE_RAWCONTENT)
    parameters = zstandard.ZstdCompressionParameters.from_level(
        1, min_match=6, hash_log=17, window_log=18, strategy=zstandard.STRATEGY_FAST,
        format=zstandard.FORMAT_ZSTD1_MAGICLESS, write_content_size=False, write_checksum=False, write_dict_id=False,
    )
    held.precompute_compress(compression_params=parameters)
    return zstandard.ZstdCompressor(dict_data=held, compression_params=parameters)


def lengths(content: bytes, cut: list[bytes]) -> np.ndarray:
    compress = compressor(content).compress
    return np.fromiter((len(compress(w)) for w in cut), np.int64, len(cut))


def features(distance: np.ndarray, rare: float) -> list[float]:
    """What a text's score reads of the distances of its windows."""
    if not len(distance):
        return [0.0] * FEATURES
    top = np.sort(distance)[::-1][:4]
    beyond = distance > rare
    return [
        float(top[0]), float(top[:2].mean()), float(top.mean()), float(distance.mean()),
        float(np.log1p(beyond.sum())), float(np.log(len(distance))), float(beyond.mean()),
    ]


class Ordinary:
    """The base and the ordinary dictionaries of any size, and the ordinary windows that neither has seen."""

    def __init__(self, texts: list[list[bytes]], others: list[list[bytes]]):
        mine, self.own = (shuffled(w for t in texts[i::2] for w in windows(t)) for i in range(2))
        self.base, self.usual = trained(mine, BASE_BYTES), set(mine) | set(self.own)
        self.untouched = shuffled(w for t in others for w in windows(t))[: MOST_WINDOWS // 2]
        self.held: dict[int, tuple[bytes, np.ndarray]] = {}

    def of(self, size: int) -> tuple[bytes, np.ndarray]:
        """The dictionary with ``size`` bytes beside the base, and the lengths of the untouched windows with it."""
        if size not in self.held:
            content = self.base + trained(self.own, size)
            self.held[size] = content, lengths(content, self.untouched)
        return self.held[size]

    def rare(self, size: int, toxic: bytes) -> float:
        """The distance that few ordinary windows exceed."""
        return float(np.quantile(self.of(size)[1] - lengths(toxic, self.untouched), RARE)) if self.untouched else 0.0


def learn(ordinary: Ordinary, toxic: list[list[bytes]], size: int) -> tuple[bytes, float]:
    """The toxic dictionary for the words of toxic texts, and the distance that few ordinary windows exceed."""
    parts = [[w for w in shuffled(w for t in toxic[i::PARTS] for w in windows(t)) if w not in ordinary.usual] for i in range(PARTS)]
    chosen = parts
    for turn in range(ROUNDS):
        now = max(size, 8192 >> (2 * turn))  # wide at first, then as narrow as the result
        plain, kept = ordinary.of(now)[0], []
        for i, own in enumerate(parts):
            other = ordinary.base + trained([w for j, part in enumerate(chosen) if j != i for w in part], now)
            rare = ordinary.rare(now, other)
            kept.append([w for w, d in zip(own, lengths(plain, own) - lengths(other, own), strict=True) if d > rare])
        if sum(map(len, kept)) < 4 * PARTS:
            break
        chosen = kept
    other = ordinary.base + trained([w for part in chosen for w in part], size)
    return other, ordinary.rare(size, other)


class CompressionDistance:
    """The dictionaries and the calibration; plain data, so it ships to executors."""

    def __init__(self, base: float = 0.0):
        self.ordinary = b""
        self.toxic: list[tuple[bytes, float]] = []
        self.mean = self.scale = self.weights = None
        self.shift, self.base = 0.0, base
        self.ready = None

    def __getstate__(self):
        return self.__dict__ | {"ready": None}

    def distances(self, words: list[bytes]) -> list[np.ndarray]:
        """For each toxic dictionary, the bytes that it saves in each window."""
        if self.ready is None:
            self.ready = [compressor(x) for x in (self.ordinary, *(content for content, _ in self.toxic))]
        cut = windows(words)
        found = [np.fromiter((len(c.compress(w)) for w in cut), np.int64, len(cut)) for c in self.ready]
        return [found[0] - x for x in found[1:]]

    def score(self, texts: list[str | None]) -> np.ndarray:
        if self.weights is None:
            return np.full(len(texts), self.base)
        each = [self.distances(words_of(t or "")) for t in texts]
        total = np.zeros(len(texts))
        for i, (_, rare) in enumerate(self.toxic):
            x = np.array([features(d[i], rare) for d in each]).reshape(len(texts), FEATURES)
            total += np.c_[(x - self.mean) / self.scale, np.ones(len(x))] @ self.weights
        return sigmoid(total / len(self.toxic) + self.shift)


def train(sample: list[tuple[str, int]], threshold: float = 0.3) -> CompressionDistance:
    """Trains on (text, toxic) rows; all choices are made on out-of-fold scores."""
    texts = sorted({t: (words_of(t), y) for t, y in sample}.values(), key=lambda r: zlib.crc32(b" ".join(r[0])))
    plain, toxic = ([w for w, y in texts if y == k] for k in (0, 1))
    if not plain or not toxic:
        return CompressionDistance(float(np.mean([y for _, y in sample])) if sample else 0.0)
    seen, unseen = plain[: len(plain) // 2], plain[len(plain) // 2 :]
    ordinary = Ordinary(seen, unseen)
    judged = [*unseen, *toxic]
    y = np.repeat([0, 1], [len(unseen), len(toxic)])
    fold = np.concatenate([np.arange(len(unseen)), np.arange(len(toxic))]) % FOLDS
    stands_for = len(plain) / len(unseen)  # ordinary texts that one judged text stands for
    tried = []
    for size in CLASS_BYTES:
        model = CompressionDistance()
        model.ordinary = ordinary.of(size)[0]
        model.toxic = [learn(ordinary, [w for w, f in zip(toxic, fold[len(unseen) :], strict=True) if f != k], size) for k in range(FOLDS)]
        x = np.array([features(model.distances(w)[k], model.toxic[k][1]) for w, k in zip(judged, fold.tolist(), strict=True)])
        model.mean, model.scale = x.mean(0), x.std(0) + 1e-9
        z = np.c_[(x - model.mean) / model.scale, np.ones(len(x))]
        for ridge in RIDGES:
            p = np.zeros(len(y))
            for k in range(FOLDS):
                p[fold == k] = sigmoid(z[fold == k] @ fit_logistic(z[fold != k], y[fold != k], ridge))
            p = np.clip(p, 1e-6, 1 - 1e-6)
            loss = -float((y * np.log(p) + (1 - y) * np.log(1 - p)).sum())
            tried.append((loss, size, ridge, p, z, model))
    _, _, ridge, p, z, model = min(tried, key=lambda t: t[:3])
    model.weights = fit_logistic(z, y, ridge)
    cuts = np.unique(np.quantile(p, np.linspace(0.02, 0.995, 196)))
    hits, alarms = np.array([(y[p >= c] == 1).sum() for c in cuts]), np.array([(y[p >= c] == 0).sum() for c in cuts]) * stands_for
    f1 = 2 * hits / np.maximum(1, hits + alarms + y.sum())
    model.shift = logit(threshold) - logit(float(cuts[int(np.argmax(f1))]))
    return model


def toxicity(model: CompressionDistance, text: Column) -> Column:
    @F.arrow_udf(T.DoubleType())
    def score(texts: pa.Array) -> pa.Array:
        return pa.array(model.score(texts.to_pylist()), pa.float64())

    return score(text)


def scored(
    spark: SparkSession, docs: DataFrame, labels: DataFrame, id_col: str = "doc_id", text_col: str = "text",
    threshold: float = 0.3, sample_rows: int = 2500, sample_chars: int = 20_000,
) -> DataFrame:
    """(id, held_out, score, predicted) of every document; ``sample_rows`` and ``sample_chars`` bound the fit."""
    model = train(training_sample(docs, labels, "toxic", sample_rows, sample_chars, id_col, text_col), threshold)
    out = docs.select(F.col(id_col), held_out(F.col(id_col)).alias("held_out"), toxicity(model, F.col(text_col)).alias("score"))
    return out.withColumn("predicted", (F.col("score") >= threshold).cast("int"))


def op9_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    return scored(spark, spark.read.parquet(f"{sf_dir}/documents.parquet"), spark.read.parquet(f"{sf_dir}/labels.parquet"))


QUERIES = {"op9_toxicity": op9_toxicity}
SQL: dict[str, str] = {}
