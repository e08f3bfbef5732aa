"""Quality classifier with supervised subword embeddings.

Words and the character n-grams in them are hashed into a table of vectors, and one more
stands for a word that repeats the one before it; a document is the mean of its vectors, a softmax layer gives the classes. Vectors and layer are
learned together by stochastic gradient descent in numpy, on a bounded sample of
labelled documents (``MOST``), whole texts. As the layer is linear in the mean,
scoring needs one number for each hashed feature.

Defined results: a null or empty text has no features and scores by the bias alone;
without labels of both classes every score is the share of label 1 (one half if
there are no labels); repeated rows score alike; an empty table gives no rows; labels, lang,
source and doc_id enter no score; extra columns are ignored.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..plans.ship import map_arrow
from .labelled import remainder, sample, shares
from .textbatch import Words, code_points, expanded, slices, words

BUCKETS, DIMENSIONS, GRAMS = 1 << 17, 12, (3, 4, 5)
EPOCHS, RATE, MOST, SEED = 8, 0.6, 5000, 7
#: Bytes of text at once; the n-grams of its different words take some fifty times as much for a moment.
SLICE = 1 << 19
#: The feature of a word that is the one before it, and how many features it counts as.
REPEAT, REPEAT_WEIGHT = BUCKETS, 4
MODULUS, HELD_OUT, PREDICTED_FROM = 4, 2, 0.7

_MULTIPLIER = np.uint64(0x9E3779B97F4A7C15)


def _mix(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> np.uint64(32))) * np.uint64(0xD6E8FEB86659FD93)
    return x ^ (x >> np.uint64(32))


def word_features(vocabulary: pa.Array, buckets: int = BUCKETS, grams: tuple[int, ...] = GRAMS) -> tuple[np.ndarray, np.ndarray]:
    """Buckets of all words' features in one array, and each word's bounds in it: the word, and its n-grams between '<' and '>'."""
    flat, bounds = code_points(vocabulary)
    n = len(bounds) - 1
    lengths = np.diff(bounds) + 2
    ends = np.cumsum(lengths)
    begins = ends - lengths
    padded = np.zeros(int(ends[-1]) if n else 0, dtype=np.uint64)
    inner = expanded(begins + 1, lengths - 2)
    padded[inner] = flat
    padded[begins], padded[ends - 1] = ord("<"), ord(">")
    owner = np.repeat(np.arange(n), lengths)
    place = np.arange(len(padded)) - np.repeat(begins, lengths)
    # The whole word: a polynomial of its code points.
    powers = np.cumprod(np.full(int(lengths.max()) if n else 1, _MULTIPLIER, dtype=np.uint64))
    whole = np.add.reduceat(padded * powers[place], begins) if n else np.empty(0, dtype=np.uint64)
    owners, hashes = [np.arange(n)], [_mix(whole)]
    for size in grams:
        if len(padded) < size:
            continue
        starts = np.flatnonzero(owner[size - 1 :] == owner[: len(owner) - size + 1])
        key = np.full(len(starts), size, dtype=np.uint64)
        for k in range(size):
            key = key * _MULTIPLIER + padded[starts + k]
        owners.append(owner[starts])
        hashes.append(_mix(key))
    who, what = np.concatenate(owners), (np.concatenate(hashes) % np.uint64(buckets)).astype(np.int64)
    order = np.argsort(who, kind="stable")
    return what[order], np.concatenate([[0], np.cumsum(np.bincount(who, minlength=n))])


def _repeats(split: Words) -> np.ndarray:
    """For each text how many words are the word before them."""
    if len(split.codes) < 2:
        return np.zeros(len(split.bounds) - 1, dtype=np.int64)
    owners = split.owners
    same = (split.codes[1:] == split.codes[:-1]) & (owners[1:] == owners[:-1])
    return np.bincount(owners[1:][same], minlength=len(split.bounds) - 1)


def _documents(split: Words) -> list[tuple[np.ndarray, np.ndarray]]:
    """For each text its different buckets and their shares of all its features."""
    features, bounds = word_features(split.vocabulary)
    repeats = _repeats(split)
    out = []
    for i in range(len(split.bounds) - 1):
        codes = split.codes[split.bounds[i] : split.bounds[i + 1]]
        own = features[expanded(bounds[codes], bounds[codes + 1] - bounds[codes])]
        bucket, count = np.unique(own, return_counts=True)
        if repeats[i]:
            bucket, count = np.append(bucket, REPEAT), np.append(count, REPEAT_WEIGHT * repeats[i])
        out.append((bucket.astype(np.int32), (count / max(1, count.sum())).astype(np.float32)))
    return out


def learned(documents: list[tuple[np.ndarray, np.ndarray]], y: np.ndarray, seed: int = SEED, epochs: int = EPOCHS, rate: float = RATE) -> tuple[np.ndarray, float]:
    """Weights of the buckets and the bias in the log odds of class 1, from a softmax over two classes."""
    random = np.random.default_rng(seed)
    vectors = random.uniform(-1, 1, (BUCKETS + 1, DIMENSIONS)).astype(np.float32) / DIMENSIONS
    layer = np.zeros((2, DIMENSIONS), dtype=np.float32)
    bias = np.zeros(2, dtype=np.float32)
    weight = len(y) / (2 * np.maximum(1, np.bincount(y, minlength=2)))
    steps, at = epochs * len(y), 0
    for _ in range(epochs):
        for i in random.permutation(len(y)):
            bucket, share = documents[i]
            now = rate * (1 - at / steps)
            at += 1
            mean = share @ vectors[bucket]
            logits = layer @ mean + bias
            odds = np.exp(logits - logits.max())
            wrong = odds / odds.sum()
            wrong[y[i]] -= 1
            wrong *= now * weight[y[i]]
            # In the mean each feature has a small share, so its vector moves by the whole gradient of a mean.
            vectors[bucket] -= np.outer(np.minimum(1.0, share * 50), wrong @ layer).astype(np.float32)
            layer -= np.outer(wrong, mean)
            bias -= wrong
    return (vectors @ (layer[1] - layer[0])).astype(np.float32), float(bias[1] - bias[0])


def calibrated(raw: np.ndarray, y: np.ndarray, share: float) -> tuple[float, float]:
    """Slope and offset that make the log odds fit documents that were not learned from, for this share of class 1."""
    slope, offset = 1.0, 0.0
    prior = np.log(share / (1 - share))
    weight = np.where(y == 1, share / max(1, (y == 1).sum()), (1 - share) / max(1, (y == 0).sum()))
    scale = max(1e-6, float(np.abs(raw).mean()))
    x = raw / scale
    for _ in range(60):  # Newton steps of a two-parameter logistic regression with a small ridge
        p = 1 / (1 + np.exp(-np.clip(slope * x + offset, -30, 30)))
        g = np.array([(weight * (p - y) * x).sum() + 1e-4 * slope, (weight * (p - y)).sum() + 1e-4 * (offset - prior)])
        h = weight * p * (1 - p)
        hess = np.array([[(h * x * x).sum() + 1e-4, (h * x).sum()], [(h * x).sum(), h.sum() + 1e-4]])
        step = np.linalg.solve(hess, g)
        slope, offset = slope - float(np.clip(step[0], -2, 2)), offset - float(np.clip(step[1], -2, 2))
    return slope / scale, offset


def train(docs: DataFrame, labels: DataFrame, most: int = MOST) -> tuple[np.ndarray, float]:
    """The model: a weight for each bucket and the bias, in log odds of label 1. One task reads the bounded sample and trains."""
    share = shares(labels, "quality", MODULUS, HELD_OUT)
    rows = sample(docs, labels, "quality", MODULUS, HELD_OUT, most)

    def fit(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        documents, y, ids, sums = [], [], [], []
        for whole in batches:
            for batch in slices(whole, limit=SLICE):
                documents += _documents(words(batch.column("text")))
                y += batch.column("y").to_pylist()
                ids += batch.column("doc_id").to_pylist()
                sums += [zlib.crc32(t.encode()) for t in batch.column("text").to_pylist()]
        order = np.lexsort((np.array(sums, dtype=np.int64), np.array(ids, dtype=np.int64)))  # rows of one doc_id by their texts
        documents, y = [documents[i] for i in order], np.array(y, dtype=np.int64)[order]
        weights, bias = np.zeros(BUCKETS + 1, dtype=np.float32), float(np.log(share / (1 - share)))
        if len(np.unique(y)) == 2:
            aside = np.arange(len(y)) % 5 == 0
            if len(np.unique(y[aside])) == 2 and len(np.unique(y[~aside])) == 2:
                weights, base = learned([d for d, a in zip(documents, aside, strict=True) if not a], y[~aside])
                raw = np.array([float(s @ weights[b]) + base for (b, s), a in zip(documents, aside, strict=True) if a])
                slope, offset = calibrated(raw, y[aside], share)
                weights, bias = weights * np.float32(slope), base * slope + offset
            else:
                weights, base = learned(documents, y)
                bias = base + float(np.log(share / (1 - share)))
        yield pa.RecordBatch.from_arrays([pa.array([weights.astype("<f4").tobytes()]), pa.array([bias])], names=["weights", "bias"])

    model = map_arrow(rows.select("doc_id", "text", F.col("y").cast("int").alias("y")).repartition(1), fit, "weights binary, bias double").collect()
    return (np.frombuffer(model[0]["weights"], dtype="<f4"), model[0]["bias"]) if model else (np.zeros(BUCKETS + 1, dtype=np.float32), float(np.log(share / (1 - share))))


def _scores(column: pa.Array, weights: np.ndarray, bias: float) -> np.ndarray:
    """The probability of label 1 for each text."""
    split = words(column)
    features, bounds = word_features(split.vocabulary)
    running = np.concatenate([[0.0], np.cumsum(weights[features], dtype=np.float64)])
    by_word, sizes = running[bounds[1:]] - running[bounds[:-1]], np.diff(bounds)
    rows = len(split.bounds) - 1
    sums, counts = (np.bincount(split.owners, x[split.codes], rows) for x in (by_word, sizes.astype(np.float64)))
    repeats = REPEAT_WEIGHT * _repeats(split)
    sums, counts = sums + weights[REPEAT] * repeats, counts + repeats
    return 1 / (1 + np.exp(-np.clip(bias + sums / np.maximum(1, counts), -30, 30)))


def scored(docs: DataFrame, model: tuple[np.ndarray, float]) -> DataFrame:
    """(doc_id, score) of every document."""
    weights, bias = model
    sent = docs.sparkSession.sparkContext.broadcast(weights)  # 4 bytes for each bucket

    def score(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for batch in slices(whole, limit=SLICE):
                yield pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array(_scores(batch.column("text"), sent.value, bias))], names=["doc_id", "score"])

    return map_arrow(docs.select(F.col("doc_id").cast("bigint").alias("doc_id"), F.col("text").cast("string").alias("text")), score, "doc_id bigint, score double")


def accepted(docs: DataFrame, labels: DataFrame, least: float = PREDICTED_FROM, most: int = MOST) -> DataFrame:
    """The documents that score at least so much, all columns as they are."""
    weights, bias = train(docs, labels, most)
    sent = docs.sparkSession.sparkContext.broadcast(weights)

    def keep(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for batch in slices(whole, limit=SLICE):
                yield batch.filter(pa.array(_scores(batch.column("text"), sent.value, bias) >= least))

    return map_arrow(docs, keep, docs.schema)


def classify(docs: DataFrame, labels: DataFrame, most: int = MOST) -> DataFrame:
    """(doc_id, held_out, score, predicted) of every document."""
    out = scored(docs, train(docs, labels, most))
    return out.select("doc_id", F.coalesce(remainder(MODULUS) == HELD_OUT, F.lit(False)).alias("held_out"), "score", (F.col("score") >= PREDICTED_FROM).cast("int").alias("predicted"))
