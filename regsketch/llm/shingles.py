"""Sets of word shingles, and prefixes of them that similar sets must share.

A set's shingles are put in one global order, rare ones first. Two sets with a Jaccard
similarity of at least t then share a shingle among the first ``size - ceil(t * size) + 1``
of each, and of the smaller set (of both, if sizes are equal) even among the first
``size - ceil(2t / (1 + t) * size) + 1``. That holds for any order, so how well rarity is known
touches costs alone: it is counted over all texts in ``SLOTS`` counters, whatever the size of the input.

Shingles are 64-bit hashes of runs of words, A-Z lower-cased; a text of fewer words has one shingle, one without words none.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..plans.ship import map_arrow
from .textbatch import expanded, filled, slices

#: Words of a shingle, and least similarity.
SHINGLE, SIMILARITY = 5, 0.8
#: Counters of how often shingles occur.
SLOTS_LOG = 16
#: Bytes of text that are turned into shingles at once.
SLICE = 1 << 20

_STEP, _LAST = np.uint64(0x9E3779B97F4A7C15), np.uint64(0xBF58476D1CE4E5B9)
_LOW = np.uint64((1 << (64 - SLOTS_LOG)) - 1)


def _powers(base: int, n: int) -> np.ndarray:
    out = np.full(n, base, dtype=np.uint64)
    out[:1] = 1
    return np.multiply.accumulate(out)


#: A word's hash is the polynomial of its bytes' numbers modulo 2**64 in this odd base.
_BASE = 0x9E3779B97F4A7C15
_INVERSE = pow(_BASE, -1, 1 << 64)
_FOLDED = np.array([b + 32 if 65 <= b <= 90 else b for b in range(256)], dtype=np.uint64)
#: A number for each byte, A-Z as a-z.
_NUMBERS = (_FOLDED + np.uint64(1)) * np.uint64(0xD1B54A32D192ED03)
_NUMBERS = (_NUMBERS ^ (_NUMBERS >> np.uint64(29))) * np.uint64(0xBF58476D1CE4E5B9) | np.uint64(1)
_SPACE = np.isin(np.arange(256), list(b" \t\n\r\x0b\x0c"))
_tables = [_powers(_BASE, SLICE), _powers(_INVERSE, SLICE)]


def word_hashes(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """A hash of each word, A-Z lower-cased, in one array, and each text's bounds in it."""
    text = filled(column)
    rows = len(text)
    offsets = np.frombuffer(text.buffers()[1], dtype=np.int64)[text.offset : text.offset + rows + 1]
    raw = np.frombuffer(text.buffers()[2] or b"", dtype=np.uint8)[offsets[0] : offsets[-1]]
    offsets = offsets - offsets[0]
    inside = np.zeros(len(raw) + 2, dtype=bool)
    inside[1:-1] = ~_SPACE[raw]
    opens = inside[1:] & ~inside[:-1]
    joined = offsets[1:-1][(offsets[1:-1] > 0) & (offsets[1:-1] < len(raw))]
    opens[joined] = inside[joined + 1]  # a text's first word begins with it
    closes = inside[:-1] & ~inside[1:]
    closes[joined] = inside[joined]
    starts, ends = np.flatnonzero(opens[:-1]), np.flatnonzero(closes)
    out = np.empty(len(starts), dtype=np.uint64)
    at = 0
    while at < len(starts):  # words that lie within as many bytes as there are powers, or one long word
        stop = max(at + 1, int(np.searchsorted(ends, starts[at] + SLICE, side="right")))
        first, n = starts[at], int(ends[stop - 1] - starts[at])
        powers, inverse = _tables if n <= SLICE else (_powers(_BASE, n), _powers(_INVERSE, n))
        sums = np.zeros(n + 1, dtype=np.uint64)
        np.cumsum(_NUMBERS[raw[first : first + n]] * powers[:n], out=sums[1:])
        own, upto = starts[at:stop] - first, ends[at:stop] - first
        out[at:stop] = (sums[upto] - sums[own]) * inverse[own]
        at = stop
    return out ^ (out >> np.uint64(32)), np.searchsorted(starts, offsets)


def shingles(column: pa.Array, width: int = SHINGLE) -> tuple[np.ndarray, np.ndarray]:
    """The hashes of the shingles of each text, repeats too, in one array, and each text's bounds in it."""
    own, bounds = word_hashes(column)
    counts = np.diff(bounds)
    many = np.where(counts > 0, np.maximum(1, counts - width + 1), 0)
    at = expanded(bounds[:-1], many)
    short = (counts > 0) & (counts < width)
    length = np.repeat(np.minimum(counts, width), many) if short.any() else None
    key = np.zeros(len(at), dtype=np.uint64)
    for k in range(width):
        if length is None:
            key = _mixed(key, own[at + k])
        else:
            there = k < length
            key[there] = _mixed(key[there], own[at[there] + k])
    return spread(key), np.concatenate([[0], np.cumsum(many)])


def _mixed(key: np.ndarray, word: np.ndarray) -> np.ndarray:
    key = (key ^ word) * _STEP
    return key ^ (key >> np.uint64(31))


def spread(key: np.ndarray) -> np.ndarray:
    """Other 64-bit numbers in place of these, one to one, without their order."""
    key = (key ^ (key >> np.uint64(32))) * _LAST
    return key ^ (key >> np.uint64(29))


def rarity(docs: DataFrame, width: int = SHINGLE) -> np.ndarray:
    """How many shingles of all texts fall into each counter: 1 << SLOTS_LOG numbers, added up by the executors."""

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros(1 << SLOTS_LOG, dtype=np.int64)
        for whole in batches:
            for batch in slices(whole, limit=SLICE):
                total += np.bincount(_slots(shingles(batch.column("text"), width)[0]), minlength=len(total))
        used = np.flatnonzero(total)
        yield pa.RecordBatch.from_arrays([pa.array(used.astype(np.int32)), pa.array(total[used])], names=["slot", "n"])

    out = np.zeros(1 << SLOTS_LOG, dtype=np.int64)
    counted = map_arrow(docs.select(F.col("text").cast("string").alias("text")), count, "slot int, n bigint").groupBy("slot").agg(F.sum("n").alias("n"))
    for row in counted.collect():  # at most 1 << SLOTS_LOG rows
        out[row["slot"]] = row["n"]
    return out


def _slots(hashes: np.ndarray) -> np.ndarray:
    return (hashes >> np.uint64(64 - SLOTS_LOG)).astype(np.int64)


def ordered_sets(column: pa.Array, counts: np.ndarray | None = None, width: int = SHINGLE) -> tuple[np.ndarray, np.ndarray]:
    """The different shingles of each text in one array, rare ones first, and each text's bounds in it.

    They come as keys that sort in that order: the logarithm of the counter, then the hash without the counter's number. (Without counters, in any order.)
    """
    hashes, ends = shingles(column, width)
    if counts is not None:
        level = (np.log2(1.0 + counts) * 1024).astype(np.uint64)  # under 1 << 16
        hashes = (level[_slots(hashes)] << np.uint64(64 - SLOTS_LOG)) | (hashes & _LOW)
    for a, b in zip(ends[:-1].tolist(), ends[1:].tolist(), strict=True):
        hashes[a:b].sort()
    first = np.ones(len(hashes), dtype=bool)
    first[1:] = hashes[1:] != hashes[:-1]
    first[ends[:-1][ends[:-1] < len(hashes)]] = True
    running = np.concatenate([[0], np.cumsum(first)])
    return hashes[first], running[ends]


def prefixes(keys: np.ndarray, bounds: np.ndarray, similarity: float = SIMILARITY) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """The first keys of each set: the keys, the sets' bounds in them, how many of each set's a partner no smaller must share, and how frequent they are (mean logarithm of the counters)."""
    sizes = np.diff(bounds)
    probe = np.where(sizes > 0, sizes - np.ceil(similarity * sizes - 1e-9) + 1, 0).astype(np.int64)
    sure = np.where(sizes > 0, sizes - np.ceil(2 * similarity / (1 + similarity) * sizes - 1e-9) + 1, 0).astype(np.int64)
    own = keys[expanded(bounds[:-1], probe)]
    level = np.bincount(np.repeat(np.arange(len(sizes)), probe), (own >> np.uint64(64 - SLOTS_LOG)) / 1024.0, len(sizes)) / np.maximum(1, probe)
    return own, np.concatenate([[0], np.cumsum(probe)]), sure, level
