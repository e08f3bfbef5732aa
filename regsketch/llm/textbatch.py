"""Arrow batches of text as flat arrays of words.

Words are maximal runs of anything but the six ASCII white-space characters
(space, tab, line feed, vertical tab, form feed, carriage return).
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

#: Bytes of text that a worker turns into arrays at once; a longer text is a slice of its own.
SLICE_BYTES = 4 << 20


def slices(batch: pa.RecordBatch, column: str = "text", limit: int = SLICE_BYTES) -> Iterator[pa.RecordBatch]:
    """Consecutive rows of the batch with at most ``limit`` bytes of text, one row at least."""
    if not batch.num_rows:
        return
    sizes = pc.fill_null(pc.binary_length(batch.column(column)), 0).to_numpy(zero_copy_only=False)
    ends = np.cumsum(sizes, dtype=np.int64)
    start = 0
    while start < len(ends):
        before = ends[start - 1] if start else 0
        stop = max(start + 1, int(np.searchsorted(ends, before + limit, side="right")))
        yield batch.slice(start, stop - start)
        start = stop


@dataclass
class Words:
    """Words of some texts: ``codes[bounds[i]:bounds[i+1]]`` index ``vocabulary`` for text i."""

    codes: np.ndarray
    bounds: np.ndarray
    vocabulary: pa.Array

    @property
    def counts(self) -> np.ndarray:
        return np.diff(self.bounds)

    @property
    def owners(self) -> np.ndarray:
        return np.repeat(np.arange(len(self.bounds) - 1), self.counts)


def filled(column: pa.Array) -> pa.Array:
    """The texts as large strings, nulls as empty texts."""
    return pc.fill_null(column.cast(pa.large_string()), "")


def words(column: pa.Array) -> Words:
    """The words of each text of an Arrow string column; a null text has none."""
    lists = pc.ascii_split_whitespace(filled(column))
    flat, ends = lists.flatten(), lists.value_lengths().to_numpy(zero_copy_only=False).astype(np.int64)
    full = pc.not_equal(pc.binary_length(flat), 0)
    kept = full.to_numpy(zero_copy_only=False)
    bounds = np.concatenate([[0], np.cumsum(ends)])
    running = np.concatenate([[0], np.cumsum(kept)])
    coded = flat.filter(full).dictionary_encode()
    return Words(coded.indices.to_numpy(zero_copy_only=False).astype(np.int64), running[bounds], coded.dictionary)


def expanded(starts: np.ndarray, lengths: np.ndarray) -> np.ndarray:
    """start, start+1, ... for each of the ranges, one after another."""
    lengths = np.asarray(lengths, dtype=np.int64)
    ends = np.cumsum(lengths)
    total = int(ends[-1]) if len(ends) else 0
    return np.arange(total, dtype=np.int64) + np.repeat(np.asarray(starts, dtype=np.int64) - (ends - lengths), lengths)


def code_points(vocabulary: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """All strings' code points in one array, and each string's bounds in it."""
    lengths = pc.utf8_length(vocabulary).to_numpy(zero_copy_only=False).astype(np.int64)
    flat = np.frombuffer("".join(vocabulary.to_pylist()).encode("utf-32-le"), dtype="<u4")
    return flat, np.concatenate([[0], np.cumsum(lengths)])
