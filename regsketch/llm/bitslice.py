"""Hamming distances by vertical bit planes.

Fingerprints that may match lie in groups next to each other. For each distance d
between places, one pass compares row i with row i + d for all i at once: plane b
holds bit b of 64 rows in a word, and the differing bits are added up in bitwise
counters, so that one word operation serves 64 pairs.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np

#: Planes that are added up before blocks of which every pair is too far apart are left.
CHECK_EVERY = 8


def planes(fingerprints: np.ndarray) -> np.ndarray:
    """Bit planes of unsigned 64-bit numbers: row b has bit b of all of them, 64 to a word, with a spare word."""
    n = len(fingerprints)
    bits = np.unpackbits(np.ascontiguousarray(fingerprints, dtype="<u8").view(np.uint8).reshape(n, 8), axis=1, bitorder="little")
    padded = np.zeros((64, (n // 64 + 2) * 64), dtype=np.uint8)
    padded[:, :n] = bits.T
    return np.packbits(padded, axis=1, bitorder="little").view("<u8")


def _lanes(flags: np.ndarray) -> np.ndarray:
    padded = np.zeros((len(flags) // 64 + 1) * 64, dtype=np.uint8)
    padded[: len(flags)] = flags
    return np.packbits(padded, bitorder="little").view("<u8")


def pairs_by_shift(fingerprints: np.ndarray, last: np.ndarray, radius: int) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """All (i, j), i < j <= last[i], whose fingerprints differ in ``radius`` bits at most, those of one distance j - i at a time.

    ``last[i]`` is the place of the last row of i's group.
    """
    n = len(fingerprints)
    own = np.arange(n)
    sliced = planes(fingerprints)
    reach = int((last - own).max()) if n else 0
    width = int(radius + 1).bit_length()
    start = (1 << width) - 1 - radius  # one more difference than the radius overflows the counter
    for d in range(1, reach + 1):
        valid = _lanes(own + d <= last)
        at = np.flatnonzero(valid)
        over = ~valid[at]
        counter = [np.full(len(at), ~np.uint64(0) if start >> k & 1 else np.uint64(0)) for k in range(width)]
        words, shift = divmod(d, 64)
        for b in range(64):
            other = sliced[b].take(at + words, mode="clip") >> np.uint64(shift)
            if shift:
                other |= sliced[b].take(at + words + 1, mode="clip") << np.uint64(64 - shift)
            carry = sliced[b, at] ^ other
            for k in range(width):
                counter[k], carry = counter[k] ^ carry, counter[k] & carry
            over |= carry
            if b % CHECK_EVERY == CHECK_EVERY - 1:
                open_ = np.flatnonzero(~over)
                if len(open_) < len(at):
                    at, over, counter = at[open_], over[open_], [c[open_] for c in counter]
                if not len(at):
                    break
        if len(at):
            hits = np.unpackbits(np.ascontiguousarray(~over).view(np.uint8).reshape(len(at), 8), axis=1, bitorder="little")
            block, lane = np.nonzero(hits)
            i = at[block] * 64 + lane
            yield i, i + d


def near_pairs(fingerprints: np.ndarray, last: np.ndarray, radius: int) -> tuple[np.ndarray, np.ndarray]:
    """All pairs of ``pairs_by_shift`` at once."""
    found = [(np.empty(0, dtype=np.int64),) * 2, *pairs_by_shift(fingerprints, last, radius)]
    return tuple(np.concatenate(x) for x in zip(*found, strict=True))


def smallest_reachable(n: int, i: np.ndarray, j: np.ndarray) -> np.ndarray:
    """For each of n rows the first row that it is linked to, directly or through others."""
    label = np.arange(n)
    while True:
        low = np.minimum(label[i], label[j])
        new = label.copy()
        np.minimum.at(new, i, low)
        np.minimum.at(new, j, low)
        new = new[new]
        if np.array_equal(new, label):
            return label
        label = new
