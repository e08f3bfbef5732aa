"""Best-two-fit packing of tokenised documents into sequences of bounded length.

The decision needs no documents, only how many pieces there are of each length:
at most ``capacity`` numbers. The driver plans bins on that histogram (many equal
bins at once), and executors then deal pieces to the planned places by their rank
among the pieces of the same length.

Defined results: a null text is empty; an empty text is the separator alone; a
text longer than the capacity is cut into pieces of the capacity and a last,
shorter one; an empty table gives no rows; repeated rows (the same doc_id too)
are packed as documents of their own; extra columns are ignored.
"""

from __future__ import annotations

import json
import os
import re
import zlib
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ..plans.ship import map_arrow
from .storage import cut
from .textbatch import SLICE_BYTES, expanded, slices, words

CAPACITY = 2048
#: Pieces of one length are ranked within so many groups, as one length may hold a third of them.
SALTS = 64
#: Words whose ids a worker remembers, and their characters, at most when a slice of text begins.
REMEMBERED, REMEMBERED_CHARS = 250_000, 8 << 20

PIECES = "doc_id bigint, piece int, start bigint, length bigint, ids_crc32 bigint"

_tokenizers: dict = {}

#: How the tokenizer of the contract cuts lower-cased words into pieces.
_PIECES = r"'s|'t|'re|'ve|'m|'ll|'d|[\p{L}]+|[\p{N}]|[^\s\p{L}\p{N}]+"
#: The same over ASCII and the letters of Latin-1, for which lower-casing and composition are plain.
_PLAIN_WORD = re.compile("[!-~\u00c0-\u00d6\u00d8-\u00f6\u00f8-\u00ff]+")
_PLAIN_PIECES = re.compile("'s|'t|'re|'ve|'m|'ll|'d|[a-z\u00df-\u00f6\u00f8-\u00ff]+|[0-9]|[^\\sa-z0-9\u00df-\u00f6\u00f8-\u00ff]+")
#: Stands for the end of a piece, which is part of the piece's last token.
_END = "\x01"


def _byte_letters() -> dict[str, int]:
    """The printable letters that byte-level vocabularies write bytes as."""
    shown = [*range(33, 127), *range(161, 173), *range(174, 256)]
    hidden = [b for b in range(256) if b not in shown]
    return {chr(b): b for b in shown} | {chr(256 + k): b for k, b in enumerate(hidden)}


class PlainWords:
    """A faster encoder of plain words with the same merges: ends of pieces become a byte of their own, merged first."""

    def __init__(self, spec: dict):
        import tiktoken

        letters, vocabulary = _byte_letters(), spec["model"]["vocab"]
        ending = spec["model"]["end_of_word_suffix"]

        def as_bytes(token: str) -> bytes:
            end = token.endswith(ending)
            return bytes(letters[c] for c in (token[: -len(ending)] if end else token)) + _END.encode() * end

        ordered = [bytes([b]) for b in range(256)]
        ordered += [as_bytes(t) for t in vocabulary if t.endswith(ending) and len(t) == len(ending) + 1]
        ordered += [as_bytes("".join(m if isinstance(m, list) else m.split(" "))) for m in spec["model"]["merges"]]
        ranks = {t: k for k, t in enumerate(ordered)}
        special = {x["content"] for x in spec["added_tokens"]}
        ids = {as_bytes(t): i for t, i in vocabulary.items() if t not in special}
        self.ids = np.array([ids.get(t, 0) for t in ordered], dtype="<u4")
        self.ends = np.array([t.endswith(_END.encode()) for t in ordered])
        self.coder = tiktoken.Encoding("words", pat_str=f"[^\n{_END}]+{_END}", mergeable_ranks=ranks, special_tokens={})

    @staticmethod
    def of(spec: dict) -> PlainWords | None:
        """One for tokenizers that cut and fold words as is known here."""
        fold = [x.get("type") for x in (spec.get("normalizer") or {}).get("normalizers", [])]
        cut_ = [x.get("pattern", {}).get("Regex") for x in (spec.get("pre_tokenizer") or {}).get("pretokenizers", [])]
        same = fold == ["NFC", "Replace", "Lowercase"] and cut_[:1] == [_PIECES] and spec["model"].get("end_of_word_suffix")
        return PlainWords(spec) if same else None

    def encode(self, plain: list[str]) -> tuple[np.ndarray, np.ndarray]:
        """The ids of the words in one array, and how many each has."""
        marked = _PLAIN_PIECES.sub(rf"\g<0>{_END}", "\n".join(plain).lower())
        seen = np.frombuffer(marked.encode("latin-1"), dtype=np.uint8)
        ended = np.cumsum(seen == 1)
        upto = np.append(ended[seen == 10], ended[-1])  # pieces up to each word's end
        ranks = np.array(self.coder.encode_ordinary(marked), dtype=np.int64)
        bounds = np.flatnonzero(self.ends[ranks])[upto - 1] + 1
        return self.ids[ranks], np.diff(bounds, prepend=0)


class WordTokenizer:
    """Token ids of texts by way of their distinct words.

    It holds for tokenizers that drop white space and never join across it; the
    ids of a text are then the ids of its words, one after another.
    """

    def __init__(self, path: str):
        os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_file(path)
        with open(path, encoding="utf-8") as spec:
            self.plain = PlainWords.of(json.load(spec))
        self._forget()

    @classmethod
    def of(cls, path: str) -> WordTokenizer:
        """One for each worker and file."""
        if path not in _tokenizers:
            _tokenizers[path] = cls(path)
        return _tokenizers[path]

    def _forget(self) -> None:
        self.known: dict[str, int] = {}
        self.chars = 0
        self.flat = np.empty(0, dtype="<u4")
        self.bounds = np.zeros(1, dtype=np.int64)

    def _learn(self, new: list[str]) -> None:
        """Remember the ids of new words."""
        self.chars += sum(map(len, new))
        fits = [bool(self.plain and _PLAIN_WORD.fullmatch(w) and "<|" not in w) for w in new]
        plain, other = [w for w, f in zip(new, fits, strict=True) if f], [w for w, f in zip(new, fits, strict=True) if not f]
        ids, lengths = [self.flat], []
        for i in range(0, len(plain), 20_000):
            own, counts = self.plain.encode(plain[i : i + 20_000])
            ids.append(own)
            lengths.append(counts)
        for coded in self.tokenizer.encode_batch(other, add_special_tokens=False) if other else []:
            ids.append(np.array(coded.ids, dtype="<u4"))
            lengths.append(np.array([len(coded.ids)]))
        self.known.update(zip(plain + other, range(len(self.known), len(self.known) + len(new)), strict=True))
        self.flat = np.concatenate(ids)
        self.bounds = np.concatenate([self.bounds, self.bounds[-1] + np.cumsum(np.concatenate(lengths))])

    def ids(self, column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
        """The ids of all texts in one array, and each text's bounds in it."""
        split = words(column)
        distinct = split.vocabulary.to_pylist()
        if len(self.known) > REMEMBERED or self.chars > REMEMBERED_CHARS:
            self._forget()
        if new := [w for w in distinct if w not in self.known]:
            self._learn(new)
        at = np.fromiter(map(self.known.__getitem__, distinct), dtype=np.int64, count=len(distinct))[split.codes]
        begins, lengths = self.bounds[at], self.bounds[at + 1] - self.bounds[at]
        ids = self.flat[expanded(begins, lengths)]
        running = np.concatenate([[0], np.cumsum(lengths)])
        return ids, running[split.bounds]


def _cut_up(whole: pa.RecordBatch, coder: WordTokenizer, capacity: int, separator: int, at_once: int) -> Iterator[pa.RecordBatch]:
    """The pieces of a batch of texts, of which so many bytes are tokenised at once."""
    for batch in slices(whole, limit=at_once):
        ids, bounds = coder.ids(batch.column("text"))
        doc_ids = batch.column("doc_id").to_pylist()
        out: list[tuple] = []
        for row, doc_id in enumerate(doc_ids):
            own = np.append(ids[bounds[row] : bounds[row + 1]], np.uint32(separator)).astype("<u4").tobytes()
            total = len(own) // 4
            for piece, start in enumerate(range(0, total, capacity)):
                stop = min(total, start + capacity)
                out.append((doc_id, piece, start, stop - start, zlib.crc32(own[4 * start : 4 * stop])))
        columns = list(zip(*out, strict=True))
        kinds = (pa.int64(), pa.int32(), pa.int64(), pa.int64(), pa.int64())
        yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(columns, kinds, strict=True)], names=["doc_id", "piece", "start", "length", "ids_crc32"])


def pieces(docs: DataFrame, tokenizer: str, capacity: int = CAPACITY, separator: int = 0, at_once: int = SLICE_BYTES) -> DataFrame:
    """One row for each piece: doc_id, piece, start, length, ids_crc32 (its ids as little-endian unsigned 32-bit)."""

    def cutter(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        coder = WordTokenizer.of(tokenizer)
        for whole in batches:
            yield from _cut_up(whole, coder, capacity, separator, at_once)

    return map_arrow(docs.select(F.col("doc_id").cast("bigint").alias("doc_id"), F.col("text").cast("string").alias("text")), cutter, PIECES)


@dataclass
class Pattern:
    """``times`` bins that each hold pieces of these lengths, in this order."""

    lengths: tuple[int, ...]
    times: int


def best_two_fit(histogram: np.ndarray, capacity: int = CAPACITY) -> list[Pattern]:
    """Plan bins for ``histogram[l]`` pieces of each length l.

    A bin begins with the longest piece left and takes the longest that fits until
    none does. If space is left, its smallest piece is put back when two unpacked
    pieces fill the gap so opened more tightly. Bins planned alike are made at once,
    as often as the pieces last; so the work follows the number of lengths.
    """
    left = np.array(histogram, dtype=np.int64)
    left[0] = 0
    plans: list[Pattern] = []
    sizes = np.arange(capacity + 1)
    while left.any():
        taken: list[int] = []
        trial, gap = left.copy(), capacity
        while gap:
            fits = np.flatnonzero(trial[: gap + 1])
            if not len(fits):
                break
            longest = int(fits[-1])
            same = min(int(trial[longest]), gap // longest)
            taken += [longest] * same
            trial[longest] -= same
            gap -= longest * same
        if gap and len(taken) > 1:
            smallest = taken[-1]
            pair = _two_for(trial, gap + smallest, smallest, sizes)
            if pair:
                trial[smallest] += 1
                taken[-1:] = pair
                for length in pair:
                    trial[length] -= 1
        uses = np.bincount(taken, minlength=capacity + 1)
        used = np.flatnonzero(uses)
        times = int((left[used] // uses[used]).min())
        left[used] -= uses[used] * times
        plans.append(Pattern(tuple(taken), times))
    return plans


def _two_for(left: np.ndarray, room: int, beat: int, sizes: np.ndarray) -> list[int] | None:
    """Two lengths that fill ``room`` more tightly than one of ``beat``, or None; of the tightest, the pair with the longest piece."""
    there = left > 0
    below = np.maximum.accumulate(np.where(there, sizes, 0))  # the longest available of at most this length
    firsts = np.flatnonzero(there[: room + 1])
    if not len(firsts):
        return None
    rest = room - firsts
    seconds = below[rest]
    alone = (seconds == firsts) & (left[firsts] < 2)
    seconds[alone] = below[np.maximum(firsts[alone] - 1, 0)]
    sums = np.where(seconds > 0, firsts + seconds, 0)
    best = int(sums.max())
    if best <= beat:
        return None
    at = int(np.flatnonzero(sums == best)[-1])
    return sorted((int(firsts[at]), int(seconds[at])), reverse=True)


def places(plans: list[Pattern]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Where pieces go, by length and rank.

    Three arrays: sorted keys (length << 40 | first rank), the first bin and the
    offset of the places from that rank on; ranks up to the next key take the next bins.
    """
    next_rank: dict[int, int] = {}
    keys, bins, offsets, first = [], [], [], 0
    for plan in plans:
        offset = 0
        for length in plan.lengths:
            rank = next_rank.get(length, 0)
            keys.append((length << 40) | rank)
            bins.append(first)
            offsets.append(offset)
            next_rank[length] = rank + plan.times
            offset += length
        first += plan.times
    order = np.argsort(np.array(keys, dtype=np.int64), kind="stable")
    return tuple(np.array(x, dtype=np.int64)[order] for x in (keys, bins, offsets))


def pack(docs: DataFrame, tokenizer: str, capacity: int = CAPACITY, separator: int = 0, salts: int = SALTS, at_once: int = SLICE_BYTES) -> DataFrame:
    """Every piece of every document with its place: PIECES, then sequence_id and offset. A worker tokenises ``at_once`` bytes of text at a time: less takes less memory and more time."""
    made = cut(pieces(docs, tokenizer, capacity, separator, at_once).withColumn("salt", F.pmod(F.xxhash64("doc_id", "piece", "ids_crc32"), F.lit(salts)).cast("int")))
    counts = made.groupBy("length", "salt").agg(F.count(F.lit(1)).alias("n"))
    table = counts.collect()  # at most capacity * salts rows
    histogram = np.zeros(capacity + 1, dtype=np.int64)
    for row in table:
        histogram[row["length"]] += row["n"]
    keys, bins, offsets = places(best_two_fit(histogram, capacity))
    order = sorted((r["length"], r["salt"], r["n"]) for r in table)
    before, running, of = [], 0, None
    for length, salt, n in order:
        running = running if length == of else 0
        before.append((length, salt, running))
        running, of = running + n, length
    group = np.array([(length << 20) | salt for length, salt, _ in before], dtype=np.int64)
    base = np.array([b for _, _, b in before], dtype=np.int64)
    ranked = made.withColumn("rank", F.row_number().over(Window.partitionBy("length", "salt").orderBy("doc_id", "piece", "ids_crc32")))

    def placer(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            if not batch.num_rows:
                continue
            length, salt, rank = (batch.column(c).to_numpy(zero_copy_only=False).astype(np.int64) for c in ("length", "salt", "rank"))
            rank = rank - 1 + base[np.searchsorted(group, (length << 20) | salt)]
            key = (length << 40) | rank
            at = np.searchsorted(keys, key, side="right") - 1
            own = [batch.column(c) for c in ("doc_id", "piece", "start", "length", "ids_crc32")]
            yield pa.RecordBatch.from_arrays([*own, pa.array(bins[at] + key - keys[at]), pa.array(offsets[at])], names=["doc_id", "piece", "start", "length", "ids_crc32", "sequence_id", "offset"])

    return map_arrow(ranked, placer, f"{PIECES}, sequence_id bigint, offset bigint")
