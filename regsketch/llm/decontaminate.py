"""Benchmark items in training text: BM25 over passages, block-max WAND, and a check of question and answer.

The items are the indexed side; every passage of every document is a query. An item's
impacts are scaled so that a passage with all its terms scores 1, and all items at or above
``THRESHOLD`` are wanted, so the bound that WAND prunes by is fixed. Before WAND runs
on a passage, the same kind of bound is taken for all passages of a batch at once:
impacts of the rarer terms are added up by (half passage, item), the most that an item's
common terms can add is granted to it, and passages that cannot reach the threshold are left.

A hit counts if the passage holds enough of the item's five-word shingles: half of
those of the question and half of those of the answer, or four fifths of all. The
answer is the last sentence or line; an item of one sentence is cut in half. An item of more than ``ENTRY`` terms
is indexed as several entries of at most so many, one after another, and is found if one of them is; so a passage has one length
whatever the items are.

Items beyond ``INDEX_BYTES`` of text are dealt to several indexes, which are used one after another. Document frequencies, the number of
entries and their mean length are those of the whole benchmark in each of them, so hits and scores do not depend on how many there are.

Defined results: a null or empty text has no passages; items without words are never
found; rows of one item_id are one item and are found once, those without one each by itself; repeated rows give repeated results; empty tables
give no rows; texts of any length are searched whole; other columns pass through ``clean``.
"""

from __future__ import annotations

import bisect
import math
import re
from array import array
from collections import Counter, defaultdict
from collections.abc import Iterator
from dataclasses import dataclass
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..plans.ship import map_arrow
from .storage import cut
from .textbatch import Words, slices, words

THRESHOLD, K1, B = 0.6, 1.2, 0.75
SHINGLE, PART_OVERLAP, WHOLE_OVERLAP = 5, 0.5, 0.8
#: Postings of a block; words of half a passage, and most terms of an entry, which so lies in one passage as a whole.
BLOCK, ENTRY = 32, 128
#: A term in more than this share of the items is common.
COMMON = 0.05
#: Bytes of benchmark text that one index, which is sent to all executors, may hold; it takes twenty to thirty times as much memory. More text takes more passes.
INDEX_BYTES = 8 << 20
#: Entries of one item that stay in one index. A longer item (of a million words) may be found once for each run of so many.
TOGETHER = 8192

#: Bytes of text that a worker searches at once: its passages' postings are spread out beside it, at some twenty times as much.
SLICE = 1 << 20

_TRIM = ".,;:!?\"'()[]"
_UPPER = {ord(c): c.lower() for c in "ABCDEFGHIJKLMNOPQRSTUVWXYZ"}


def term(word: str) -> str:
    return word.strip(_TRIM).translate(_UPPER)


def _split(text: str) -> list[str]:
    return [t for t in (term(w) for w in re.findall(r"[^\x20\x09-\x0D]+", text)) if t]


def parts(text: str) -> tuple[list[str], list[str]]:
    """Terms of question and answer."""
    sentences = [s for s in (_split(x) for x in re.split(r"(?<=[.!?])[\x20\x09-\x0D]+|\n", text)) if s]
    if len(sentences) > 1:
        return [t for s in sentences[:-1] for t in s], sentences[-1]
    whole = sentences[0] if sentences else []
    return whole[: (len(whole) + 1) // 2], whole[(len(whole) + 1) // 2 :]


def entries(text: str) -> list[tuple[list[str], list[str]]]:
    """Question and answer of each entry of an item: one, or as many as its length takes."""
    question, answer = parts(text)
    whole = question + answer
    if len(whole) <= ENTRY:
        return [(question, answer)]
    each = [whole[i : i + ENTRY] for i in range(0, len(whole), ENTRY)]
    return [(x[: (len(x) + 1) // 2], x[(len(x) + 1) // 2 :]) for x in each]


def windows(ids: np.ndarray, width: int) -> np.ndarray:
    """A number for each run of so many known terms (ids from 0); runs with an unknown term (-1) are left."""
    n = len(ids) - width + 1
    if n <= 0 or not width:
        return np.empty(0, dtype=np.uint64)
    key, known = np.zeros(n, dtype=np.uint64), np.ones(n, dtype=bool)
    for k in range(width):
        own = ids[k : k + n]
        known &= own >= 0
        key = (key ^ own.astype(np.uint64)) * np.uint64(0x9E3779B97F4A7C15)
        key ^= key >> np.uint64(29)
    return key[known]


@dataclass
class Postings:
    """Entries of one term by rising number, their impacts, and each block's last entry and largest impact."""

    items: array
    impacts: array
    block_last: array
    block_most: array
    most: float


@dataclass
class Collection:
    """What scores need to know of all entries, whichever of them an index holds."""

    size: int
    mean: float
    frequency: dict[str, int]

    @staticmethod
    def of(texts: list[tuple[list[str], list[str]]]) -> Collection:
        lengths = [len(q) + len(a) for q, a in texts]
        return Collection(len(texts), sum(lengths) / max(1, sum(n > 0 for n in lengths)), Counter(t for q, a in texts for t in {*q, *a}))


class Index:
    """Inverted index of entries (item, question, answer) with scaled BM25 impacts and block maxima, in flat arrays."""

    def __init__(self, rows: list[tuple[int, list[str], list[str]]], collection: Collection | None = None):
        self.ids = [i for i, _, _ in rows]
        known: dict[int | None, int] = {}
        self.first = [k if i is None else known.setdefault(i, k) for k, i in enumerate(self.ids)]  # the first entry of the same item
        of = collection or Collection.of([(q, a) for _, q, a in rows])
        n, mean = len(rows), of.mean or 1.0
        idf = {t: math.log(1 + (of.size - f + 0.5) / (f + 0.5)) for t, f in of.frequency.items()}
        lists: dict[str, tuple[array, array]] = defaultdict(lambda: (array("i"), array("d")))
        for k, (_, q, a) in enumerate(rows):
            bag, length = Counter(q + a), len(q) + len(a)
            impact = {t: idf[t] * f * (K1 + 1) / (f + K1 * (1 - B + B * length / mean)) for t, f in bag.items()}
            own = sum(impact.values())
            for t, x in impact.items():
                lists[t][0].append(k)
                lists[t][1].append(x / own)
        self.terms = {t: i for i, t in enumerate(sorted(lists))}
        self.postings = []
        for t in self.terms:
            items, impacts = lists.pop(t)
            starts = range(0, len(items), BLOCK)
            self.postings.append(Postings(items, impacts, array("i", (items[min(i + BLOCK, len(items)) - 1] for i in starts)), array("d", (max(impacts[i : i + BLOCK]) for i in starts)), max(impacts)))
        # For the bound over a whole batch: postings of the rarer terms in flat arrays, and what common terms add at most.
        rare = [len(p.items) <= max(4, COMMON * n) for p in self.postings]
        self.granted = np.zeros(n)
        for p, r in zip(self.postings, rare, strict=True):
            if not r:
                np.add.at(self.granted, p.items, p.impacts)
        sizes = np.array([len(p.items) if r else 0 for p, r in zip(self.postings, rare, strict=True)], dtype=np.int64)
        self.begins, self.sizes = np.cumsum(sizes) - sizes, sizes
        kept = [p for p, r in zip(self.postings, rare, strict=True) if r]
        self.flat_items = np.concatenate([np.frombuffer(p.items, dtype=np.int32) for p in kept]) if kept else np.empty(0, dtype=np.int32)
        self.flat_impacts = np.concatenate([np.frombuffer(p.impacts) for p in kept]) if kept else np.empty(0)
        self.shingles = []
        for _, q, a in rows:
            ids = np.array([self.terms[t] for t in q + a], dtype=np.int64)
            # (words of a shingle, the different shingles) of the question, the answer and all
            self.shingles.append(tuple((w, np.unique(windows(x, w))) for x, w in ((x, min(SHINGLE, len(x))) for x in (ids[: len(q)], ids[len(q) :], ids))))

    @classmethod
    def of(cls, items: list[tuple[int, str]]) -> Index:
        """An index of whole items by themselves."""
        return cls([(i, q, a) for i, t in items for q, a in entries(t or "")])

    def nbytes(self) -> int:
        """Bytes of the arrays and terms."""
        lists = sum(8 * len(p.impacts) + 4 * len(p.items) + 12 * len(p.block_last) + 400 for p in self.postings)
        return lists + sum(120 + len(t) for t in self.terms) + sum(x.nbytes + 130 for e in self.shingles for _, x in e) + self.flat_items.nbytes + self.flat_impacts.nbytes + 3 * self.granted.nbytes

    def retrieve(self, query: set[int], threshold: float = THRESHOLD) -> list[tuple[int, float]]:
        """All items whose impacts over the query's terms add up to the threshold or more, by block-max WAND."""
        slack = threshold - 1e-9
        cursors = [[self.postings[t].items[0], 0, self.postings[t]] for t in sorted(query)]
        found = []
        while cursors:
            cursors.sort(key=lambda c: c[0])
            bound, pivot = 0.0, -1
            for k, (_, _, p) in enumerate(cursors):
                bound += p.most
                if bound >= slack:
                    pivot = k
                    break
            if pivot < 0:
                break
            item = cursors[pivot][0]
            while pivot + 1 < len(cursors) and cursors[pivot + 1][0] == item:
                pivot += 1
            blocks, nearest = 0.0, cursors[pivot + 1][0] if pivot + 1 < len(cursors) else self.size
            for _, _, p in cursors[: pivot + 1]:
                at = bisect.bisect_left(p.block_last, item)
                if at < len(p.block_last):
                    blocks += p.block_most[at]
                    nearest = min(nearest, p.block_last[at] + 1)
            if blocks < slack:
                goal = max(item + 1, nearest)  # no item before can do better in these blocks
            else:
                score = 0.0
                for _, _, p in cursors[: pivot + 1]:
                    at = bisect.bisect_left(p.items, item)
                    if at < len(p.items) and p.items[at] == item:
                        score += p.impacts[at]
                if score >= slack:
                    found.append((item, score))
                goal = item + 1
            for c in cursors[: pivot + 1]:
                c[1] = bisect.bisect_left(c[2].items, goal, c[1])
                c[0] = c[2].items[c[1]] if c[1] < len(c[2].items) else self.size
            cursors = [c for c in cursors if c[0] < self.size]
        return found

    @property
    def size(self) -> int:
        return len(self.ids)

    def overlaps(self, item: int, passage: np.ndarray) -> tuple[float, float, float]:
        """Shares of the question's, the answer's and all shingles of the entry that the passage (ids of terms, -1 for others) has."""
        have = {w: windows(passage, w) for w in {w for w, _ in self.shingles[item]}}
        return tuple(float(np.isin(own, have[w]).mean()) if len(own) else 1.0 for w, own in self.shingles[item])


def hits(split: Words, index: Index, threshold: float = THRESHOLD) -> list[tuple[int, int, int, float, float, float]]:
    """(text, entry, first word of the passage, score, question's share, answer's share) of every item found in each text; the best entry and passage for each."""
    vocabulary = [term(w) for w in split.vocabulary.to_pylist()]
    lookup = np.array([index.terms.get(t, -1) for t in vocabulary], dtype=np.int64)
    empty = np.array([not t for t in vocabulary], dtype=bool)
    codes = split.codes[~empty[split.codes]] if len(split.codes) else split.codes
    owners = split.owners[~empty[split.codes]] if len(split.codes) else split.owners
    if not len(codes):
        return []
    firsts = np.searchsorted(owners, np.arange(len(split.bounds) - 1))
    ends = np.append(firsts[1:], len(owners))
    place = np.arange(len(owners)) - firsts[owners]
    per_text = np.maximum(1, -(-(ends - firsts) // ENTRY))
    begin_half = np.cumsum(per_text) - per_text
    half = begin_half[owners] + place // ENTRY
    ids = lookup[codes]
    known = np.flatnonzero((ids >= 0) & (index.sizes[np.maximum(ids, 0)] > 0)) if len(index.sizes) else np.empty(0, dtype=np.int64)
    # Each term once in a half; then its rarer postings.
    pair = np.unique(half[known] * len(index.terms) + ids[known]) if len(known) else np.empty(0, dtype=np.int64)
    which, t = np.divmod(pair, max(1, len(index.terms)))
    counts = index.sizes[t] if len(t) else np.empty(0, dtype=np.int64)
    spread = np.repeat(index.begins[t] - (np.cumsum(counts) - counts), counts) + np.arange(int(counts.sum())) if len(t) else np.empty(0, dtype=np.int64)
    key = np.repeat(which, counts) * index.size + index.flat_items[spread]
    cells, inverse = np.unique(key, return_inverse=True)
    sums = np.bincount(inverse, index.flat_impacts[spread], minlength=len(cells))
    # A passage is a half and the next one of the same text.
    cell_half, cell_item = np.divmod(cells, max(1, index.size))
    passages: set[int] = set()
    for shift in (0, 1):  # the passages that the half begins and ends
        start = cell_half - shift
        total = sums.copy()
        mate = (start + 1 - shift) * index.size + cell_item  # the other half of the passage
        at = np.minimum(np.searchsorted(cells, mate), max(0, len(cells) - 1))
        if len(cells):
            total += np.where(cells[at] == mate, sums[at], 0)
        passages.update(start[(total + index.granted[cell_item] >= threshold - 1e-9) & (start >= 0)].tolist())
    if (index.granted >= threshold - 1e-9).any():  # an item of common terms alone may be anywhere
        passages.update(range(int(per_text.sum())))
    text_of_half = np.repeat(np.arange(len(per_text)), per_text)
    best: dict[tuple[int, int], tuple] = {}
    for start in sorted(passages):
        text = int(text_of_half[start])
        first = int(firsts[text] + (start - begin_half[text]) * ENTRY)
        last = min(int(ends[text]), first + 2 * ENTRY)
        if first >= last:
            continue
        query = set(ids[first:last].tolist()) - {-1}
        found = index.retrieve(query, threshold)
        if not found:
            continue
        passage = ids[first:last]
        for item, score in found:
            question, answer, whole = index.overlaps(item, passage)
            if (question >= PART_OVERLAP and answer >= PART_OVERLAP) or whole >= WHOLE_OVERLAP:
                row, key = (text, item, int(place[first]), score, question, answer), (text, index.first[item])
                if key not in best or best[key][3] < score:
                    best[key] = row
    return [best[k] for k in sorted(best)]


def entry_rows(benchmark: DataFrame) -> DataFrame:
    """(item_id, place, question, answer): the entries of every item, lists of terms."""

    def cutter(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        kind = pa.list_(pa.string())
        for whole in batches:
            for batch in slices(whole):
                found = [entries(t or "") for t in batch.column("text").to_pylist()]
                rows = np.repeat(np.arange(len(found)), [len(x) for x in found])
                flat = [e for x in found for e in x]
                places = pa.array([k for x in found for k in range(len(x))], pa.int32())
                yield pa.RecordBatch.from_arrays([batch.column("item_id").take(pa.array(rows)), places, pa.array([q for q, _ in flat], kind), pa.array([a for _, a in flat], kind)], names=["item_id", "place", "question", "answer"])

    rows = benchmark.select(F.col("item_id").cast("bigint").alias("item_id"), F.col("text").cast("string").alias("text"))
    return map_arrow(rows, cutter, "item_id bigint, place int, question array<string>, answer array<string>")


def indexes(benchmark: DataFrame, most: int = INDEX_BYTES) -> Iterator[tuple[Index, bool]]:
    """The benchmark in as few indexes as its size allows, one after another, and whether there are more than one; entries are dealt by a hash."""
    found = cut(entry_rows(benchmark))
    terms = F.concat("question", "answer")
    row = found.agg(F.sum(F.aggregate(terms, F.lit(0).cast("bigint"), lambda n, t: n + F.octet_length(t) + 1)).alias("size"), F.count(F.lit(1)).alias("n"), F.sum(F.size(terms)).alias("terms"), F.count(F.when(F.size(terms) > 0, 1)).alias("full")).first()
    passes = 1 + (row["size"] or 0) // most
    part = F.pmod(F.xxhash64("item_id", F.floor(F.col("place") / TOGETHER)), F.lit(passes))
    of_term = found.select(F.explode(F.array_distinct(terms)).alias("term"))
    frequency = cut(of_term.groupBy("term").agg(F.count(F.lit(1)).alias("n")))
    for k in range(passes):
        own = found.where(part == k)
        rows = [(r["item_id"], r["question"], r["answer"]) for r in own.orderBy("item_id", "place", "question", "answer").collect()]
        here = own.select(F.explode(terms).alias("term")).distinct()
        counted = {r["term"]: r["n"] for r in frequency.join(here, "term", "left_semi").collect()}  # terms of this index's entries
        yield Index(rows, Collection(row["n"], (row["terms"] or 0) / max(1, row["full"]), counted)), passes > 1


def _passes(docs: DataFrame, benchmark: DataFrame, of_pass) -> Iterator[DataFrame]:
    """What ``of_pass`` makes of each index's broadcast; with several indexes each result is written before the next index is built."""
    for index, several in indexes(benchmark):
        sent = docs.sparkSession.sparkContext.broadcast(index)  # bounded by INDEX_BYTES of text
        own = of_pass(sent)
        yield cut(own) if several else own
        if several:
            sent.unpersist()


HITS = "doc_id bigint, item_id bigint, first_word bigint, score double, question_overlap double, answer_overlap double"


def scan(docs: DataFrame, benchmark: DataFrame, threshold: float = THRESHOLD) -> DataFrame:
    """HITS: a row for each benchmark item in each document."""
    rows = docs.select(F.col("doc_id").cast("bigint").alias("doc_id"), F.col("text").cast("string").alias("text"))

    def of_pass(sent) -> DataFrame:
        def find(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for whole in batches:
                for batch in slices(whole, limit=SLICE):
                    found = hits(words(batch.column("text")), sent.value, threshold)
                    columns = list(zip(*found, strict=True)) or [()] * 6
                    ids = batch.column("doc_id").take(pa.array(columns[0], pa.int64()))
                    items = pa.array([sent.value.ids[k] for k in columns[1]], pa.int64())
                    yield pa.RecordBatch.from_arrays([ids, items, pa.array(columns[2], pa.int64()), *(pa.array(c, pa.float64()) for c in columns[3:])], names=[x.split()[0] for x in HITS.split(", ")])

        return map_arrow(rows, find, HITS)

    return reduce(DataFrame.unionByName, _passes(docs, benchmark, of_pass))


def _kept(whole: pa.RecordBatch, index: Index, threshold: float = THRESHOLD) -> Iterator[pa.RecordBatch]:
    """The rows of a batch in whose text no item is found."""
    for batch in slices(whole, limit=SLICE):
        bad = {h[0] for h in hits(words(batch.column("text")), index, threshold)}
        yield batch.filter(pa.array([k not in bad for k in range(batch.num_rows)]))


def clean(docs: DataFrame, benchmark: DataFrame, threshold: float = THRESHOLD) -> DataFrame:
    """The documents without any benchmark item, all columns as they are."""
    left = [docs]

    def of_pass(sent) -> DataFrame:
        def keep(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for whole in batches:
                yield from _kept(whole, sent.value, threshold)

        return map_arrow(left[-1], keep, docs.schema)

    for out in _passes(docs, benchmark, of_pass):
        left.append(out)
    return left[-1]
