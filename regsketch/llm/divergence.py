"""Quality rules by distribution divergence.

Each document becomes two histograms: of character classes, and of common words of
four languages with one bin for all other words. References are the same histograms
of all documents of a language that the base rules keep. A document passes if there is one language to which
the Jensen-Shannon distances of both its histograms are within the limits, each in texts long enough for it to mean something.

Defined results: a null text has no words; texts under 50 words, and texts of which
over half the words lie in repeated three-word windows, fail before any divergence;
texts under ``LEAST_CHARS`` code points are not judged on classes nor those under
``LEAST_WORDS`` on words; repeated rows give repeated results; an empty table gives
none; documents without a language are in no reference but are judged; without any
reference no document is judged; extra columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..plans.ship import map_arrow
from .storage import cut
from .textbatch import Words, filled, slices, words

#: Base rules.
LEAST_TOTAL, MOST_REPEATED = 50, 0.5
#: Guards and limits of the distances (square roots of divergences in bits, 0 to 1).
LEAST_CHARS, LEAST_WORDS, CLASS_LIMIT, WORD_LIMIT = 200, 50, 0.23, 0.42
#: Languages with fewer documents than this share are in no reference.
LEAST_SHARE = 0.001

#: Frequent function words.
COMMON = {
    "en": "the of and to in a is that for it on with as was at by this be are from or an not have had but his they".split(),
    "de": "der die und in den von zu das mit sich des auf für ist im dem nicht ein eine als auch es an er so dass".split(),
    "fr": "de la le et les des en un du une que est pour qui dans par plus pas au sur ne se ce il sont avec".split(),
    "es": "de la que el en y a los se del las un por con no una su para es al lo como más pero sus le".split(),
}
SYMBOLS = b"#*$%&|<>"
CLASSES = ("lower", "upper", "digit", "space", "punctuation", "symbol", "other letter", "control")
_SPACES = b" \t\n\r\x0b\x0c"
BINS = sorted({w for own in COMMON.values() for w in own})
FEATURES = "doc_id bigint, lang string, n_words bigint, word_chars bigint, n_symbols bigint, n_dup_lines bigint, n_repeat_words bigint, classes array<int>, commons array<int>"


def _class_table() -> np.ndarray:
    """Class of each byte of UTF-8: the first byte of a longer sequence stands for the character, the others (class 8) for nothing."""
    table = np.full(256, 7, dtype=np.int64)
    for c in range(33, 127):
        table[c] = 0 if chr(c).islower() else 1 if chr(c).isupper() else 2 if chr(c).isdigit() else 5 if c in SYMBOLS + b"@+=~^\\_{}" else 4
    table[list(_SPACES)] = 3
    table[0x80:0xC0] = 8
    table[0xC0:] = 6
    return table


_CLASS = _class_table()
_SYMBOL = np.isin(np.arange(256), list(SYMBOLS))
_SPACE = np.isin(np.arange(256), list(_SPACES))


def repeated_words(split: Words) -> np.ndarray:
    """For each text, how many words lie in three-word windows that are found twice or more in it."""
    codes, n = split.codes, len(split.codes)
    out = np.zeros(len(split.bounds) - 1, dtype=np.int64)
    if n < 3:
        return out
    owners = split.owners
    at = np.flatnonzero(owners[2:] == owners[:-2])
    a, b, c, d = (x.astype(np.uint64) for x in (codes[at], codes[at + 1], codes[at + 2], owners[at]))
    key = np.zeros(len(at), dtype=np.uint64)
    for part in (a, b, c, d):
        key = (key ^ part) * np.uint64(0x9E3779B97F4A7C15)
        key ^= key >> np.uint64(32)
    order = np.argsort(key, kind="stable")
    same = key[order[1:]] == key[order[:-1]]
    x, y = at[order[1:][same]], at[order[:-1][same]]
    if not all(((codes[x + k] == codes[y + k]).all() for k in range(3))) or not (owners[x] == owners[y]).all():
        order = np.lexsort((c, b, a, d))  # two windows share a key by chance
        same = np.ones(len(at) - 1, dtype=bool)
        for part in (a, b, c, d):
            same &= part[order[1:]] == part[order[:-1]]
    twice = np.zeros(len(at), dtype=bool)
    twice[1:] |= same
    twice[:-1] |= same
    starts = at[order[twice]]
    covered = np.zeros(n, dtype=bool)
    for k in range(3):
        covered[starts + k] = True
    return np.bincount(owners[covered], minlength=len(out)).astype(np.int64)


def _per_text(flags: np.ndarray, offsets: np.ndarray) -> np.ndarray:
    running = np.concatenate([[0], np.cumsum(flags)])
    return running[offsets[1:]] - running[offsets[:-1]]


def _duplicate_lines(text: bytes) -> int:
    lines = [x for x in text.split(b"\n") if x.strip()]
    return len(lines) - len(set(lines))


def measured(docs: DataFrame) -> DataFrame:
    """FEATURES of every document."""

    def measure(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        place = {w: k for k, w in enumerate(BINS)}
        for whole in batches:
            for batch in slices(whole):
                text = filled(batch.column("text"))
                rows = len(text)
                offsets = np.frombuffer(text.buffers()[1], dtype=np.int64)[text.offset : text.offset + rows + 1]
                raw = np.frombuffer(text.buffers()[2] or b"", dtype=np.uint8)[offsets[0] : offsets[-1]]
                offsets = offsets - offsets[0]
                owner = np.repeat(np.arange(rows), np.diff(offsets))
                kinds = np.bincount(owner * 9 + _CLASS[raw], minlength=rows * 9).reshape(rows, 9)
                characters = kinds[:, :8].sum(1)
                spaces = _per_text(_SPACE[raw], offsets)
                split = words(text)
                low = [place.get(w.strip(".,;:!?\"'()|#*$%&").lower(), len(BINS)) for w in split.vocabulary.to_pylist()]
                common = np.bincount(split.owners * (len(BINS) + 1) + np.array(low, dtype=np.int64)[split.codes], minlength=rows * (len(BINS) + 1)).reshape(rows, -1)
                copies = [_duplicate_lines(x) for x in pc.cast(text, pa.large_binary()).to_pylist()]
                lists = [pa.ListArray.from_arrays(pa.array(np.arange(rows + 1, dtype=np.int32) * x.shape[1]), pa.array(x.ravel().astype(np.int32))) for x in (kinds[:, :8], common)]
                numbers = [pa.array(x.astype(np.int64)) for x in (split.counts, characters - spaces, _per_text(_SYMBOL[raw], offsets), np.array(copies), repeated_words(split))]
                yield pa.RecordBatch.from_arrays([batch.column("doc_id"), batch.column("lang"), *numbers, *lists], names=[x.split()[0] for x in FEATURES.split(", ")])

    lang = F.col("lang").cast("string") if "lang" in docs.columns else F.lit(None).cast("string")
    return map_arrow(docs.select(F.col("doc_id").cast("bigint").alias("doc_id"), lang.alias("lang"), F.col("text").cast("string").alias("text")), measure, FEATURES)


def references(features: DataFrame, least_share: float = LEAST_SHARE) -> list[tuple[str, np.ndarray, np.ndarray]]:
    """For each language the sums of both histograms over all its documents that pass the base rules: a few hundred numbers each."""
    sums = lambda name, n: [F.sum(F.get(name, F.lit(k))).alias(f"{name}{k}") for k in range(n)]
    sound = (F.col("n_words") >= LEAST_TOTAL) & (100 * F.col("n_repeat_words") <= 100 * MOST_REPEATED * F.col("n_words"))
    table = features.where(F.col("lang").isNotNull() & sound).groupBy("lang").agg(F.count(F.lit(1)).alias("n"), *sums("classes", 8), *sums("commons", len(BINS) + 1))
    total = features.count()
    rows = table.where(F.col("n") >= max(1, least_share * total)).orderBy("lang").collect()  # at most 1 / least_share rows
    return [(r["lang"], np.array([r[f"classes{k}"] for k in range(8)], dtype=float), np.array([r[f"commons{k}"] for k in range(len(BINS) + 1)], dtype=float)) for r in rows]


def jensen_shannon(counts: np.ndarray, reference: np.ndarray) -> np.ndarray:
    """The distance (square root of the divergence in bits) of each row's distribution to the reference; 0 for an empty row."""
    total = counts.sum(1, keepdims=True)
    p = counts / np.maximum(total, 1)
    q = reference / max(reference.sum(), 1)
    middle = (p + q) / 2
    with np.errstate(divide="ignore", invalid="ignore"):
        left = np.where(p > 0, p * np.log2(p / middle), 0).sum(1)
        right = np.where(q > 0, q * np.log2(q / middle), 0).sum(1)
    return np.where(total[:, 0] > 0, np.sqrt(np.maximum(0, (left + right) / 2)), 0)


def judged(docs: DataFrame, class_limit: float = CLASS_LIMIT, word_limit: float = WORD_LIMIT) -> DataFrame:
    """doc_id, n_words, the measures, base_failed, kept, and both distances to the language that is nearest by words."""
    found = cut(measured(docs))
    known = references(found)

    def judge(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            if not batch.num_rows:
                continue
            n, total, repeats = batch.num_rows, batch.column("n_words").to_numpy(), batch.column("n_repeat_words").to_numpy()
            classes, commons = (batch.column(c).flatten().to_numpy().reshape(n, -1) for c in ("classes", "commons"))
            failed = (total < LEAST_TOTAL) | (100 * repeats > 100 * MOST_REPEATED * total)
            by_class, by_word = (np.stack([jensen_shannon(x, r[k]) for r in known], axis=1) if known else np.zeros((n, 1)) for k, x in ((1, classes), (2, commons)))
            nearest = by_word.argmin(1)
            class_near = (classes.sum(1) < LEAST_CHARS)[:, None] | (by_class <= class_limit)
            word_near = (total < LEAST_WORDS)[:, None] | (by_word <= word_limit)
            near, at = (class_near & word_near).any(1), np.arange(n)
            names = [known[k][0] if known else None for k in nearest]
            own = [batch.column(c) for c in ("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words")]
            yield pa.RecordBatch.from_arrays([*own, pa.array(failed), pa.array(~failed & near), pa.array(by_class[at, nearest]), pa.array(by_word[at, nearest]), pa.array(names, pa.string())], names=["doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept", "class_distance", "word_distance", "nearest_lang"])

    schema = "doc_id bigint, n_words bigint, word_chars bigint, n_symbols bigint, n_dup_lines bigint, n_repeat_words bigint, base_failed boolean, kept boolean, class_distance double, word_distance double, nearest_lang string"
    return map_arrow(found, judge, schema)
