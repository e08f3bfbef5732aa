"""SimHash fingerprints and near duplicates by bit-sliced comparison.

Two ways to use it:

* ``link_fingerprints``: every pair of fingerprints that differ in at most two
  bits is linked. Of four quarters of a fingerprint two are then equal, so pairs
  meet in one of six tables keyed by two quarters; within a bucket the bit-sliced
  kernel finds them all. Buckets beyond ``BUCKET_ROWS`` different fingerprints go a
  second exact way: each fingerprint and its 64 one-bit neighbours are keys, and two
  fingerprints are within two bits exactly if they share a key, so a key has 65
  fingerprints at most however dense the bucket is.
* ``near_duplicates``: documents whose sets of word shingles have a Jaccard
  similarity of at least 0.8. Such pairs are too far apart for exact tables
  on fingerprints (about ten bits of 64), so buckets are the shingles that similar sets
  must share if the rare ones come first (``shingles.prefixes``): no similar pair is in no bucket. Of each bucket's
  rows the bit-sliced kernel discards pairs beyond a wide radius, and the exact
  similarity of the shingle sets decides. Nothing is capped.

Defined results: a null or white-space text has no words and fingerprint zero, and
is linked like any other; fewer words than a shingle form one shingle; repeated rows
are rows of the same component; an empty table gives no rows; other columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..plans.ship import map_arrow
from .bitslice import near_pairs, pairs_by_shift, smallest_reachable
from .components import components
from .shingles import SHINGLE, SIMILARITY, SLICE, ordered_sets, prefixes, rarity, spread
from .storage import collect_garbage, cut, free
from .textbatch import expanded, filled, slices

SEED = 42
RADIUS = 2
#: Different fingerprints of one bucket that are compared with each other in a worker's memory.
BUCKET_ROWS = 4096
#: Rows that the kernel takes at once, whole buckets.
KERNEL_ROWS = 1 << 17

#: The radius beyond which fingerprints of sets with a similarity of 0.8 do not lie: ten bits on average, three as deviation; four shingles of five: twelve bits, beyond 28 some 1e-6.
WIDE_RADIUS = 28
#: Bits of the map that says which rows are needed for a join; 8 MB.
MARKS = 1 << 26
#: Rounds in which rows are tried against the hubs of their buckets, before all that are still apart are compared.
STARS = 2
#: Pairs of one text that are verified in one place.
FAN = 2000


def shingle_hashes(text: bytes, width: int, seed: int = SEED) -> np.ndarray:
    """XXH64 of each run of ``width`` words, A-Z lower-cased, joined by a space; of all words if fewer."""
    words = text.lower().split()
    if not words:
        return np.empty(0, dtype="<u8")
    digest, join = xxhash.xxh64_intdigest, b" ".join
    return np.array([digest(join(words[i : i + width]), seed) for i in range(max(1, len(words) - width + 1))], dtype="<u8")


#: For each byte a word with bit k of it in byte k: eight counters side by side, good for 255 additions.
_LANES = np.unpackbits(np.arange(256, dtype=np.uint8)[:, None], axis=1, bitorder="little").astype(np.uint8).view("<u8").ravel()


def majority_bits(hashes: np.ndarray, bounds: np.ndarray) -> np.ndarray:
    """For each run of hashes the number whose bits are set in over half of them; zero for an empty run."""
    counts = np.diff(bounds)
    out = np.zeros(len(counts), dtype="<u8")
    full = np.flatnonzero(counts)
    if len(full):
        parts = -(-counts[full] // 255)
        starts = np.repeat(bounds[:-1][full], parts) + 255 * expanded(np.zeros(len(full), dtype=np.int64), parts)
        eight = hashes.view(np.uint8).reshape(-1, 8)
        lanes = np.stack([np.add.reduceat(_LANES[eight[:, k]], starts) for k in range(8)], axis=1)
        sums = np.add.reduceat(np.ascontiguousarray(lanes).view(np.uint8).reshape(-1, 64), np.cumsum(parts) - parts, axis=0, dtype=np.int64)
        out[full] = np.packbits(2 * sums > counts[full, None], axis=1, bitorder="little").view("<u8").ravel()
    return out


def _hashed(column: pa.Array, width: int, seed: int) -> tuple[np.ndarray, np.ndarray]:
    each = [shingle_hashes(x, width, seed) for x in pc.cast(filled(column), pa.large_binary()).to_pylist()]
    bounds = np.concatenate([[0], np.cumsum([len(x) for x in each], dtype=np.int64)])
    return (np.concatenate(each) if each else np.empty(0, dtype="<u8")), bounds


def fingerprints(docs: DataFrame, width: int = 3, seed: int = SEED) -> DataFrame:
    """(doc_id, fp): the 64-bit SimHash of each text as a signed long."""

    def hasher(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for batch in slices(whole, limit=1 << 20):
                hashes, bounds = _hashed(batch.column("text"), width, seed)
                yield pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array(majority_bits(hashes, bounds).view("<i8"))], names=["doc_id", "fp"])

    return map_arrow(docs.select(F.col("doc_id").cast("bigint").alias("doc_id"), F.col("text").cast("string").alias("text")), hasher, "doc_id bigint, fp bigint")


def _quarters(fp: str = "fp") -> list:
    """Six keys, each of two 16-bit quarters, as (table, key)."""
    part = [F.shiftrightunsigned(F.col(fp), 16 * k).bitwiseAND(F.lit(0xFFFF)) for k in range(4)]
    pairs = [(a, b) for a in range(4) for b in range(a)]
    return [F.struct(F.lit(t).alias("table"), F.shiftleft(part[a], 16).bitwiseOR(part[b]).alias("key")) for t, (a, b) in enumerate(pairs)]


def _whole_groups(batches: Iterator[pa.RecordBatch], keys: list[str], rows: int) -> Iterator[pa.Table]:
    """Sorted batches put together to about ``rows`` rows that end where a group ends, but for a group longer than that."""
    held: list[pa.RecordBatch] = []
    for batch in batches:
        if batch.num_rows:
            held.append(batch)
        if sum(b.num_rows for b in held) >= rows:
            table = pa.Table.from_batches(held).combine_chunks()
            ends = _group_ends([table.column(k).to_numpy() for k in keys])
            stop = int(ends[ends < table.num_rows - 1][-1]) + 1 if (ends < table.num_rows - 1).any() else table.num_rows
            yield table.slice(0, stop)
            held = table.slice(stop).to_batches()
    if held:
        yield pa.Table.from_batches(held).combine_chunks()


def _group_ends(columns: list[np.ndarray]) -> np.ndarray:
    n = len(columns[0])
    differs = np.zeros(n, dtype=bool)
    differs[-1:] = True
    for c in columns:
        differs[:-1] |= c[1:] != c[:-1]
    return np.flatnonzero(differs)


def bucket_links(distinct: DataFrame, radius: int = RADIUS, bucket_rows: int = BUCKET_ROWS) -> DataFrame:
    """(src, dst) between fingerprints of one bucket, enough to join all that lie within ``radius`` 2; dst null: its bucket is too large."""

    def compare(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        before = None
        for table in _whole_groups(batches, ["table", "key"], KERNEL_ROWS):
            fps, at, key = (table.column(k).to_numpy() for k in ("fp", "table", "key"))
            fps = fps.view("<u8")
            ends = _group_ends([at, key])
            sizes = np.diff(np.concatenate([[-1], ends]))
            if before == (at[0], key[0]):  # the rest of a bucket that filled the rows before
                sizes[0] = max(sizes[0], bucket_rows + 1)
            before = (at[-1], key[-1])
            rows = np.diff(np.concatenate([[-1], ends]))
            size, last = np.repeat(sizes, rows), np.repeat(ends, rows)
            small, large = np.flatnonzero((size > 1) & (size <= bucket_rows)), np.flatnonzero(size > bucket_rows)
            new_place = np.cumsum((size > 1) & (size <= bucket_rows)) - 1
            i, j = near_pairs(fps[small], new_place[last[small]], radius)
            label = smallest_reachable(len(small), i, j)
            moved = np.flatnonzero(label != np.arange(len(small)))
            src = np.concatenate([fps[small][moved], fps[large]]).view("<i8")
            dst = pa.array(np.concatenate([fps[small][label[moved]], fps[large]]).view("<i8"), mask=np.arange(len(src)) >= len(moved))
            yield pa.RecordBatch.from_arrays([pa.array(src), dst], names=["src", "dst"])

    keyed = distinct.select("fp", F.explode(F.array(*_quarters())).alias("at")).select("at.table", "at.key", "fp")
    return map_arrow(keyed.repartition("table", "key").sortWithinPartitions("table", "key", "fp"), compare, "src bigint, dst bigint")


def neighbour_links(dense: DataFrame) -> DataFrame:
    """(src, dst) that join all of ``dense`` (fp) within two bits: by way of shared one-bit neighbours."""
    flips = F.array(F.col("fp"), *(F.col("fp").bitwiseXOR(F.lit(1 << b if b < 63 else -(1 << 63))) for b in range(64)))
    keyed = dense.select("fp", F.explode(flips).alias("key"))
    least = keyed.groupBy("key").agg(F.min("fp").alias("dst"), F.count(F.lit(1)).alias("n")).where("n > 1")
    return keyed.join(least, "key").where("fp <> dst").select(F.col("fp").alias("src"), "dst")


def link_fingerprints(rows: DataFrame, bucket_rows: int = BUCKET_ROWS) -> DataFrame:
    """``rows`` (doc_id, fp) with component_id: the smallest doc_id reachable over links of at most two differing bits."""
    distinct = cut(rows.groupBy("fp").agg(F.min("doc_id").alias("least_id")))
    found = cut(bucket_links(distinct, RADIUS, bucket_rows))
    dense = found.where(F.col("dst").isNull()).select(F.col("src").alias("fp")).distinct()
    links = found.where(F.col("dst").isNotNull())
    roots = components(links.union(neighbour_links(dense)))
    of = distinct.join(roots.withColumnRenamed("node", "fp"), "fp", "left").withColumn("root", F.coalesce("root", "fp"))
    named = of.join(of.groupBy("root").agg(F.min("least_id").alias("component_id")), "root").select("fp", "component_id")
    return rows.join(named, "fp")


def simhash_components(docs: DataFrame, width: int = 3, seed: int = SEED) -> DataFrame:
    """(doc_id, fp, component_id) for every document."""
    return link_fingerprints(cut(fingerprints(docs, width, seed)))


def features(docs: DataFrame, counts: np.ndarray, width: int = SHINGLE, similarity: float = SIMILARITY) -> DataFrame:
    """(doc_id, text_key, size, fp, level, keys, sure) of every document: its shingles' number and SimHash, and the prefix that similar sets share with it.

    Equal texts have equal text_key. The first ``sure`` keys are those that a partner no smaller must share; ``level`` says how frequent the keys are.
    """

    def hasher(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for batch in slices(whole, limit=SLICE):
                whole_sets, bounds = ordered_sets(batch.column("text"), counts, width)
                keys, of, sure, level = prefixes(whole_sets, bounds, similarity)
                lists = pa.ListArray.from_arrays(pa.array(of.astype(np.int32)), pa.array(keys.view("<i8")))
                fps = pa.array(majority_bits(spread(whole_sets), bounds).view("<i8"))
                yield pa.RecordBatch.from_arrays([batch.column("doc_id"), batch.column("text_key"), pa.array(np.diff(bounds)), fps, pa.array(level), lists, pa.array(sure.astype(np.int32))], names=FEATURE_NAMES)

    text = F.coalesce(F.col("text").cast("string"), F.lit(""))
    source = docs.select(F.col("doc_id").cast("bigint").alias("doc_id"), text.alias("text"), F.md5(text).alias("text_key"))
    return map_arrow(source, hasher, "doc_id bigint, text_key string, size bigint, fp bigint, level double, keys array<bigint>, sure int")


FEATURE_NAMES = ["doc_id", "text_key", "size", "fp", "level", "keys", "sure"]


def _fits(a: str, b: str, similarity: float, radius: int) -> Column:
    """Whether rows a and b (node, size, fp, sure, root) of one bucket may be a similar pair that is still apart."""
    one, two = F.col(f"{a}.size"), F.col(f"{b}.size")
    near = F.bit_count(F.col(f"{a}.fp").bitwiseXOR(F.col(f"{b}.fp"))) <= radius
    sure = (F.col(f"{a}.sure") | (one > two)) & (F.col(f"{b}.sure") | (two > one))
    return (F.col(f"{a}.node") != F.col(f"{b}.node")) & (F.col(f"{a}.root") != F.col(f"{b}.root")) & (F.least(one, two) >= F.lit(similarity) * F.greatest(one, two) - 1e-9) & sure & near


def shared_keys(of: DataFrame) -> DataFrame:
    """(key, node, size, fp, level, sure) for every prefix key that two texts or more have."""
    keyed = of.select("node", "size", "fp", "level", F.posexplode("keys").alias("place", "key"), F.col("sure").alias("upto")).withColumn("sure", F.col("place") < F.col("upto")).drop("place", "upto")
    twice = cut(keyed.groupBy("key").agg(F.count(F.lit(1)).alias("n")).where("n > 1").select("key"))
    return cut(_marked(keyed, twice, ["key"]).join(twice, "key"))


def star_candidates(rooted: DataFrame, hubs: DataFrame, similarity: float = SIMILARITY, radius: int = WIDE_RADIUS) -> tuple[DataFrame, DataFrame]:
    """(a, b): each row of ``rooted`` (key, node, size, fp, level, sure, root) with its bucket's hub, where they may be similar; and the hubs (node).

    The hub is the row whose own keys are the most frequent, which is the plainest of a group of near copies, and none of ``hubs``.
    """
    rank = F.struct(F.col("level"), F.col("node"))
    row = F.struct("node", "size", "fp", "sure", "root")
    best = cut(rooted.join(hubs, "node", "left_anti").groupBy("key").agg(F.max_by(row, rank).alias("hub")))
    pairs = rooted.select("key", row.alias("own")).join(best, "key").where(_fits("own", "hub", similarity, radius))
    return cut(pairs.select(F.col("own.node").alias("a"), F.col("hub.node").alias("b")).distinct()), cut(best.select(F.col("hub.node").alias("node")).union(hubs).distinct())


def cross_candidates(rooted: DataFrame, similarity: float = SIMILARITY, radius: int = WIDE_RADIUS, bucket_rows: int = BUCKET_ROWS) -> DataFrame:
    """(a, b): all pairs of ``rooted`` (key, node, size, fp, sure, root) that share a key, are of different roots and may be similar, by the bit-sliced kernel.

    Buckets of one root are done. Those of more than ``bucket_rows`` are dealt to tasks by pairs of parts, so that any two rows of them meet.
    """

    def compare(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for table in _whole_groups(batches, ["key", "first", "second"], KERNEL_ROWS):
            column = {c: table.column(c).to_numpy(zero_copy_only=False) for c in table.column_names}
            ends = _group_ends([column[c] for c in ("key", "first", "second")])
            last = np.repeat(ends, np.diff(np.concatenate([[-1], ends])))
            size, sure, root, node = (column[c] for c in ("size", "sure", "root", "node"))
            for i, j in pairs_by_shift(np.ascontiguousarray(column["fp"]).view("<u8"), last, radius):
                one, two = size[i], size[j]
                fits = (root[i] != root[j]) & (np.minimum(one, two) >= similarity * np.maximum(one, two) - 1e-9) & (sure[i] | (one > two)) & (sure[j] | (two > one))
                if fits.any():
                    x, y = node[i[fits]], node[j[fits]]
                    yield pa.RecordBatch.from_arrays([pa.array(np.minimum(x, y)), pa.array(np.maximum(x, y))], names=["a", "b"])

    mixed = rooted.groupBy("key").agg(F.min("root").alias("least"), F.max("root").alias("most"), F.count(F.lit(1)).alias("n")).where("least <> most")
    rows = rooted.join(mixed.select("key", F.ceil(2 * F.col("n") / F.lit(bucket_rows)).alias("parts")), "key").withColumn("parts", F.when(F.col("parts") > 2, F.col("parts")).otherwise(F.lit(1)))
    own = rows.withColumn("part", F.pmod(F.xxhash64("node"), F.col("parts")))
    dealt = own.withColumn("other", F.explode(F.sequence(F.lit(0), F.col("parts") - 1)))
    dealt = dealt.where((F.col("parts") == 1) | (F.col("part") != F.col("other")))
    dealt = dealt.select("key", F.least("part", "other").alias("first"), F.greatest("part", "other").alias("second"), "node", "size", "fp", "sure", "root")
    return map_arrow(dealt.repartition("key", "first", "second").sortWithinPartitions("key", "first", "second", "node"), compare, "a bigint, b bigint").distinct()


def similar(pairs: DataFrame, texts: DataFrame, width: int = SHINGLE, similarity: float = SIMILARITY) -> DataFrame:
    """The pairs (src, dst) of ``pairs`` (a, b, key_a, key_b) whose sets of shingles have at least this Jaccard similarity; texts: (text_key, text), one row a key.

    A text that many pairs have as their second is dealt out in copies, one for each ``FAN`` pairs.
    """

    def judge(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for batch in slices(whole, "text_a", SLICE):
                (one, ends_one), (two, ends_two) = (ordered_sets(batch.column(f"text_{k}"), None, width) for k in "ab")
                sizes = np.diff(ends_one), np.diff(ends_two)
                owner = np.concatenate([np.repeat(np.arange(batch.num_rows), x) for x in sizes])
                shingle = np.concatenate([one, two])
                order = np.lexsort((shingle, owner))
                same = (shingle[order][1:] == shingle[order][:-1]) & (owner[order][1:] == owner[order][:-1])
                both = np.bincount(owner[order][1:][same], minlength=batch.num_rows)
                kept = both >= similarity * (sizes[0] + sizes[1] - both) - 1e-9
                yield batch.select(["a", "b"]).filter(pa.array(kept)).rename_columns(["src", "dst"])

    spread = pairs.groupBy("key_b").agg(F.ceil(F.count(F.lit(1)) / F.lit(FAN)).cast("int").alias("parts"))
    dealt = pairs.join(spread, "key_b").withColumn("part", F.pmod(F.xxhash64("a"), F.col("parts")).cast("int")).drop("parts")
    one = texts.select(F.col("text_key").alias("key_a"), F.col("text").alias("text_a"))
    two = texts.select(F.col("text_key").alias("key_b"), F.col("text").alias("text_b")).join(spread, "key_b")
    two = two.withColumn("part", F.explode(F.sequence(F.lit(0), F.col("parts") - 1))).drop("parts")
    return map_arrow(dealt.join(one, "key_a").join(two, ["key_b", "part"]).select("a", "b", "text_a", "text_b"), judge, "src bigint, dst bigint")


def _marked(rows: DataFrame, needed: DataFrame, keys: list[str], there: bool = True) -> DataFrame:
    """The rows whose keys may be among ``needed``, by a bitmap of their hashes; or with ``there`` false those whose keys cannot be.

    What passes still has to be joined, by an inner join with different keys (Spark would push a semi join below the bitmap). The bitmap has MARKS bits at any
    size of the input, so it is broadcast; it spares most rows the shuffle of their text, and where it is full it only lets all rows pass.
    """
    slot = F.pmod(F.xxhash64(*keys), F.lit(MARKS))
    bits = needed.select(slot.alias("slot")).groupBy(F.bitmap_bucket_number("slot").alias("_part")).agg(F.bitmap_construct_agg(F.bitmap_bit_position("slot")).alias("_bits"))
    place = F.bitmap_bit_position(slot).cast("int")
    byte = F.conv(F.hex(F.col("_bits").substr(F.shiftright(place, 3) + 1, F.lit(1))), 16, 10).cast("int")
    joined = rows.withColumn("_part", F.bitmap_bucket_number(slot)).join(F.broadcast(bits), "_part", "left")
    marked = F.coalesce(F.pmod(F.floor(byte / F.pow(F.lit(2.0), place % 8)), F.lit(2)) == 1, F.lit(False))
    return joined.where(marked if there else ~marked).select(*rows.columns)


def near_duplicates(docs: DataFrame, width: int = SHINGLE, similarity: float = SIMILARITY) -> DataFrame:
    """(doc_id, text_key, component_id, keep): groups of equal or similar texts; keep marks the text of each group that stays."""
    rows, groups = grouped(docs, width, similarity)
    out = rows.join(groups, "text_key", "left")
    return out.select("doc_id", "text_key", "component_id", F.coalesce(F.col("node") == F.col("component_id"), F.lit(False)).alias("keep"))


def grouped(docs: DataFrame, width: int = SHINGLE, similarity: float = SIMILARITY) -> tuple[DataFrame, DataFrame]:
    """(doc_id, text_key) of every document, and (text_key, node, component_id) of every text: its least doc_id and its group's.

    In ``STARS`` rounds every row is tried against the hub of each of its buckets, which joins groups of copies without forming their
    pairs; then all rows of a bucket that are still apart are compared with each other. Documents without a doc_id group by text alone.
    """
    found = cut(features(docs, rarity(docs, width), width, similarity))
    first = {c: F.first(c).alias(c) for c in ("size", "fp", "level", "keys", "sure")}
    of = cut(found.where(F.col("doc_id").isNotNull()).groupBy("text_key").agg(F.min("doc_id").alias("node"), *first.values()))
    text = F.coalesce(F.col("text").cast("string"), F.lit(""))
    texts = docs.select(text.alias("text"), F.md5(text).alias("text_key"))

    def verified(pairs: DataFrame) -> DataFrame:
        key = {k: of.select(F.col("node").alias(k), F.col("text_key").alias(f"key_{k}")) for k in "ab"}
        keyed = cut(pairs.join(key["a"], "a").join(key["b"], "b"))
        needed = keyed.select(F.col("key_a").alias("text_key")).union(keyed.select("key_b")).distinct()
        # All by text_key, so that a text is shuffled once, and once more with the other text of its pair.
        own = _marked(texts, needed, ["text_key"]).join(needed, "text_key").dropDuplicates(["text_key"])
        out = cut(similar(keyed, own, width, similarity))
        collect_garbage(docs.sparkSession)
        return out

    shared = shared_keys(of)
    roots = None

    def rooted() -> DataFrame:
        return shared.withColumn("root", F.col("node")) if roots is None else shared.join(roots, "node", "left").withColumn("root", F.coalesce("root", "node"))

    links, tried, hubs = None, None, of.select("node").limit(0)
    for step in range(STARS + 1):
        if step < STARS:
            pairs, hubs = star_candidates(rooted(), hubs, similarity)
        else:
            pairs = cut(cross_candidates(rooted(), similarity))
        new = pairs if tried is None else pairs.join(tried, (pairs["a"] == tried["x"]) & (pairs["b"] == tried["y"]), "left_anti")
        both_ways = pairs.select(F.col("a").alias("x"), F.col("b").alias("y")).union(pairs.select("b", "a"))
        tried = both_ways if tried is None else tried.union(both_ways)
        more = verified(new)
        if links is None or not more.isEmpty():
            links = more if links is None else links.union(more)
            roots = components(links)
    groups = of.select("node", "text_key").join(roots, "node", "left").select("text_key", "node", F.coalesce("root", "node").alias("component_id"))
    return found.select("doc_id", "text_key"), groups


def deduplicated(docs: DataFrame, width: int = SHINGLE, similarity: float = SIMILARITY) -> DataFrame:
    """One document of each group of equal or similar texts, the one with the least doc_id, all columns as they are.

    A row without a doc_id takes part under a negative number made from its text.
    """
    text = F.coalesce(F.col("text").cast("string"), F.lit(""))
    own = F.coalesce(F.col("doc_id").cast("bigint"), -1 - F.pmod(F.xxhash64(text), F.lit(1 << 62)))
    rows, groups = grouped(docs.select(own.alias("doc_id"), text.alias("text")), width, similarity)
    name, key = (free(n, docs.columns) for n in ("_dedup_id", "_dedup_key"))
    chosen = cut(groups.where("node = component_id").select(F.col("node").alias(name), F.col("text_key").alias(key)))
    # Only rows that go or that are there twice, and what a bitmap cannot tell from them, are joined: the others are not shuffled.
    each = rows.groupBy(F.col("doc_id").alias(name), F.col("text_key").alias(key)).agg(F.count(F.lit(1)).alias("n"))
    doubtful = cut(each.join(chosen.withColumn("stays", F.lit(True)), [name, key], "left").where("n > 1 OR stays IS NULL").select(name, key))
    marked = docs.withColumns({name: own, key: F.md5(text)})
    sure = _marked(marked, doubtful, [name, key], there=False)
    unsure = _marked(marked, doubtful, [name, key]).join(chosen, [name, key]).dropDuplicates([name, key])
    return sure.select(*docs.columns).unionByName(unsure.select(*docs.columns))
