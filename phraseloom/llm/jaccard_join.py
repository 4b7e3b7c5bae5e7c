"""N-gram Jaccard join: size-banded tiles, hashed bitmap signatures, exact sorted-array intersection.

1. Every text becomes its set of distinct word shingles (64-bit values). Equal sets share one node, named by a 64-bit
   digest; copies are never compared with each other. The same pass counts
   recurring shingles over all documents; the most frequent ones, a list of a fixed size, serve the order only.
2. Shingles are ordered by rarity: frequent ones last, the longer shingle first. Under any such order two linked sets
   must meet in the prefixes of ``n - ceil(t n) + 1`` shingles. Prefix entries are dealt by shingle once, frequent shingles salted, and entries that stand alone go. A tile
   is a shingle and a size band with its neighbours; entries without company in their tile go too.
3. To begin with, sets that agree on a band of least hashes pair with the band's leader, then members outside a tile's
   main component with leaders of it. A pair of a tile passes when the prefix hits that it shares leave room for the needed overlap, then when the bit count of its XORed
   bitmaps does, and is then verified by intersecting the sorted arrays. Verified links give components.
4. What is left to look at are pairs inside a tile whose members lie in different components. Such a pair meets in every
   tile that it shares, but counts only where none of the ``PRIOR`` entries before it, in either set's order, is common: at
   its first common shingle, and rarely once more. There the places leave room for the needed overlap, or it is no link.
   Then the bit counts decide, and every pair that is left is verified unless links found meanwhile have joined its
   components, likely ones first. So no component is missed, and a large group of near copies, which leaders have joined,
   is not expanded into pairs.

Defined cases: null and empty texts have no shingles and stand alone; shorter texts than a shingle are one shingle;
repeated rows share their node; null keys take part and never become a component's id unless all of its keys are null;
empty tables give empty results; columns besides key and text never enter.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from phraseloom.llm import byte_words as bw
from phraseloom.llm.common import Scratch, bit_set, drop_finished_shuffles, durable, is_lit, release_memory, tidy
from phraseloom.llm.components import components

FREQUENT = 1 << 18
FOLD_AT = 1 << 20
RECURS = 4
ROUNDS = 1
LEADERS = 8
BANDS, BAND_ROWS = 16, 4
#: Pairs that a node brings to each of the last rounds; the final one takes all that are left.
LAST_ROUNDS = (1, 8, None)
#: Entries just before one of the same set that tell whether a pair has met already.
PRIOR = 6
SALTS = 64
SLICE = 1 << 19


def _needed(n_a: Column, n_b: Column, percent: int) -> Column:
    """Least intersection of linked sets: 100 i >= percent * (a + b - i)."""
    return F.ceil(F.lit(percent) * (n_a + n_b) / F.lit(100.0 + percent) - 1e-9)


def _sets(column: pa.Array, size: int):
    """Per slice of a text column: first row, distinct sorted shingles, their bounds, and each row's digest."""
    raw, offsets = bw.buffers(column)
    for first, last in bw.slices(offsets, SLICE):
        hashes, at, sizes = bw.words_and_sizes(raw[offsets[first] : offsets[last]], offsets[first : last + 1] - offsets[first], bw.NOT_SPACE)
        values, bounds = bw.shingles(hashes, at, size, sizes)
        total = np.concatenate([np.zeros(1, np.uint64), np.cumsum(bw.mix(values + np.uint64(0x2545F4914F6CDD1D)))])
        yield first, values, bounds, bw.mix(total[bounds[1:]] - total[bounds[:-1]]).view(np.int64)


class _Counts:
    """Shingles that recur in a task, with their counts, in bounded memory: what is seen once is dropped at each fold."""

    def __init__(self) -> None:
        self.values, self.hits = np.zeros(0, np.uint64), np.zeros(0, np.int64)
        self.waiting: list[np.ndarray] = []
        self.held = 0

    def add(self, values: np.ndarray) -> None:
        self.waiting.append(values)
        self.held += len(values)
        if self.held >= FOLD_AT:
            self.fold()

    def fold(self) -> None:
        values, hits = np.unique(np.concatenate([*self.waiting, np.zeros(0, np.uint64)]), return_counts=True)
        merged, where = np.unique(np.concatenate([self.values, values[hits > 1]]), return_inverse=True)
        counts = np.bincount(where, np.concatenate([self.hits, hits[hits > 1]]), minlength=len(merged)).astype(np.int64)
        if len(merged) > FREQUENT:
            keep = np.sort(np.argsort(-counts, kind="stable")[:FREQUENT])
            merged, counts = merged[keep], counts[keep]
        self.values, self.hits, self.waiting, self.held = merged, counts, [], 0


def _profile(docs: DataFrame, size: int) -> DataFrame:
    """``(doc_id, text_hash, n, node)`` per row, and ``(shingle, hits)`` rows for what recurs in a task."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        counts = _Counts()
        fields = ["doc_id", "text_hash", "n", "node", "shingle", "hits"]
        null = lambda n: pa.nulls(n, pa.int64())
        for batch in tidy(batches):
            sizes, nodes = [np.zeros(0, np.int64)], [np.zeros(0, np.int64)]
            for _, values, bounds, digest in _sets(batch.column(1), size):
                counts.add(values)
                sizes.append(np.diff(bounds))
                nodes.append(digest)
            n = batch.num_rows
            yield pa.record_batch([batch.column(0), batch.column(2), pa.array(np.concatenate(sizes)), pa.array(np.concatenate(nodes)), null(n), null(n)], names=fields)
        counts.fold()
        loud = np.flatnonzero(counts.hits >= RECURS)
        if len(loud):
            yield pa.record_batch([*[null(len(loud))] * 4, pa.array(counts.values[loud].view(np.int64)), pa.array(counts.hits[loud])], names=fields)

    return docs.mapInArrow(run, "doc_id long, text_hash long, n long, node long, shingle long, hits long")


def _frequency(profile: DataFrame) -> tuple[np.ndarray, np.ndarray]:
    """The most frequent shingles, sorted, and their log-scaled frequencies: at most ``FREQUENT`` rows of two numbers."""
    seen = profile.where(F.col("shingle").isNotNull()).groupBy("shingle").agg(F.sum("hits").alias("hits")).orderBy(F.desc("hits"), "shingle").limit(FREQUENT).toArrow()
    values, hits = seen.column("shingle").to_numpy().view(np.uint64), seen.column("hits").to_numpy()
    order = np.argsort(values)
    del seen
    release_memory()
    return values[order], np.clip(np.log2(np.maximum(hits[order], 1)) * 6, 1, 255).astype(np.uint64)


def _loudness(values: np.ndarray, frequency: tuple[np.ndarray, np.ndarray]) -> np.ndarray:
    known, level = frequency
    if not len(known):
        return np.zeros(len(values), np.uint64)
    at = np.minimum(np.searchsorted(known, values), len(known) - 1)
    return np.where(known[at] == values, level[at], np.uint64(0))


def _prefixes(docs: DataFrame, size: int, percent: int, frequency) -> DataFrame:
    """``(node, n, keys, bands, bits)``: the rarest shingles in order, the least-hash bands, and the bitmap, of each distinct set that a task sees."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        table, seen = frequency.value, set()
        for batch in tidy(batches):
            for _, values, bounds, digest in _sets(batch.column(1), size):
                order = (_loudness(values, table) << np.uint64(56)) | (values >> np.uint64(8))
                nodes, sizes, keys, bands, bits = [], [], [], [], []
                for r in range(len(digest)):
                    low, high = int(bounds[r]), int(bounds[r + 1])
                    n = high - low
                    if not n or (name := (int(digest[r]), n)) in seen:
                        continue
                    seen.add(name)
                    most = n - -(-percent * n // 100) + 1
                    part = order[low:high]
                    keys.append(np.sort(np.partition(part, most - 1)[:most] if most < n else part))
                    bands.append(_bands(values[low:high]))
                    bits.append(_bitmap(values[low:high]))
                    nodes.append(name[0])
                    sizes.append(n)
                flat = np.concatenate(keys).view(np.int64) if keys else np.zeros(0, np.int64)
                ends = np.cumsum([0, *map(len, keys)])
                yield pa.record_batch([pa.array(nodes, pa.int64()), pa.array(sizes, pa.int64()), pa.ListArray.from_arrays(pa.array(ends, pa.int32()), pa.array(flat)), pa.array(bands, pa.list_(pa.int64())), pa.array(bits, pa.list_(pa.int64()))], names=["node", "n", "keys", "bands", "bits"])

    return docs.mapInArrow(run, "node long, n long, keys array<long>, bands array<long>, bits array<long>")


def _bitmap(values: np.ndarray) -> np.ndarray:
    """A bitmap of about two bits a shingle, by size band, and 1,024 at least, as longs: in small sets a few hidden differences decide."""
    width = 1 << max(10, min(16, int(len(values) * 2 - 1).bit_length()))
    own = np.zeros(width, np.uint8)
    own[(bw.mix(values) % np.uint64(width)).astype(np.int64)] = 1
    return np.packbits(own, bitorder="little").view(np.int64)


def _bands(values: np.ndarray) -> np.ndarray:
    """Hashes of groups of bucket minima: sets that agree on a group are likely near copies."""
    hashed = np.sort(bw.mix(values ^ np.uint64(0x5851F42D4C957F2D)))
    first = np.searchsorted(hashed, np.arange(BANDS * BAND_ROWS, dtype=np.uint64) << np.uint64(64 - (BANDS * BAND_ROWS).bit_length() + 1))
    least = hashed[first % len(hashed)]  # an empty bucket takes the next one's
    out = np.arange(BANDS, dtype=np.uint64)
    for r in range(BAND_ROWS):
        out = bw.mix(out * np.uint64(31) + least[r::BAND_ROWS])
    return out.view(np.int64)


def _alike(prefixes: DataFrame, percent: int) -> DataFrame:
    """Candidate pairs of each node with the leaders of its bands."""
    banded = prefixes.select("node", "n", F.explode("bands").alias("band"))
    lead = banded.groupBy("band").agg(F.min("node").alias("b"), F.max("node").alias("other"), F.min(F.struct("node", "n")).alias("l")).where("b != other").select("band", "b", F.col("l.n").alias("n_b"))
    met = banded.join(lead, "band").where((F.col("node") != F.col("b")) & (100 * F.least("n", "n_b") >= percent * F.greatest("n", "n_b")))
    return met.select(F.col("node").alias("a"), "b", F.col("n").alias("n_a"), "n_b").distinct()


def _band(percent: int) -> Column:
    return F.floor(F.log(F.col("n").cast("double")) / F.lit(-math.log(percent / 100)) + 1e-9).cast("int")


def _tiles(scratch: Scratch, prefixes: DataFrame, percent: int, parts: int) -> DataFrame:
    """Prefix entries ``(key, node, n, at)`` that share their shingle with another node of a near size; ``at`` is the entry's place."""
    frequent = F.shiftrightunsigned("key", 56) != 0
    entry = prefixes.select("node", F.col("n").cast("int").alias("n"), F.posexplode("keys").alias("at", "key"))
    dealt = entry.withColumn("salt", F.when(frequent, F.pmod("node", F.lit(SALTS))).otherwise(F.lit(0)).cast("int")).repartition(parts, "key", "salt")
    beside = Window.partitionBy("key", "salt").orderBy("node")
    dealt = dealt.select("key", "node", "n", "at", F.lag("node").over(beside).alias("before"), F.lead("node").over(beside).alias("after"))
    kept = dealt.where((frequent | F.col("before").isNotNull() | F.col("after").isNotNull()) & (F.col("before").isNull() | (F.col("before") != F.col("node"))))
    kept = scratch.keep(kept.select("key", "node", "n", "at", _band(percent).alias("band")))
    tile = kept.groupBy("key", "band").agg(F.min("node").alias("low"), F.max("node").alias("high"))
    shared = tile.groupBy("key").agg(F.collect_list(F.struct("band", "low", "high")).alias("bands"), F.min("low").alias("low"), F.max("high").alias("high")).where("low != high").select("key", "bands")
    company = F.exists("bands", lambda b: (F.abs(b["band"] - F.col("band")) <= 1) & ((b["low"] != F.col("node")) | (b["high"] != F.col("node"))))
    tiles = scratch.keep(kept.join(shared, "key").where(company).select("key", "node", "n", "at"))
    scratch.drop(kept)
    return tiles


def _bounded(pairs: DataFrame, percent: int) -> DataFrame:
    """Pairs ``(a, n_a, b, n_b, hits)`` that sizes and shared prefix entries still allow."""
    low, high = F.least("n_a", "n_b"), F.greatest("n_a", "n_b")
    beyond = lambda n: n - (n - F.ceil(F.lit(percent) * n / F.lit(100.0) - 1e-9) + 1)
    allowed = F.col("hits") + F.greatest(beyond(F.col("n_a")), beyond(F.col("n_b"))) >= _needed(F.col("n_a"), F.col("n_b"), percent)
    return pairs.where((100 * low >= percent * high) & allowed)


def _signed_sets(docs: DataFrame, wanted: DataFrame, profile: DataFrame, size: int) -> DataFrame:
    """``(node, bits, shingles)`` for the wanted nodes: one document of each is found by a filter of a fixed size."""
    ids = profile.where("n > 0").groupBy("node").agg(F.min("text_hash").alias("h")).join(wanted, "node").select("h")
    wanted_docs = docs.where(is_lit(bit_set(ids), F.col("text_hash")))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        seen: set = set()
        for batch in tidy(batches):
            for _, values, bounds, digest in _sets(batch.column(1), size):
                rows = []
                for r in range(len(digest)):
                    if bounds[r] < bounds[r + 1] and int(digest[r]) not in seen:
                        seen.add(int(digest[r]))
                        rows.append(r)
                bits = []
                for r in rows:
                    part = values[bounds[r] : bounds[r + 1]]
                    bits.append(_bitmap(part))
                sets = [values[bounds[r] : bounds[r + 1]].view(np.int64) for r in rows]
                yield pa.record_batch([pa.array(digest[rows] if rows else [], pa.int64()), pa.array(bits, pa.list_(pa.int64())), pa.array(sets, pa.list_(pa.int64()))], names=["node", "bits", "shingles"])

    return durable(wanted_docs.mapInArrow(run, "node long, bits array<long>, shingles array<long>").dropDuplicates(["node"]))


def _fold(bits: Column, width: Column) -> Column:
    """A bitmap folded by OR to ``width`` words (a power of two), so that bitmaps of unlike bands compare."""
    folded = F.transform(F.sequence(F.lit(0), width - 1), lambda i: F.aggregate(F.sequence(i, F.size(bits) - 1, width), F.lit(0).cast("long"), lambda acc, k: acc.bitwiseOR(F.get(bits, k))))
    return F.when(F.size(bits) == width, bits).otherwise(folded)


def _room(bits_a: Column, bits_b: Column) -> Column:
    """The greatest intersection that the bit counts of two bitmaps allow."""
    width = F.least(F.size(bits_a), F.size(bits_b))
    apart = F.aggregate(F.zip_with(_fold(bits_a, width), _fold(bits_b, width), lambda x, y: F.bit_count(x.bitwiseXOR(y))), F.lit(0), lambda acc, x: acc + x)
    return F.floor((F.col("n_a") + F.col("n_b") - apart) / 2)


def _near(percent: int) -> Column:
    """Do the bit counts of ``bits_a`` and ``bits_b`` leave room for the needed overlap?"""
    return _room(F.col("bits_a"), F.col("bits_b")) >= _needed(F.col("n_a"), F.col("n_b"), percent)


def _close(docs: DataFrame, pairs: DataFrame, profile: DataFrame, size: int, percent: int) -> DataFrame:
    """Links ``(a, b)`` among candidate pairs: bitmap bound first, then the exact intersection."""
    pairs = durable(pairs)
    sets = _signed_sets(docs, _nodes(pairs), profile, size)
    bits_a, bits_b = (sets.select(F.col("node").alias(x), F.col("bits").alias(f"bits_{x}")) for x in "ab")
    return _verified(pairs.join(bits_a, "a").join(bits_b, "b").where(_near(percent)), sets, percent)


def _nodes(pairs: DataFrame) -> DataFrame:
    return pairs.select(F.col("a").alias("node")).unionByName(pairs.select(F.col("b").alias("node"))).distinct()


def _verified(pairs: DataFrame, sets: DataFrame, percent: int) -> DataFrame:
    """The pairs ``(a, b)`` whose sorted arrays intersect as needed."""
    both = pairs.select("a", "b").join(sets.select(F.col("node").alias("a"), F.col("shingles").alias("set_a")), "a").join(sets.select(F.col("node").alias("b"), F.col("shingles").alias("set_b")), "b")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in tidy(batches):
            keep = []
            for x, y in zip(batch.column(2), batch.column(3), strict=True):
                left, right = (v.values.to_numpy().view(np.uint64) for v in (x, y))
                common = len(np.intersect1d(left, right, assume_unique=True))
                keep.append(100 * common >= percent * (len(left) + len(right) - common))
            yield batch.filter(pa.array(keep, pa.bool_())).select([0, 1])

    return durable(both.select("a", "b", "set_a", "set_b").mapInArrow(run, "a long, b long"))


def _mixed(scratch: Scratch, tiles: DataFrame, links: DataFrame) -> DataFrame:
    """Entries ``(key, node, n, at, root, main)`` of the tiles that hold several components; main is the largest there."""
    labelled = scratch.keep(tiles.join(components(links), "node", "left").select("key", "node", "n", "at", F.coalesce("root", "node").alias("root")))
    held = labelled.groupBy("key", "root").agg(F.count(F.lit(1)).alias("held"))
    mixed = held.groupBy("key").agg(F.max_by("root", F.struct("held", "root")).alias("main"), F.min("root").alias("r0"), F.max("root").alias("r1")).where("r0 != r1").select("key", "main")
    entries = scratch.keep(labelled.join(mixed, "key"))
    scratch.drop(labelled)
    return entries


def _led(entries: DataFrame, turn: int, percent: int) -> DataFrame:
    """Candidate partners for the entries outside their tile's main component: leaders of that component, new ones each turn.

    A tile's leaders are its members of the least rank, so near tiles share their leaders and hits with them add up.
    """
    ranked = Window.partitionBy("key").orderBy(F.xxhash64("node", F.lit(turn)))
    lead = entries.where("root = main").withColumn("place", F.row_number().over(ranked)).where(F.col("place") <= LEADERS).select("key", F.col("node").alias("b"), F.col("n").alias("n_b"))
    met = entries.where("root != main").select("key", F.col("node").alias("a"), F.col("n").alias("n_a")).join(lead, "key").groupBy("a", "b", "n_a", "n_b").agg(F.count(F.lit(1)).alias("hits"))
    # Hits with what does not lead every tile it shares are too few; what a low count hides is looked at later.
    return _closest(_bounded(met.withColumn("hits", 2 * F.col("hits")), percent), 2)


def _closest(pairs: DataFrame, most: int | None, by: str = "hits") -> DataFrame:
    """Each first node's pairs of the greatest ``by``."""
    if most is None:
        return pairs
    order = Window.partitionBy("a").orderBy(F.desc(by), "b")
    return pairs.withColumn("place", F.row_number().over(order)).where(F.col("place") <= most).drop("place")


def _open_pairs(entries: DataFrame, prefixes: DataFrame, percent: int) -> DataFrame:
    """Pairs ``(a, b, room)`` across components that sizes, places and bit counts still allow, of a tile's minor members with all others."""
    bits = prefixes.select("node", "bits").join(entries.select("node").distinct(), "node", "left_semi").dropDuplicates(["node"])
    own = Window.partitionBy("node").orderBy("at")
    prior = F.filter(F.array(*[F.lag("key", k).over(own) for k in range(1, PRIOR + 1)]), lambda k: k.isNotNull())
    entries = entries.select("key", "node", "n", (F.col("n") - F.col("at")).alias("rest"), "root", (F.col("root") == F.col("main")).alias("is_main"), prior.alias("prior")).join(bits, "node")
    columns = ("node", "n", "rest", "root", "is_main", "prior", "bits")
    minor, other = (entries.select("key", *[F.col(c).alias(f"{c}_{x}") for c in columns]) for x in "ab")
    apart = (F.col("root_a") != F.col("root_b")) & (F.col("is_main_b") | (F.col("node_a") < F.col("node_b"))) & (100 * F.least("n_a", "n_b") >= percent * F.greatest("n_a", "n_b"))
    reach = F.least("rest_a", "rest_b") >= _needed(F.col("n_a"), F.col("n_b"), percent)
    met = minor.where("not is_main_a").join(other, "key").where(apart & reach & ~F.arrays_overlap("prior_a", "prior_b") & _near(percent))
    return met.select(F.least("node_a", "node_b").alias("a"), F.greatest("node_a", "node_b").alias("b"), _room(F.col("bits_a"), F.col("bits_b")).alias("room")).groupBy("a", "b").agg(F.max("room").alias("room"))


def _across(pairs: DataFrame, links: DataFrame) -> DataFrame:
    """The pairs whose nodes lie in different components."""
    roots = durable(components(links))
    for side in "ab":
        pairs = pairs.join(roots.select(F.col("node").alias(side), F.col("root").alias(f"root_{side}")), side, "left").withColumn(f"root_{side}", F.coalesce(f"root_{side}", side))
    return pairs.where("root_a != root_b").drop("root_a", "root_b")


def near_duplicates(docs: DataFrame, size: int = 4, percent: int = 85, key: str = "doc_id", text: str = "text") -> DataFrame:
    """``(doc_id, text_hash, n_shingles, component_id, group)`` per row; ``group`` names the component even without ids."""
    spark = docs.sparkSession
    rows = docs.select(F.col(key).cast("long").alias("doc_id"), F.col(text).alias("text"), F.xxhash64(F.coalesce(F.col(text), F.lit(""))).alias("text_hash"))
    profile = durable(_profile(rows, size))
    frequency = spark.sparkContext.broadcast(_frequency(profile))
    own = profile.where(F.col("shingle").isNull()).select("doc_id", "text_hash", "n", "node")
    parts = int(spark.conf.get("spark.sql.shuffle.partitions"))
    scratch = Scratch(spark)
    prefixes = scratch.keep(_prefixes(rows, size, percent, frequency))
    tiles = _tiles(scratch, prefixes, percent, parts)
    drop_finished_shuffles(spark)
    links = _close(rows, _alike(prefixes, percent), own, size, percent)
    for turn in range(ROUNDS):
        entries = _mixed(scratch, tiles, links)
        links = links.unionByName(_close(rows, _led(entries, turn, percent), own, size, percent))
        scratch.drop(entries)
        drop_finished_shuffles(spark)

    entries = _mixed(scratch, tiles, links)
    scratch.drop(tiles)
    rest = durable(_open_pairs(entries, prefixes, percent))
    scratch.drop(entries, prefixes)
    drop_finished_shuffles(spark)
    sets = _signed_sets(rows, _nodes(rest), own, size)
    for most in LAST_ROUNDS:
        rest = durable(_across(rest, links))
        links = links.unionByName(_verified(_closest(rest, most, "room"), sets, percent))
        drop_finished_shuffles(spark)
    roots = components(links)

    least = own.where("n > 0").groupBy("node").agg(F.min("doc_id").alias("least")).join(roots, "node", "left").select("node", "least", F.coalesce("root", "node").alias("group"))
    names = least.groupBy("group").agg(F.min("least").alias("component_id"))
    named = least.join(names, "group").select("node", "group", "component_id")
    full = own.where("n > 0").join(named, "node").select("doc_id", "text_hash", F.col("n").alias("n_shingles"), "component_id", "group")
    alone = own.where("n = 0").select("doc_id", "text_hash", F.col("n").alias("n_shingles"), F.col("doc_id").alias("component_id"), F.lit(None).cast("long").alias("group"))
    return full.unionByName(alone)


def keep_one_per_group(docs: DataFrame, size: int = 5, percent: int = 80, key: str = "doc_id", text: str = "text") -> DataFrame:
    """The rows of ``docs``, all columns kept, with one document of each group: the one of the least key.

    Rows without shingles all stay. Only rows of groups with more than one row are shuffled with their text.
    """
    found = near_duplicates(docs, size, percent, key, text)
    groups = found.where(F.col("group").isNotNull()).groupBy("group").agg(F.min(F.struct(F.col("doc_id").isNull().alias("last"), "doc_id", "text_hash")).alias("stay"), F.count(F.lit(1)).alias("members"))
    many = groups.where("members > 1").select("group", "stay")
    ruled = found.join(many, "group").select("doc_id", "text_hash", "group", ((F.col("doc_id").eqNullSafe(F.col("stay.doc_id"))) & (F.col("text_hash") == F.col("stay.text_hash"))).alias("stays"))
    ruled = durable(ruled.distinct())
    lit = bit_set(ruled.select("text_hash"))
    body = F.xxhash64(F.coalesce(F.col(text), F.lit("")))
    marked = docs.withColumns({"_id": F.col(key).cast("long"), "_h": body})
    touched = is_lit(lit, F.col("_h"))
    rule = ruled.select(F.col("doc_id").alias("_rid"), F.col("text_hash").alias("_rh"), "group", "stays")
    judged = marked.where(touched).join(rule, F.col("_h").eqNullSafe(F.col("_rh")) & F.col("_id").eqNullSafe(F.col("_rid")), "left")
    free = judged.where(F.col("group").isNull()).select(*docs.columns)
    kept = judged.where("stays").dropDuplicates(["group"]).select(*docs.columns)
    return marked.where(~touched).select(*docs.columns).unionByName(free).unionByName(kept)

