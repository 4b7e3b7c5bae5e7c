"""Benchmark decontamination with suffix arrays over the training words.

Each task cuts its rows into shards of a few million bytes and builds, per shard, the suffix array of the shard's word
sequence (prefix doubling, refined only where suffixes still tie, to the depth of the longest benchmark item). Every
suffix of every benchmark item is binary-searched in it, which yields its longest verbatim match; a shard suffix's own
longest match is with one of the two test suffixes next to it in that order. Windows whose match is long enough are then searched for their whole range of occurrences. Nothing is shuffled.
The benchmark is sent out in blocks of a bounded number of bytes; a task goes through the blocks one after the other and
holds one at a time.

A window is ``window`` consecutive words of an item (an item with fewer words, but not none, is one window). A document
word inside an occurrence of a window is hit.

Defined cases: a null text has no words; items without words have no windows; a null item id marks hits but is not
listed; repeated items and ids count once, repeated documents each on their own; empty tables leave nothing hit; columns
besides key and text never enter.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from phraseloom.llm import byte_words as bw
from phraseloom.llm.common import tidy

WINDOW = 10
BLOCK_BYTES = 16 << 20
SHARD_BYTES = 2 << 20
ROWS = 1024
SHARD_WORDS = 1 << 20
REPORT = "doc_id long, n_words long, n_hit long, n_items long, items_sha256 string, contaminated boolean, longest_match long, longest_at long"


@dataclass
class TestBlock:
    """Benchmark items as word values: ``at`` bounds the items, ``ids`` are their ids as strings (None: no id)."""

    values: np.ndarray
    at: np.ndarray
    ids: list[str | None]
    window: int

    def __post_init__(self) -> None:
        sizes = np.diff(self.at)
        self.end = np.repeat(self.at[1:], sizes)
        self.item = np.repeat(np.arange(len(sizes)), sizes)
        self.width = np.repeat(np.minimum(sizes, self.window), sizes)
        self.depth = int(sizes.max(initial=0))
        self.order = suffix_array(self.values, self.end, self.depth) if len(self.values) else np.zeros(0, np.int64)


def suffix_array(values: np.ndarray, end: np.ndarray, depth: int) -> np.ndarray:
    """Positions in the order of their suffixes' first ``depth`` words; a suffix ends with its document (``end``)."""
    n = len(values)
    order = np.argsort(values, kind="stable")
    opens = np.ones(n, dtype=bool)
    opens[1:] = values[order[1:]] != values[order[:-1]]
    rank = np.empty(n, np.int64)
    rank[order] = np.maximum.accumulate(np.where(opens, np.arange(n), 0))
    known = 1
    while known < depth:
        tied = ~opens
        tied[:-1] |= ~opens[1:]
        slot = np.flatnonzero(tied)
        if not len(slot):
            break
        place = order[slot]
        follow = place + known
        second = np.where(follow < end[place], rank[np.minimum(follow, n - 1)] + 1, 0)
        first = rank[place]
        turn = np.lexsort((second, first))
        place, first, second = place[turn], first[turn], second[turn]
        order[slot] = place
        starts = np.ones(len(slot), dtype=bool)
        starts[1:] = (first[1:] != first[:-1]) | (second[1:] != second[:-1])
        rank[place] = np.maximum.accumulate(np.where(starts, slot, 0))
        opens[slot] = starts
        known *= 2
    return order


def _compare(values: np.ndarray, end: np.ndarray, place: np.ndarray, test: TestBlock, query: np.ndarray, stop: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Length of the agreement of shard suffixes with test suffixes up to ``stop``, and whether the shard's is smaller."""
    agree = np.zeros(len(place), np.int64)
    less = np.zeros(len(place), dtype=bool)
    live = np.arange(len(place))
    while len(live):
        at, q = place[live] + agree[live], query[live] + agree[live]
        live, at, q = (x[q < stop[live]] for x in (live, at, q))
        ended = at >= end[place[live]]
        less[live[ended]] = True
        live, at, q = live[~ended], at[~ended], q[~ended]
        left, right = values[at], test.values[q]
        less[live] = left < right
        live = live[left == right]
        agree[live] += 1
    return agree, less


def _search(values: np.ndarray, end: np.ndarray, order: np.ndarray, test: TestBlock, query: np.ndarray, stop: np.ndarray, after: bool = False) -> np.ndarray:
    """First slot whose suffix is not smaller (``after``: is greater) than each test suffix cut at ``stop``."""
    low, high = np.zeros(len(query), np.int64), np.full(len(query), len(order), np.int64)
    while (open_ := np.flatnonzero(low < high)).size:
        middle = (low[open_] + high[open_]) // 2
        agree, less = _compare(values, end, order[middle], test, query[open_], stop[open_])
        if after:
            less |= agree == stop[open_] - query[open_]
        low[open_] = np.where(less, middle + 1, low[open_])
        high[open_] = np.where(less, high[open_], middle)
    return low


def match_shard(values: np.ndarray, end: np.ndarray, test: TestBlock, matches: bool = True) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Occurrences of windows in one shard: places, widths, items; and (``matches``) the longest match that starts at each place."""
    none = np.zeros(0, np.int64)
    if not len(values) or not len(test.values):
        return none, none, none, np.zeros(len(values), np.int64)
    order = suffix_array(values, end, test.depth)
    query = np.arange(len(test.values))
    slot = _search(values, end, order, test, query, test.end)
    longest = np.zeros(len(query), np.int64)
    for near in (slot - 1, slot):
        ok = np.flatnonzero((near >= 0) & (near < len(order)))
        agree, _ = _compare(values, end, order[near[ok]], test, query[ok], test.end[ok])
        longest[ok] = np.maximum(longest[ok], agree)
    full = np.flatnonzero((longest >= test.width) & (query + test.width <= test.end))
    stop = full + test.width[full]
    low = _search(values, end, order, test, full, stop)
    high = _search(values, end, order, test, full, stop, after=True)
    count = high - low
    places = order[np.repeat(low - np.concatenate([[0], np.cumsum(count)[:-1]]), count) + np.arange(count.sum())] if count.sum() else none
    starts = np.zeros(len(values), np.int64)
    if matches:
        above = np.searchsorted(slot[test.order], np.arange(len(order)), side="right")  # test suffixes that are not greater
        for near in (above - 1, above):
            ok = np.flatnonzero((near >= 0) & (near < len(query)))
            with_ = test.order[near[ok]]
            agree, _ = _compare(values, end, order[ok], test, with_, test.end[with_])
            starts[order[ok]] = np.maximum(starts[order[ok]], agree)
    return places, np.repeat(test.width[full], count), np.repeat(test.item[full], count), starts


def _test_blocks(benchmark: DataFrame, window: int, block_bytes: int, key: str, text: str) -> list:
    """The benchmark's distinct items as broadcast blocks, each collected by itself and of bounded size."""
    spark = benchmark.sparkSession
    items = benchmark.select(F.col(key).cast("string").alias("id"), F.col(text).alias("text")).where(F.col("text").isNotNull()).distinct()
    total = items.agg(F.coalesce(F.sum(F.octet_length("text")), F.lit(0))).first()[0]
    blocks = max(1, -(-total // block_bytes))
    out = []
    for k in range(blocks):
        part = items.where(F.pmod(F.xxhash64("id", "text"), F.lit(blocks)) == k).toArrow().sort_by("id")
        values, at = bw.words(*bw.buffers(part.column("text")), bw.ALNUM)
        out.append(spark.sparkContext.broadcast(TestBlock(values, at, part.column("id").to_pylist(), window)))
    return out


def _shards(values: np.ndarray, at: np.ndarray, overlap: int):
    """Word ranges ``(low, high, read_to)`` of a bounded size; a match may read ``overlap`` words past ``high``."""
    for low in range(0, len(values), SHARD_WORDS):
        high = min(low + SHARD_WORDS, len(values))
        yield low, high, min(high + overlap, len(values))


class Scan:
    """The words of a text column and what the blocks passed to ``add`` one after the other have found in them."""

    def __init__(self, column: pa.Array) -> None:
        raw, offsets = bw.buffers(column)
        rows = len(offsets) - 1
        self.parts = []
        for first, last in bw.slices(offsets, SHARD_BYTES):
            values, at = bw.words(raw[offsets[first] : offsets[last]], offsets[first : last + 1] - offsets[first], bw.ALNUM)
            self.parts.append((first, last, values, at, np.zeros(len(values) + 1, np.int32)))
        self.found: list[set[str]] = [set() for _ in range(rows)]
        self.best, self.best_at = np.zeros(rows, np.int64), np.full(rows, -1, np.int64)

    def add(self, test: TestBlock, matches: bool = True) -> None:
        for first, last, values, at, cover in self.parts:
            rows = last - first
            row_of = np.repeat(np.arange(rows), np.diff(at))
            end = at[1:][row_of] if len(row_of) else np.zeros(0, np.int64)
            for low, high, reach in _shards(values, at, test.depth):
                places, widths, items, longest = match_shard(values[low:reach], np.minimum(end[low:reach], reach) - low, test, matches)
                own = places < high - low
                places, widths, items = places[own] + low, widths[own], items[own]
                np.add.at(cover, places, 1)
                np.add.at(cover, places + widths, -1)
                for r, i in zip(*np.divmod(np.unique(row_of[places] * len(test.ids) + items), max(1, len(test.ids))), strict=True):
                    if test.ids[i] is not None:
                        self.found[first + r].add(test.ids[i])
                got = np.flatnonzero(longest[: high - low])
                here = row_of[got + low]
                most = np.zeros(rows, np.int64)
                np.maximum.at(most, here, longest[got])
                top = longest[got] == most[here]
                starts = got[top]
                for r, k in zip(*np.unique(here[top], return_index=True), strict=True):
                    p, row = starts[k] + low - at[r], first + r
                    if most[r] > self.best[row] or most[r] == self.best[row] and p < self.best_at[row]:
                        self.best[row], self.best_at[row] = most[r], p

    def rows(self) -> Iterator[tuple[int, int, int, set[str], int, int]]:
        """Per row: words, hit words, number of items, item ids, longest match and its first place (none: 0 and -1)."""
        for first, last, _, at, cover in self.parts:
            hit = np.concatenate([[0], np.cumsum(np.cumsum(cover[:-1]) > 0)])
            for r in range(last - first):
                names = self.found[first + r]
                yield int(at[r + 1] - at[r]), int(hit[at[r + 1]] - hit[at[r]]), len(names), names, int(self.best[first + r]), int(self.best_at[first + r])


def scan_rows(column: pa.Array, blocks: Iterable[TestBlock], matches: bool = True) -> Iterator[tuple[int, int, int, set[str], int, int]]:
    """``Scan.rows`` after all blocks, which are taken one after the other."""
    scan = Scan(column)
    for block in blocks:
        scan.add(block, matches)
    yield from scan.rows()


def _one_by_one(sent: list) -> Iterator[TestBlock]:
    """The blocks of broadcasts; of several, a worker keeps none once it is through with it and reads it again for the next batch."""
    for broadcast in sent:
        yield broadcast.value
        if len(sent) > 1 and getattr(broadcast, "_path", None):
            broadcast.__dict__.pop("_value", None)


def report(docs: DataFrame, benchmark: DataFrame, window: int = WINDOW, block_bytes: int = BLOCK_BYTES, key: str = "doc_id", text: str = "text", item_key: str = "item_id", item_text: str = "text") -> DataFrame:
    """One row per document: words, hits, items, and the longest verbatim match with any item and its first place."""
    blocks = _test_blocks(benchmark, window, block_bytes, item_key, item_text)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in tidy(batches):
            rows = list(scan_rows(batch.column(1), _one_by_one(blocks)))
            words, hits, counts, names, longest, place = zip(*rows, strict=True) if rows else ([],) * 6
            digests = [hashlib.sha256(",".join(sorted(x)).encode()).hexdigest() for x in names]
            yield pa.record_batch(
                [batch.column(0), *(pa.array(x, pa.int64()) for x in (words, hits, counts)), pa.array(digests, pa.string()), pa.array([h > 0 for h in hits], pa.bool_()), pa.array(longest, pa.int64()), pa.array(place, pa.int64())],
                names=["doc_id", "n_words", "n_hit", "n_items", "items_sha256", "contaminated", "longest_match", "longest_at"],
            )

    return docs.select(F.col(key).cast("long").alias("doc_id"), F.col(text).alias("text")).mapInArrow(run, REPORT)


def decontaminate(docs: DataFrame, benchmark: DataFrame, window: int = WINDOW, block_bytes: int = BLOCK_BYTES, text: str = "text", item_key: str = "item_id", item_text: str = "text") -> DataFrame:
    """The rows of ``docs``, all columns kept, without those that have a hit word."""
    blocks = _test_blocks(benchmark, window, block_bytes, item_key, item_text)
    place = docs.columns.index(text)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in tidy(batches):
            for low in range(0, batch.num_rows, ROWS):
                part = batch.slice(low, ROWS)
                clean = [hits == 0 for _, hits, *_ in scan_rows(part.column(place), _one_by_one(blocks), matches=False)]
                yield part.filter(pa.array(clean, pa.bool_()))

    return docs.mapInArrow(run, docs.schema)
