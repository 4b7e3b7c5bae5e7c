"""Orthogonality of Boolean vectors through parse lengths, and the direct join as its baseline.

Vectors are the distinct sign patterns of a table; multiplicities carry the counts of all rows. ``patterns`` takes the
first d <= 10 coordinates as an integer, so that at most 2^d vectors come to the driver. ``whole_patterns`` takes every
coordinate as a string of 0 and 1; its operators (``whole_*``) cut A into blocks; B is broadcast in groups, and nothing else comes to the driver but counts.
``whole_pair_gadget`` returns every pair, so there each task has few patterns of either set, and its rows come in an order that compresses.
"""

from __future__ import annotations

from collections.abc import Callable, Iterable, Iterator
from functools import lru_cache
from math import isqrt

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.pandas.types import to_arrow_schema

from phraseloom.functions import gadgets as g
from phraseloom.functions import kernels as k
from phraseloom.operators.per_string import SYMBOLS as GROUP, flat_map

MOST_DIMENSIONS = 10


def pattern(embedding: str, d: int) -> Column:
    """The first d signs as an integer, coordinate 1 in the highest bit."""
    bits = F.transform(F.slice(embedding, 1, d), lambda x: (x > 0).cast("long"))
    return F.aggregate(bits, F.lit(0).cast("long"), lambda acc, b: acc * 2 + b)


def patterns(vectors: DataFrame, d: int, key: str = "vec_id", embedding: str = "embedding") -> tuple[DataFrame, DataFrame]:
    """``(bits, copies)`` of the set A (even keys) and of the set B (odd keys)."""
    if d > MOST_DIMENSIONS:
        raise ValueError(f"at most {MOST_DIMENSIONS} dimensions")
    named = vectors.select((F.col(key) % 2).alias("side"), pattern(embedding, d).alias("bits"))
    return tuple(named.where(F.col("side") == side).groupBy("bits").agg(F.count(F.lit(1)).alias("copies")) for side in (0, 1))


def _vector(bits: int, d: int) -> list[int]:
    return [bits >> (d - 1 - j) & 1 for j in range(d)]


def square_set(a: DataFrame, d: int) -> tuple[list[int], int]:
    """A's patterns (at most 2^d), filled up to a square number by all-ones vectors; and how many were added."""
    own = sorted(r["bits"] for r in a.select("bits").collect())
    root = isqrt(max(0, len(own) - 1)) + 1
    return own + [(1 << d) - 1] * (root * root - len(own)), root * root - len(own)


def query_strings(a: list[int], u: int, d: int) -> tuple[str, list[str]]:
    """What comes before A's blocks, for one query vector, and the blocks."""
    fresh, n = g.Fresh(), len(a)
    head = g.dictionary(n, d, fresh) + g.query_vector(_vector(u, d), n, fresh)
    return head, g.matrix([_vector(v, d) for v in a], fresh)


def phrases_per_vector(a: list[int], u: int, d: int) -> list[int]:
    """Phrases that cover each block of A: d + 1, and one more where the vectors share a coordinate."""
    head, blocks = query_strings(a, u, d)
    text, at = head + "".join(blocks), len(head)
    ends, counts = [], [0] * len(blocks)
    for b in blocks:
        ends.append((ends[-1] if ends else at) + len(b))
    block = 0
    while at < len(text):
        at += max(1, k.earlier_factor(text, at)[0])
        counts[block] += 1
        if at >= ends[block]:
            block += 1
    return counts


def phrase_counts(a: DataFrame, b: DataFrame, d: int) -> DataFrame:
    """``(u, v, phrases)`` for every query pattern and every pattern of A."""
    own, added = square_set(a, d)

    def kernel(u: int) -> list[tuple]:
        return [(u, v, c) for v, c in zip(own[: len(own) - added], phrases_per_vector(own, u, d), strict=False)]

    return flat_map(b.select("bits"), kernel, "u long, v long, phrases long")


def decide(a: DataFrame, b: DataFrame, d: int) -> DataFrame:
    """Per query pattern: difference of the two parse lengths, orthogonal patterns, and whether there is one."""
    own, added = square_set(a, d)

    def kernel(u: int) -> list[tuple]:
        head, blocks = query_strings(own, u, d)
        parse = lambda s: sum(1 for _ in k.parse(s))
        diff = parse(head + "".join(blocks)) - parse(head)
        orthogonal = (d + 2) * len(own) - diff - (added if u == 0 else 0)
        return [(u, diff, orthogonal, orthogonal > 0)]

    return flat_map(b.select("bits"), kernel, "u long, diff long, orthogonal long, has_orthogonal boolean")


def pair_gadget(a: DataFrame, b: DataFrame, d: int) -> DataFrame:
    """The single-pair construction: d phrases cover an orthogonal vector's gadget, d + 1 another's."""
    own = sorted(r["bits"] for r in a.select("bits").collect())

    def kernel(u: int) -> list[tuple]:
        out = []
        for v in own:
            fresh = g.Fresh()
            head = g.simple_dictionary(d, fresh) + fresh() + g.simple_query(_vector(u, d), fresh) + fresh()
            text, at, count = head + g.simple_vector(_vector(v, d)), len(head), 0
            while at < len(text):
                at, count = at + max(1, k.earlier_factor(text, at)[0]), count + 1
            out.append((u, v, count))
        return out

    return flat_map(b.select("bits"), kernel, "u long, v long, phrases long")


def naive_set(a: DataFrame, b: DataFrame, d: int) -> DataFrame:
    """The faulty construction: simple gadgets of all of A behind one query; later gadgets copy earlier ones."""
    own = sorted(r["bits"] for r in a.select("bits").collect())

    def kernel(u: int) -> list[tuple]:
        fresh = g.Fresh()
        head = g.simple_dictionary(d, fresh) + fresh() + g.simple_query(_vector(u, d), fresh) + fresh()
        text, at, count = head + "".join(g.simple_vector(_vector(v, d)) for v in own), len(head), 0
        while at < len(text):
            at, count = at + max(1, k.earlier_factor(text, at)[0]), count + 1
        return [(u, len(own), count)]

    return flat_map(b.select("bits"), kernel, "u long, vectors long, phrases long")


def sizes(b: DataFrame, a: DataFrame, d: int) -> DataFrame:
    """Symbols of dictionary, query block, and blocks of A, and the substitutions that lead from the all-ones query to u."""
    own, _ = square_set(a, d)

    def kernel(u: int) -> list[tuple]:
        n = len(own)
        fresh = g.Fresh()
        first = len(g.dictionary(n, d, fresh))
        ones, mine = (g.query_vector(_vector(x, d), n, g.Fresh()) for x in ((1 << d) - 1, u))
        return [(u, n, first, len(mine), sum(map(len, g.matrix([_vector(v, d) for v in own], fresh))), sum(x != y for x, y in zip(ones, mine, strict=True)))]

    return flat_map(b.select("bits"), kernel, "u long, n long, dictionary_symbols long, query_symbols long, matrix_symbols long, substitutions long")


def direct_join(a: DataFrame, b: DataFrame) -> DataFrame:
    """The baseline: pairs of patterns without a common bit (both sides at most 2^d rows), with the pairs of rows they stand for."""
    left, right = b.select(F.col("bits").alias("u"), F.col("copies").alias("copies_u")), F.broadcast(a.select(F.col("bits").alias("v"), F.col("copies").alias("copies_v")))
    return left.join(right, F.col("u").bitwiseAND(F.col("v")) == 0).groupBy("u").agg(F.count(F.lit(1)).alias("orthogonal"), F.sum(F.col("copies_u") * F.col("copies_v")).alias("row_pairs"))


# --- all coordinates, A in blocks -----------------------------------------------------------------------------------

WORD = 32


def whole_patterns(vectors: DataFrame, key: str = "vec_id", embedding: str = "embedding") -> tuple[DataFrame, DataFrame]:
    """``(bits, copies)`` of A (even keys) and B (odd keys), bits a string of the signs of all coordinates."""
    bits = F.array_join(F.transform(embedding, lambda x: F.when(x > 0, F.lit("1")).otherwise(F.lit("0"))), "")
    named = vectors.select((F.col(key) % 2).alias("side"), bits.alias("bits"))
    return tuple(named.where(F.col("side") == side).groupBy("bits").agg(F.count(F.lit(1)).alias("copies")) for side in (0, 1))


def _packed(bits: str) -> Column:
    """The string as an array of longs of 32 coordinates each."""
    starts = F.sequence(F.lit(0), F.floor((F.char_length(bits) - 1) / WORD).cast("int"))
    return F.transform(starts, lambda k: F.conv(F.substring(F.col(bits), k * WORD + 1, F.lit(WORD)), 2, 10).cast("long"))


def whole_join(a: DataFrame, b: DataFrame) -> DataFrame:
    """The baseline on all coordinates: for every u of B the patterns of A without a common bit (also none), and the pairs of rows."""
    left = b.select(F.col("bits").alias("u"), F.col("copies").alias("copies_u"), _packed("bits").alias("words_u"))
    right = a.select(F.col("bits").alias("v"), F.col("copies").alias("copies_v"), _packed("bits").alias("words_v"))
    apart = F.forall(F.zip_with("words_u", "words_v", lambda x, y: x.bitwiseAND(y)), lambda w: w == 0)
    return left.join(right, apart, "left").groupBy("u").agg(F.count("v").alias("orthogonal"), F.coalesce(F.sum(F.col("copies_u") * F.col("copies_v")), F.lit(0)).alias("row_pairs"))


#: Patterns of B that one kernel call holds at once.
QUERIES_AT_ONCE = 4096
ROWS_OUT = 1 << 16
#: Bytes of patterns of either set in a task that gives pairs: half of what a Parquet writer's dictionary holds by default; past that the patterns themselves are written, once a pair.
DICTIONARY = 1 << 19
#: Queries that follow one another for every vector where pairs are given, a multiple of 8: their codes recur byte by byte.
RUN = 512
#: Closes a vector that has no separator of its own.
STOP = chr(g.SEPARATORS - 1)


def _numbered(a: DataFrame, size: int) -> DataFrame:
    """A dealt to blocks of about ``size`` patterns."""
    count = max(1, -(-a.count() // size))
    return a.select("bits", F.pmod(F.xxhash64("bits"), F.lit(count)).alias("block"))


def _blocks(a: DataFrame, b: DataFrame, size: int) -> DataFrame:
    """``(own, us)``: every block of A with every group of patterns of B. The groups, one copy of B in all, are broadcast."""
    own = _numbered(a, size).groupBy("block").agg(F.array_sort(F.collect_list("bits")).alias("own"))
    groups = max(1, -(-b.count() // QUERIES_AT_ONCE))
    us = b.groupBy(F.pmod(F.xxhash64("bits"), F.lit(groups)).alias("part")).agg(F.array_sort(F.collect_list("bits")).alias("us"))
    cores = a.sparkSession.sparkContext.defaultParallelism
    dealt = own.select("block", "own", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(groups - 1).cast("long"))).alias("part")).repartition(4 * cores, "block", "part")
    return dealt.join(F.broadcast(us), "part").select("own", "us")


def _tiles(a: DataFrame, b: DataFrame, size: int) -> tuple[DataFrame, DataFrame]:
    """``(own, us, part)``: as ``_blocks``, but a task has one group of B and so many blocks of A as one dictionary holds; and the groups, ``(part, us)``."""
    queries, d = b.agg(F.count(F.lit(1)), F.max(F.char_length("bits"))).first()
    most = max(1, DICTIONARY // ((d or 0) + 4))  # a dictionary has four bytes more for each pattern
    size = min(size, most)
    groups, blocks = max(1, -(-queries // most)), max(1, -(-a.count() // size))
    strips = min(blocks, max(-(-blocks * size // most), -(-4 * a.sparkSession.sparkContext.defaultParallelism // groups)))
    us = b.groupBy(F.pmod(F.xxhash64("bits"), F.lit(groups)).alias("part")).agg(F.array_sort(F.collect_list("bits")).alias("us"))
    own = a.groupBy(F.pmod(F.xxhash64("bits"), F.lit(blocks)).alias("block")).agg(F.array_sort(F.collect_list("bits")).alias("own"))
    dealt = own.select("block", "own", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(groups - 1).cast("long"))).alias("part"))
    dealt = dealt.repartitionById(groups * strips, (F.col("part") * strips + F.col("block") % strips).cast("int"))
    return dealt.join(F.broadcast(us), "part").select("own", "us", "part"), us


def _block_map(rows: DataFrame, kernel: Callable[..., Iterable[list]], schema: str) -> DataFrame:
    """``kernel`` on every pair of blocks; it gives whole columns."""
    kind = T._parse_datatype_string(schema)
    arrow = to_arrow_schema(kind)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for row in zip(*batch.columns, strict=True):
                for columns in kernel(*(x.as_py() for x in row)):
                    yield pa.record_batch([c if isinstance(c, pa.Array) else pa.array(c, f.type) for c, f in zip(columns, arrow, strict=True)], schema=arrow)

    return rows.mapInArrow(run, kind)


def _squared(own: list[str], d: int) -> list[int]:
    root = isqrt(len(own) - 1) + 1
    return [int(v, 2) for v in own] + [(1 << d) - 1] * (root * root - len(own))


def _coordinates(text: str, d: int) -> np.ndarray:
    """The coordinate (from 0 on) of each symbol; 0 for separators."""
    c = k.codes(text)
    return np.where(c < ord(STOP), np.clip((c - g.FIRST) // 3 - 1, 0, d - 1), 0)


def _steps(heads: list[str], tails: list[str]) -> np.ndarray:
    """Where the phrase that begins at each place of the tails ends, for the head of the all-zeros and of the all-ones query; the tails joined.

    All that a query changes in its head are its coordinates' pieces, each closed by separators and each made of symbols of its
    own coordinate. So the longest previous factor at a symbol depends on the query's bit of that symbol's coordinate only,
    and the two extreme queries give the factors of all.
    """
    out, group = [], max(1, GROUP // (len(heads[0]) + len(tails[0]) + 1))
    for head in heads:
        found = (x for i in range(0, len(tails), group) for x in k.lpf_many([head + tail for tail in tails[i : i + group]]))
        out.append(np.concatenate([np.maximum(x[len(head) :], 1) for x in found]))
    return np.arange(len(out[0])) + np.stack(out)


def _walk(steps: np.ndarray, coordinate: np.ndarray, bits: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
    """Phrases from each start to its end, one row for each start, one column for each query; all walk at once."""
    (queries, d), n = bits.shape, steps.shape[1]
    jump = np.append(steps, np.zeros((2, 1), np.int64), axis=1).astype(np.int32)
    jump[:, ends] = ends  # who has arrived stays
    coordinate = np.append(coordinate, 0).astype(np.int32)
    jump, bit = jump.ravel(), (bits * np.int32(n + 1)).astype(np.int32).ravel()
    at, end = np.repeat(starts.astype(np.int32), queries), np.repeat(ends.astype(np.int32), queries)
    row = np.tile(np.arange(queries, dtype=np.int32) * d, len(starts))
    count = np.zeros(len(at), np.int32)
    while (open_ := at != end).any():
        count += open_
        at = jump[bit[row + coordinate[at]] + at]
    return count.reshape(len(starts), queries)


def _counts_to_end(jump: np.ndarray, coordinate: np.ndarray, chosen: np.ndarray) -> np.ndarray:
    """Phrases from the first place to the end, one row for each of some tails of one length, one column for each query.

    ``jump``: where the phrase at a place of a tail ends, for either bit (bit, tail, place). ``chosen``: all ones where the query's
    bit is set, else 0 (coordinate, query). Goes backwards, as the count at a place is one more than at its phrase's end.
    """
    _, tails, length = jump.shape
    counts = np.zeros((length + 1, tails, chosen.shape[1]), chosen.dtype)
    every = np.arange(tails)
    for place in range(length - 1, -1, -1):
        off, on = counts[jump[0, :, place], every], counts[jump[1, :, place], every]
        on ^= off
        on &= chosen[coordinate[place]]
        np.add(np.bitwise_xor(off, on, out=off), 1, out=counts[place])
    return counts[0]


def _bits(us: list[str]) -> np.ndarray:
    return np.frombuffer("".join(us).encode(), np.uint8).reshape(len(us), -1).astype(np.int32) - ord("0")


def _counts(own: list[str], us: list[str]) -> np.ndarray:
    """Phrases that cover each vector of a block (row) for each query (column)."""
    d = len(us[0])
    (zeros, blocks), (ones, _) = (query_strings(_squared(own, d), u, d) for u in (0, (1 << d) - 1))
    tail = "".join(blocks)
    ends = np.cumsum([len(x) for x in blocks])
    starts = ends - [len(x) for x in blocks]
    # a vector ends with its separator, which is a phrase of its own
    return _walk(_steps([zeros, ones], [tail]), _coordinates(tail, d), _bits(us), starts[: len(own)], ends[: len(own)] - 1) + 1


def _pairs(own: list[str], us: list[str], counts: np.ndarray) -> Iterator[tuple[pa.Array, pa.Array, np.ndarray]]:
    """``(u, v, count)`` as columns, a few vectors at a time."""
    names, width = pa.array(us), max(1, ROWS_OUT // len(us))
    for i in range(0, len(own), width):
        part = pa.array(own[i : i + width])
        yield names.take(pa.array(np.tile(np.arange(len(us)), len(part)))), part.take(pa.array(np.repeat(np.arange(len(part)), len(us)))), counts[i : i + width].ravel().astype(np.int64)


def whole_phrase_counts(a: DataFrame, b: DataFrame, size: int = 9) -> DataFrame:
    """``(u, v, phrases, orthogonal)`` for all pairs of patterns: d + 1 phrases cover an orthogonal vector's block, d + 2 another's."""

    def kernel(own: list[str], us: list[str]) -> Iterator[list]:
        for u, v, c in _pairs(own, us, _counts(own, us)):
            yield [u, v, c, c == len(us[0]) + 1]

    return _block_map(_blocks(a, b, size), kernel, "u string, v string, phrases long, orthogonal boolean")


def whole_decide(a: DataFrame, b: DataFrame, size: int = 9) -> DataFrame:
    """Per query pattern: phrases over all of A, orthogonal patterns, and whether there is one; each block adds its own up."""

    def kernel(own: list[str], us: list[str]) -> Iterator[list]:
        counts = _counts(own, us)
        yield [us, counts.sum(0, dtype=np.int64), (counts == len(us[0]) + 1).sum(0, dtype=np.int64)]

    per_block = _block_map(_blocks(a, b, size), kernel, "u string, phrases long, orthogonal long")
    return per_block.groupBy("u").agg(F.sum("phrases").alias("phrases"), F.sum("orthogonal").alias("orthogonal"), (F.sum("orthogonal") > 0).alias("has_orthogonal"))


def _simple_head(u: int, d: int) -> str:
    fresh = g.Fresh()
    return g.simple_dictionary(d, fresh) + fresh() + g.simple_query(_vector(u, d), fresh) + fresh()


def whole_pair_gadget(a: DataFrame, b: DataFrame, size: int = 256) -> DataFrame:
    """The single-pair construction for all pairs: d phrases cover an orthogonal vector's gadget, d + 1 another's.

    The kernel gives a vector's counts for ``RUN`` queries as one row; the queries' names are put to them in the JVM.
    """

    def kernel(own: list[str], us: list[str], part: int) -> Iterator[list]:
        d, names = len(us[0]), pa.array(own)
        tails = [g.simple_vector(_vector(int(v, 2), d)) + STOP for v in own]
        steps = _steps([_simple_head(u, d) for u in (0, (1 << d) - 1)], tails)
        jump = (steps.reshape(2, len(own), -1) - np.arange(0, steps.shape[1], 2 * d + 1)[:, None])[:, :, : 2 * d]
        chosen = np.ascontiguousarray(-_bits(us).T).astype(np.min_scalar_type(2 * d))
        coordinate = _coordinates(tails[0], d)
        for first in range(0, len(us), RUN):
            run = np.ascontiguousarray(chosen[:, first : first + RUN])
            width = max(1, ROWS_OUT // run.shape[1])
            for i in range(0, len(own), width):
                counts = _counts_to_end(jump[:, i : i + width], coordinate, run)
                lists = pa.ListArray.from_arrays(np.arange(len(counts) + 1, dtype=np.int32) * run.shape[1], counts.ravel().astype(np.int32))
                yield [np.full(len(counts), part), np.full(len(counts), first), names[i : i + width], lists]

    tiles, us = _tiles(a, b, size)
    counted = _block_map(tiles, kernel, "part long, first int, v string, counts array<int>").join(F.broadcast(us), "part")
    return counted.select("us", "first", "v", F.posexplode("counts").alias("at", "phrases")).select(F.expr("us[first + at]").alias("u"), "v", F.col("phrases").cast("long").alias("phrases"))


def whole_naive_set(a: DataFrame, b: DataFrame, size: int = 256) -> DataFrame:
    """The faulty construction, a block of A behind one query: ``(u, vectors, phrases)`` summed over the blocks."""

    def kernel(own: list[str], us: list[str]) -> Iterator[list]:
        d = len(us[0])
        tail = "".join(g.simple_vector(_vector(int(v, 2), d)) for v in own)
        steps = _steps([_simple_head(u, d) for u in (0, (1 << d) - 1)], [tail])
        counts = _walk(steps, _coordinates(tail, d), _bits(us), np.array([0]), np.array([len(tail)]))
        yield [us, np.full(len(us), len(own)), counts[0].astype(np.int64)]

    per_block = _block_map(_blocks(a, b, size), kernel, "u string, vectors long, phrases long")
    return per_block.groupBy("u").agg(F.sum("vectors").alias("vectors"), F.sum("phrases").alias("phrases"))


@lru_cache(maxsize=64)
def _parts(n: int, d: int) -> tuple[int, int, str]:
    """Symbols of the dictionary and of n vectors' blocks, and the all-ones query."""
    fresh, ones = g.Fresh(), [1] * d
    first = len(g.dictionary(n, d, fresh))
    return first, sum(map(len, g.matrix([ones] * n, fresh))), g.query_vector(ones, n, g.Fresh())


def whole_sizes(b: DataFrame, a: DataFrame, size: int = 9) -> DataFrame:
    """Per query pattern, summed over the blocks of A: vectors with fillers, symbols of the parts; and one block's substitutions.

    No length depends on a vector's bits, so blocks of one number of vectors count together.
    """
    filled = F.pow(F.floor(F.sqrt(F.count(F.lit(1)) - 1)) + 1, 2).cast("long")
    blocks = _numbered(a, size).groupBy("block").agg(filled.alias("n")).groupBy("n").agg(F.count(F.lit(1)).alias("copies"))

    def kernel(u: str, n: int, copies: int) -> list[tuple]:
        d = len(u)
        first, matrix, ones = _parts(n, d)
        mine = g.query_vector(_vector(int(u, 2), d), n, g.Fresh())
        return [(u, copies * n, copies * first, copies * len(mine), copies * matrix, sum(x != y for x, y in zip(ones, mine, strict=True)))]

    cores = a.sparkSession.sparkContext.defaultParallelism
    pairs = b.select(F.col("bits").alias("u")).repartition(4 * cores, "u").crossJoin(F.broadcast(blocks)).select("u", "n", "copies")
    per_block = flat_map(pairs, kernel, "u string, n long, dictionary_symbols long, query_symbols long, matrix_symbols long, substitutions long")
    return per_block.groupBy("u").agg(*[F.sum(c).alias(c) for c in ("n", "dictionary_symbols", "query_symbols", "matrix_symbols")], F.max("substitutions").alias("substitutions"))
