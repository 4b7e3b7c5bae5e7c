"""Substring tools on tables of strings: agreements, occurrences, clusters, periods, runs, suffix arrays, covers."""

from __future__ import annotations

from math import log2

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from phraseloom.functions import kernels as k
from phraseloom.operators.per_string import flat_map


def lcp_pairs(pairs: DataFrame) -> DataFrame:
    """``(sid, i, j, lcp)`` for rows ``(sid, body, i, j)``."""
    return flat_map(pairs.select("sid", "body", "i", "j"), lambda sid, s, i, j: [(sid, i, j, k.agreement(s, i - 1, j - 1))], "sid long, i long, j long, lcp long")


def lcs_pairs(pairs: DataFrame) -> DataFrame:
    return flat_map(pairs.select("sid", "body", "i", "j"), lambda sid, s, i, j: [(sid, i, j, k.agreement_back(s, i - 1, j - 1))], "sid long, i long, j long, lcs long")


def all_occurrences(rows: DataFrame) -> DataFrame:
    """``(sid, pos)`` of every occurrence of ``pattern`` in rows ``(sid, body, pattern)``."""
    return flat_map(rows.select("sid", "body", "pattern"), lambda sid, s, p: [(sid, x + 1) for x in k.occurrences(s, p)], "sid long, pos long")


def pattern_clusters(rows: DataFrame) -> DataFrame:
    """``(sid, first, last, step)``: maximal progressions of the pattern's period among its occurrences."""

    def kernel(sid: int, s: str, p: str) -> list[tuple]:
        period = k.smallest_period(p)
        return [(sid, a + 1, b + 1, period) for a, b in k.clusters(k.occurrences(s, p), period)]

    return flat_map(rows.select("sid", "body", "pattern"), kernel, "sid long, first long, last long, step long")


def cluster_islands(positions: DataFrame, period: Column) -> DataFrame:
    """The same progressions from exploded positions, by a window (for positions already in a table)."""
    w = Window.partitionBy("sid").orderBy("pos")
    new = (F.col("pos") - F.lag("pos").over(w) != period) | F.lag("pos").over(w).isNull()
    numbered = positions.withColumn("_island", F.sum(new.cast("int")).over(w))
    return numbered.groupBy("sid", "_island").agg(F.min("pos").alias("first"), F.max("pos").alias("last")).select("sid", "first", "last", period.alias("step"))


def internal_match(rows: DataFrame) -> DataFrame:
    """Occurrences of ``body[p_lo..p_hi]`` inside ``body[t_lo..t_hi]`` (at most twice as long): at most two progressions."""

    def kernel(sid: int, s: str, p_lo: int, p_hi: int, t_lo: int, t_hi: int) -> list[tuple]:
        pattern = s[p_lo - 1 : p_hi]
        return [(sid, a + 1, b + 1, k.smallest_period(pattern)) for a, b in k.clusters(k.occurrences(s, pattern, t_lo - 1, t_hi), k.smallest_period(pattern))]

    return flat_map(rows.select("sid", "body", "p_lo", "p_hi", "t_lo", "t_hi"), kernel, "sid long, first long, last long, step long")


def first_last_occurrence(rows: DataFrame) -> DataFrame:
    """JVM-side: existence, leftmost and rightmost occurrence of ``pattern`` in ``body``."""
    first = F.instr("body", F.col("pattern"))
    mirrored = F.call_function("locate", F.reverse("pattern"), F.reverse("body"))
    last = F.when(first > 0, F.char_length("body") - mirrored - F.char_length("pattern") + 2).otherwise(0)
    return rows.select("sid", (first > 0).alias("found"), first.cast("long").alias("first_pos"), last.cast("long").alias("last_pos"))


def suffix_arrays(strings: DataFrame) -> DataFrame:
    return flat_map(strings.select("sid", "body"), lambda sid, s: [(sid, r + 1, int(p) + 1) for r, p in enumerate(k.suffix_array(s))], "sid long, rank long, pos long")


def suffix_search(rows: DataFrame) -> DataFrame:
    """Number of occurrences of ``pattern`` by bisection in the suffix array of ``body``."""

    def kernel(sid: int, s: str, p: str) -> list[tuple]:
        order = k.suffix_array(s)

        def bound(after: bool) -> int:
            low, high = 0, len(order)
            while low < high:
                middle = (low + high) // 2
                head = s[order[middle] : order[middle] + len(p)]
                low, high = (middle + 1, high) if head < p or (after and head == p) else (low, middle)
            return low

        return [(sid, bound(True) - bound(False))]

    return flat_map(rows.select("sid", "body", "pattern"), kernel, "sid long, occurrences long")


def periods(strings: DataFrame) -> DataFrame:
    """``(sid, n, period, periodic)``; a string is periodic if two periods fit."""
    return flat_map(strings.select("sid", "body"), lambda sid, s: [(sid, len(s), p := k.smallest_period(s), 0 < 2 * p <= len(s))], "sid long, n long, period long, periodic boolean")


def all_runs(strings: DataFrame) -> DataFrame:
    return flat_map(strings.select("sid", "body"), lambda sid, s: [(sid, *r) for r in k.runs(s)], "sid long, lo long, hi long, period long")


def interval_cover(ranges: DataFrame) -> DataFrame:
    """Pieces ``(sid, level, lo, hi)`` of the aligned partitions that cover rows ``(sid, a, b)``."""
    return flat_map(ranges.select("sid", "a", "b"), lambda sid, a, b: [(sid, *x) for x in k.cover(a, b)], "sid long, level long, lo long, hi long")


def partition_upkeep(edits: DataFrame, budget: int = 8) -> DataFrame:
    """Interval partitions of all scales under an edit list ``(sid, n, ops)``: rebuilt intervals, validity, backlog."""

    def kernel(sid: int, n: int, ops: list[tuple]) -> list[tuple]:
        levels = [k.Partition(n, level) for level in range(max(1, n).bit_length() + 1)]
        queue, rebuilt = k.BudgetedRebuild(budget), 0
        for op in ops:
            kind, pos = op["op"], op["pos"]
            touched = sum(x.insert(pos) if kind == "ins" else x.delete(pos) if kind == "del" else 1 for x in levels)
            rebuilt += touched
            queue.update(touched)
        return [(sid, len(ops), rebuilt, all(x.valid() for x in levels), sum(levels[0].lengths), queue.longest)]

    return flat_map(edits.select("sid", "n", "ops"), kernel, "sid long, edits long, rebuilt long, valid boolean, n_after long, longest_backlog long")


def dominant_points(points: DataFrame) -> DataFrame:
    """Non-dominated pairs ``(lcs, lcp)`` per ``sid``, by a running maximum over falling ``lcs``."""
    w = Window.partitionBy("sid").orderBy(F.desc("lcs"), F.desc("lcp")).rowsBetween(Window.unboundedPreceding, -1)
    best = points.select("sid", "lcs", "lcp").distinct().withColumn("_best", F.max("lcp").over(w))
    return best.where(F.col("_best").isNull() | (F.col("lcp") > F.col("_best"))).select("sid", "lcs", "lcp")


def extension_points(strings: DataFrame) -> DataFrame:
    """``(sid, i, lcs, lcp)`` of each place i with every earlier place, both agreements taken at the places themselves."""

    def kernel(sid: int, s: str) -> list[tuple]:
        return [(sid, i + 1, k.agreement_back(s, j, i), k.agreement(s, j, i)) for i in range(len(s)) for j in range(i)]

    return flat_map(strings.select("sid", "body"), kernel, "sid long, i long, lcs long, lcp long")


def skyline_sum(rows: DataFrame) -> DataFrame:
    """Over the occurrences of ``pattern``: their number, pairs, non-dominated pairs of agreements in total, and occurrences times log^2 n."""

    def kernel(sid: int, s: str, p: str) -> list[tuple]:
        places = k.occurrences(s, p)
        points, total = k.skyline_sizes(s, places)
        return [(sid, len(places), points, total, round(len(places) * log2(len(s)) ** 2, 6))]

    return flat_map(rows.select("sid", "body", "pattern"), kernel, "sid long, occurrences long, points long, nd_total long, bound double")
