"""Sharding by sampled splitters, with DataFrame functions only.

Records are ordered by (hash of the text, key), which puts equal texts side by side. A sample drawn in proportion to
size gives the quantile keys that cut this order into many ranges; records are dealt to ranges, exact totals per range
are taken, and running sizes inside each range place every record on the one line of all bytes. A shard is an equal
stretch of that line, so a range that overfills its shard is subdivided exactly where the line says. A group of equal
texts goes to one shard as a whole while it is at most ``whole_share`` of a shard; larger groups are divided.

Law ``bytes``: shards differ by no more than about ``2 * whole_share`` of a shard plus one record. ``slot`` numbers a
shard's records without gaps in that order.

What reaches the driver is bounded by parameters: about ``32 * ranges`` sampled keys, one row per range and shard.

Defined cases: a null text has size 1 and checksum 0; null keys sort first; identical rows are counted before anything
is shuffled and dealt out again at the end, in blocks, so they may fill several shards; an empty table gives no rows;
columns besides key and text never enter.
"""

from __future__ import annotations

from bisect import bisect_left
from itertools import accumulate

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from phraseloom.llm.common import durable

BLOCK = 65536
LEAST = -(1 << 63)
LEAST_RANGES, MOST_RANGES, ROWS_PER_RANGE = 256, 4096, 200_000
PER_RANGE = 32


def _longs(values: list[int]) -> Column:
    return F.array(*[F.lit(v).cast("long") for v in values]) if values else F.array().cast("array<long>")


def _range_of(splitters: list[tuple[int, int, int]]) -> Column:
    """How many splitters are at most (h, d, block), by bisection in constant arrays."""
    hs, ds, bs = (_longs([s[k] for s in splitters]) for k in range(3))
    steps = [1 << k for k in reversed(range(max(1, len(splitters).bit_length())))]
    h, d, b = F.col("h"), F.col("d"), F.col("block")

    def further(at: Column, step: Column) -> Column:
        i = at + step - 1
        same = (F.get(hs, i) == h) & ((F.get(ds, i) < d) | ((F.get(ds, i) == d) & (F.get(bs, i) <= b)))
        return F.when((i < len(splitters)) & ((F.get(hs, i) < h) | same), at + step).otherwise(at)

    return F.aggregate(F.array(*map(F.lit, steps)), F.lit(0), further)


def _splitters(items: DataFrame, total: int, rows: int, ranges: int) -> tuple[list[tuple[int, int, int]], set[int]]:
    """Quantile keys of a size-weighted sample, and the text hashes that hold several of them."""
    mean, sample = total / max(rows, 1), PER_RANGE * ranges
    weight = (F.col("size") + mean) * F.col("copies")
    rate = sample / (2.0 * total) if total else 0.0
    chance = F.pmod(F.xxhash64(F.lit("splitter"), "h", "d", "block"), F.lit(1 << 30)) / float(1 << 30)
    drawn = items.where(chance < weight * rate).select("h", "d", "block", F.greatest(weight * rate, F.lit(1.0)).alias("w")).toArrow().to_pylist()
    drawn.sort(key=lambda r: (r["h"], r["d"], r["block"]))
    marks = list(accumulate(r["w"] for r in drawn))
    picked = sorted({bisect_left(marks, marks[-1] * k / ranges) for k in range(1, ranges)}) if drawn else []
    keys = [(drawn[i]["h"], drawn[i]["d"], drawn[i]["block"]) for i in picked]
    hashes = [k[0] for k in keys]
    hot = {h for h in hashes if hashes.count(h) > 1} if len(set(hashes)) < len(hashes) else set()
    return sorted({k if k[0] in hot else (k[0], LEAST, LEAST) for k in keys}), hot


def shard_documents(docs: DataFrame, shards: int = 16, whole_share: float = 0.02, key: str = "doc_id", text: str = "text") -> DataFrame:
    """``(doc_id, size, text_crc32, law, shard, slot, grown_shard)``, one row per record."""
    body = F.coalesce(F.col(text), F.lit(""))
    narrow = docs.select(F.col(key).cast("long").alias("doc_id"), (F.octet_length(body) + 1).cast("long").alias("size"), F.crc32(body).alias("text_crc32"), F.xxhash64(body).alias("h"))
    counted = narrow.groupBy("doc_id", "size", "text_crc32", "h").agg(F.count(F.lit(1)).alias("rows"))
    blocks = counted.withColumn("block", F.explode(F.sequence(F.lit(0).cast("long"), F.expr(f"(rows - 1) div {BLOCK}"))))
    items = durable(blocks.select("doc_id", "size", "text_crc32", "h", F.coalesce("doc_id", F.lit(LEAST)).alias("d"), "block", F.least(F.lit(BLOCK).cast("long"), F.col("rows") - F.col("block") * BLOCK).alias("copies")))

    total, rows = items.agg(F.coalesce(F.sum(F.col("size") * F.col("copies")), F.lit(0)), F.coalesce(F.sum("copies"), F.lit(0))).first()
    ranges = min(MOST_RANGES, max(LEAST_RANGES, -(-rows // ROWS_PER_RANGE)))
    splitters, hot = _splitters(items, total, rows, ranges)
    ranged = items.withColumn("range", _range_of(splitters))
    totals = {r["range"]: (r["bytes"], r["n"]) for r in ranged.groupBy("range").agg(F.sum(F.col("size") * F.col("copies")).alias("bytes"), F.sum("copies").alias("n")).collect()}
    bytes_before, rows_before, b, n = [], [], 0, 0
    for k in range(len(splitters) + 1):
        bytes_before.append(b)
        rows_before.append(n)
        b, n = b + totals.get(k, (0, 0))[0], n + totals.get(k, (0, 0))[1]

    line = Window.partitionBy("range").orderBy("h", "d", "block", "size", "text_crc32").rowsBetween(Window.unboundedPreceding, -1)
    group = Window.partitionBy("range", "h")
    mass = F.col("size") * F.col("copies")
    zero = F.lit(0).cast("long")
    run = ranged.select("*", F.coalesce(F.sum(mass).over(line), zero).alias("b0"), F.coalesce(F.sum("copies").over(line), zero).alias("n0"))
    run = run.select("*", F.min("b0").over(group).alias("g0"), F.sum(mass).over(group).alias("g"))
    whole = (F.col("g") <= whole_share * total / shards) & (~F.col("h").isin(*hot) if hot else F.lit(True))
    each = run.withColumn("k", F.explode(F.sequence(zero, F.col("copies") - 1)))
    middle = F.get(_longs(bytes_before), F.col("range")) + F.when(whole, F.col("g0") + F.col("g") / 2).otherwise(F.col("b0") + F.col("k") * F.col("size") + F.col("size") / 2)
    shard = F.least(F.lit(shards - 1), F.floor(middle * shards / max(total, 1)).cast("int"))
    rank = F.get(_longs(rows_before), F.col("range")) + F.col("n0") + F.col("k")
    placed = durable(each.select("doc_id", "size", "text_crc32", shard.alias("shard"), rank.alias("rank")))
    first = dict(placed.groupBy("shard").agg(F.min("rank")).collect())
    slot = F.col("rank") - F.get(_longs([first.get(k, 0) for k in range(shards)]), F.col("shard"))
    return placed.select("doc_id", "size", "text_crc32", F.lit("bytes").alias("law"), "shard", slot.alias("slot"), F.lit(None).cast("int").alias("grown_shard"))
