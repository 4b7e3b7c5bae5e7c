"""One string too large for a task: suffix array and greedy parse from position tables, by range and hash shuffles.

The string is a table ``(pos, sym)``, pos from 1. Ranks come from prefix doubling; each round is checkpointed. Nothing
proportional to the string reaches the driver: only one count per range partition, and one row per position block.
"""

from __future__ import annotations

import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from phraseloom.plans.folders import shared_folder


def _durable(df: DataFrame) -> DataFrame:
    shared_folder(df.sparkSession)
    return df.checkpoint(eager=True)


def dense_ranks(keys: DataFrame, columns: list[str], parts: int) -> DataFrame:
    """Distinct ``columns`` with their dense rank from 1 in global order: range partitions, counted and offset."""
    dealt = _durable(keys.select(*columns).distinct().repartitionByRange(parts, *columns).withColumn("_part", F.spark_partition_id()))
    counts = {r["_part"]: r["n"] for r in dealt.groupBy("_part").agg(F.count(F.lit(1)).alias("n")).collect()}
    before, total = {}, 0
    for p in sorted(counts):
        before[p], total = total, total + counts[p]
    offset = F.coalesce(F.get(F.array(*[F.lit(before.get(p, 0)).cast("long") for p in range(max(counts, default=0) + 1)]), F.col("_part")), F.lit(0))
    local = F.row_number().over(Window.partitionBy("_part").orderBy(*columns))
    return dealt.select(*columns, (offset + local).alias("rank"))


def suffix_ranks(symbols: DataFrame, parts: int = 16, max_rounds: int = 40) -> DataFrame:
    """``(pos, rank)`` of every suffix: doubling until all ranks differ."""
    first = dense_ranks(symbols, ["sym"], parts)
    state = _durable(symbols.join(first, "sym").select("pos", "rank"))
    n, k = state.count(), 1
    for _ in range(max_rounds):
        if k >= n or state.agg(F.max("rank")).first()[0] == n:
            break
        ahead = state.select((F.col("pos") - k).alias("pos"), F.col("rank").alias("next"))
        pairs = state.join(ahead, "pos", "left").select("pos", "rank", F.coalesce("next", F.lit(0)).alias("next")).withColumnRenamed("rank", "head")
        state = _durable(pairs.join(dense_ranks(pairs, ["head", "next"], parts), ["head", "next"]).select("pos", "rank"))
        k *= 2
    return state


def root_path(reaches: DataFrame, block: int = 1 << 20) -> DataFrame:
    """Phrases ``(ord, lo, hi)`` from ``(pos, reach)`` by block contraction.

    Edges lead forward only, so one backward scan of a block of a fixed size gives each place its exit and its hops. The
    chain of block entries (one row per block) is followed on the driver; a last pass emits each block's phrases.
    """
    base = _durable(reaches.select("pos", "reach", F.expr(f"(pos - 1) div {block}").alias("block")))
    n = base.agg(F.coalesce(F.max("pos"), F.lit(0))).first()[0]

    def contract(rows: pd.DataFrame) -> pd.DataFrame:
        rows = rows.sort_values("pos")
        low, out = int(rows["pos"].iloc[0]), rows["reach"].tolist()
        hops = [1] * len(out)
        for i in range(len(out) - 1, -1, -1):
            inner = out[i] - low
            if inner < len(out):
                out[i], hops[i] = out[inner], hops[inner] + 1
        return pd.DataFrame({"pos": rows["pos"], "exit": out, "hops": hops})

    exits = _durable(base.groupBy("block").applyInPandas(contract, "pos long, exit long, hops long"))
    entries, at, before = [], 1, 0
    while at <= n:
        row = exits.where(F.col("pos") == at).first()
        entries.append((at, (at - 1) // block, before))
        at, before = row["exit"], before + row["hops"]
    chain = base.sparkSession.createDataFrame(entries, "entry long, block long, before long")  # one row per block

    def emit(rows: pd.DataFrame) -> pd.DataFrame:
        rows = rows.sort_values("pos")
        low, reach, at, out = int(rows["pos"].iloc[0]), rows["reach"].tolist(), int(rows["entry"].iloc[0]), []
        ordinal = int(rows["before"].iloc[0])
        while at - low < len(reach):
            ordinal += 1
            out.append((ordinal, at, reach[at - low] - 1))
            at = reach[at - low]
        return pd.DataFrame(out, columns=["ord", "lo", "hi"])

    return base.join(F.broadcast(chain), "block").groupBy("block").applyInPandas(emit, "ord long, lo long, hi long")
