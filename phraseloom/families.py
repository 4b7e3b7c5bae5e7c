"""Registered queries on string families: one symbol, a period, a period with one defect, Thue-Morse, Fibonacci, separated words.

Each part gives a family by its key and the two symbols that its name begins with; equal strings are built and parsed once.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from phraseloom.operators import changes, phrases as ph, stringology as st
from phraseloom.operators.per_string import spread
from phraseloom.plans import oracles as o
from phraseloom.sources import tables as src
from phraseloom.workloads import query

#: Number of each family.
FAMILIES = {1: "unary", 2: "period", 3: "defect", 4: "thue_morse", 5: "fibonacci", 6: "words"}
#: Golden ratio, in which place i of the Fibonacci word is a step of two or of one; exact for lengths below 10^6.
GOLDEN = 1.618033988749895


def families(spark: SparkSession, n: int) -> DataFrame:
    """``(sid, body)`` of every family at length n, all in the JVM."""
    places = F.sequence(F.lit(0), F.lit(n - 1))
    spell = lambda symbol: F.array_join(F.transform(places, symbol), "")
    pair = lambda i: F.when(i % 2 == 0, "a").otherwise("b")
    bodies = {
        1: F.repeat(F.lit("a"), n),
        2: spell(pair),
        3: spell(lambda i: F.when(i == n // 2, "c").otherwise(pair(i))),
        4: spell(lambda i: F.when(F.bit_count(i) % 2 == 0, "a").otherwise("b")),
        5: spell(lambda i: F.when(F.floor((i + 2) * GOLDEN) - F.floor((i + 1) * GOLDEN) == 2, "a").otherwise("b")),
        6: spell(lambda i: F.when(i % 5 == 4, "|").otherwise(F.when((i.cast("double") * i + i / 5) % 3 < 1, "a").otherwise("b"))),
    }
    chosen = F.coalesce(*[F.when(F.col("sid") == sid, body) for sid, body in bodies.items()])
    return spark.range(1, len(FAMILIES) + 1).select(F.col("id").alias("sid")).select("sid", chosen.alias("body"))


def _sql(n: int) -> str:
    pair = "CASE WHEN i % 2 = 0 THEN 'a' ELSE 'b' END"
    symbols = {
        1: "'a'", 2: pair, 3: f"CASE WHEN i = {n // 2} THEN 'c' ELSE {pair} END", 4: "CASE WHEN bit_count(i) % 2 = 0 THEN 'a' ELSE 'b' END",
        5: f"CASE WHEN floor((i + 2) * CAST({GOLDEN} AS DOUBLE)) - floor((i + 1) * CAST({GOLDEN} AS DOUBLE)) = 2 THEN 'a' ELSE 'b' END",
        6: "CASE WHEN i % 5 = 4 THEN '|' WHEN (CAST(i AS DOUBLE) * i + CAST(i AS DOUBLE) / 5) % 3 < 1 THEN 'a' ELSE 'b' END",
    }
    return " UNION ALL ".join(f"SELECT CAST({sid} AS BIGINT) AS sid, (SELECT string_agg({symbol}, '' ORDER BY i) FROM range({n}) t(i)) AS body" for sid, symbol in symbols.items())


def _seeds(spark: SparkSession, d: str) -> DataFrame:
    """``(sid, family, symbols)`` of every part whose name has two symbols."""
    named = src.part_names(spark, d).where(F.char_length("body") >= 2)
    return named.select("sid", (1 + F.pmod(F.col("sid"), F.lit(len(FAMILIES)))).alias("family"), F.substring("body", 1, 2).alias("symbols"))


def _of_parts(spark: SparkSession, d: str, n: int, operator) -> DataFrame:
    """``operator`` on the distinct strings ``(sid, body)`` of all parts at length n, its rows given to every part."""
    seeds = _seeds(spark, d)
    once = seeds.groupBy("family", "symbols").agg(F.min("sid").alias("first"))
    bodies = families(spark, n).withColumnRenamed("sid", "family")
    spelled = once.join(bodies, "family").select(F.col("first").alias("sid"), F.expr("translate(replace(body, 'c', '#'), 'ab', symbols)").alias("body"))
    found = operator(spread(spelled)).withColumnRenamed("sid", "first")
    return seeds.join(once, ["family", "symbols"]).select("sid", "first").join(found, "first").drop("first")


_SEEDS = f"(SELECT p_partkey AS sid, 1 + p_partkey % {len(FAMILIES)} AS family, left(p_name, 2) AS symbols FROM part WHERE length(p_name) >= 2)"
_SPELLED = f"SELECT min(q.sid) AS sid, translate(replace(f.body, 'c', '#'), 'ab', q.symbols) AS body FROM {_SEEDS} q JOIN ({_sql(96)}) f ON f.sid = q.family GROUP BY f.sid, f.body, q.symbols"


@query("family_phrases", o.phrases(_SPELLED, f"SELECT q.sid, ord, lo, hi FROM {_SEEDS} q JOIN (SELECT family, symbols, min(sid) AS first FROM {_SEEDS} GROUP BY family, symbols) k USING (family, symbols) JOIN w ON w.sid = k.first"))
def family_phrases(spark: SparkSession, d: str) -> DataFrame:
    return _of_parts(spark, d, 96, lambda s: ph.parse(s).select("sid", "ord", "lo", "hi"))


@query("family_parse_stats")
def family_parse_stats(spark: SparkSession, d: str) -> DataFrame:
    """Phrases at growing lengths: constant for periods, logarithmic for the two morphic words."""
    out = None
    for n in (1_000, 10_000, 100_000):
        stats = _of_parts(spark, d, n, lambda s: ph.parse_stats(s).select("sid", "n", "phrases"))
        out = stats if out is None else out.unionByName(stats)
    return out


@query("family_runs")
def family_runs(spark: SparkSession, d: str) -> DataFrame:
    return _of_parts(spark, d, 96, st.all_runs)


@query("family_edit_costs")
def family_edit_costs(spark: SparkSession, d: str) -> DataFrame:
    """Cost log of substitutions in every family at growing lengths, each equal to a rebuild."""
    out = None
    for n in (100, 400, 1_600):
        costs = changes.edit_costs(changes.edit_script(families(spark, n), 4, ("sub",), "abc"))
        out = costs if out is None else out.unionByName(costs)
    return out
