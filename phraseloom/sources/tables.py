"""The strings that the workloads read from the given tables."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from phraseloom.operators.per_string import spread, strings


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spread(strings(table(spark, sf_dir, "documents"), "doc_id", "text"))


def passages(spark: SparkSession, sf_dir: str) -> DataFrame:
    return strings(table(spark, sf_dir, "benchmark"), "item_id", "text")


def part_names(spark: SparkSession, sf_dir: str) -> DataFrame:
    return strings(table(spark, sf_dir, "part"), "p_partkey", "p_name")


def user_strings(spark: SparkSession, sf_dir: str) -> DataFrame:
    """First letters of each user's event types in the order of time."""
    entry = F.struct("ts", "event_id", F.substring("event_type", 1, 1).alias("sym"))
    ordered = F.array_join(F.transform(F.array_sort(F.collect_list(entry)), lambda e: e["sym"]), "")
    return table(spark, sf_dir, "events").groupBy(F.col("user_id").alias("sid")).agg(ordered.alias("body"))


def order_strings(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Return flag and line status of each order's lines; ties of the line number are broken by the flags themselves."""
    entry = F.struct("l_linenumber", F.concat("l_returnflag", "l_linestatus").alias("sym"))
    ordered = F.array_join(F.transform(F.array_sort(F.collect_list(entry)), lambda e: e["sym"]), "")
    return table(spark, sf_dir, "lineitem").groupBy(F.col("l_orderkey").alias("sid")).agg(ordered.alias("body"))


def conversations(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Turns of each conversation in order: ``(sid, parts)``."""
    turns = table(spark, sf_dir, "conversations").groupBy(F.col("conv_id").alias("sid")).agg(F.array_sort(F.collect_list(F.struct("turn", "text"))).alias("t"))
    return turns.select("sid", F.transform("t", lambda e: e["text"]).alias("parts"))


def conversation_strings(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Each conversation as one string, its turns joined by line breaks."""
    return spread(conversations(spark, sf_dir).select("sid", F.array_join("parts", "\n").alias("body")))


def consecutive_turns(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, DataFrame]:
    """Before and after: every turn that has a next one, and that next turn under the same ``sid`` (conversation * 2^32 + turn)."""
    turns = table(spark, sf_dir, "conversations").where("text IS NOT NULL")
    named = turns.select(F.col("conv_id").cast("long").alias("conv"), "turn", F.col("text").alias("body"), F.lead("turn").over(Window.partitionBy("conv_id").orderBy("turn")).alias("next"))
    sid = lambda turn: (F.shiftleft(F.col("conv"), 32) + F.col(turn)).cast("long").alias("sid")
    before = named.where("next IS NOT NULL")
    texts = named.select("conv", F.col("turn").alias("next"), "body")
    return before.select(sid("turn"), "body"), before.select("conv", "turn", "next").join(texts, ["conv", "next"]).select(sid("turn"), "body")


def near_copies(spark: SparkSession, sf_dir: str, shared: int = 40) -> tuple[DataFrame, DataFrame]:
    """Before and after: documents that begin with the same ``shared`` symbols, each with the next larger id of its group."""
    docs = strings(table(spark, sf_dir, "documents"), "doc_id", "text").where(F.char_length("body") >= shared)
    named = docs.select("sid", F.substring("body", 1, shared).alias("head"))
    pairs = named.withColumn("next", F.lead("sid").over(Window.partitionBy("head").orderBy("sid"))).where("next IS NOT NULL").select("sid", "next")
    return docs.join(pairs, "sid").select("sid", "body"), pairs.join(docs.withColumnRenamed("sid", "next"), "next").select("sid", "body")
