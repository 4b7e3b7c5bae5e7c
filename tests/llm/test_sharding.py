import zlib
from collections import defaultdict

import pytest
from pyspark.sql import functions as F

from phraseloom.llm import sharding


def lawful(rows, texts_bytes):
    shards = defaultdict(list)
    for r in rows:
        shards[r["shard"]].append(r)
    for members in shards.values():
        assert sorted(r["slot"] for r in members) == list(range(len(members)))
    assert sum(r["size"] for r in rows) == texts_bytes


def test_edges(edges, edge_rows, nothing):
    rows = sharding.shard_documents(edges).collect()
    assert len(rows) == len(edge_rows)
    lawful(rows, sum(len((t[1] or "").encode()) + 1 for t in edge_rows))
    want = sorted(((t[0] is None, t[0] or 0), len((t[1] or "").encode()) + 1, zlib.crc32((t[1] or "").encode())) for t in edge_rows)
    assert sorted(((r["doc_id"] is None, r["doc_id"] or 0), r["size"], r["text_crc32"]) for r in rows) == want
    assert sharding.shard_documents(nothing).count() == 0


@pytest.mark.parametrize("hot", [False, True])
def test_sizes_are_near_equal(spark, hot):
    """Also when a third of the rows are one identical row, and another third share a text."""
    df = spark.range(6000).select(F.col("id").alias("doc_id"), F.concat(F.lit("text "), F.repeat(F.col("id").cast("string"), 9)).alias("text"))
    if hot:
        df = df.withColumns({"doc_id": F.when(F.col("doc_id") % 3 == 0, 1).otherwise(F.col("doc_id")), "text": F.when(F.col("doc_id") % 3 == 0, "hot").when(F.col("doc_id") % 3 == 1, "warm text").otherwise(F.col("text"))})
    rows = sharding.shard_documents(df).collect()
    sizes = defaultdict(int)
    for r in rows:
        sizes[r["shard"]] += r["size"]
    mean = sum(sizes.values()) / 16
    assert len(sizes) == 16 and all(abs(s - mean) < 0.05 * mean + 60 for s in sizes.values())
    lawful(rows, sum(sizes.values()))


def test_small_groups_stay_whole(spark):
    df = spark.range(8000).select(F.col("id").alias("doc_id"), F.concat(F.lit("group "), (F.col("id") % 2000).cast("string"), F.lit(" text")).alias("text"))
    placed = sharding.shard_documents(df).groupBy("text_crc32").agg(F.countDistinct("shard").alias("n"))
    assert placed.agg(F.max("n")).first()[0] == 1
