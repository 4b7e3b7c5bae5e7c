"""The pipeline's stages keep the columns, take effect, and compose; the registered queries are there."""

import shutil

import corpus_pipeline
import __spark_entry__ as entry

DATA = "/root/testdata/sf0.001"


def test_every_operator_is_registered():
    names = entry.queries()
    assert "pipeline" in names and all(sum(n.startswith(f"op{k}_") for n in names) == 1 for k in range(1, 11))


def test_stages(spark):
    docs = spark.read.parquet(f"{DATA}/documents.parquet")
    counts = []
    for _, stage in corpus_pipeline.STAGES[:-1]:
        out = stage(spark, docs, DATA)
        assert out.columns == docs.columns
        docs = spark.createDataFrame(out.collect(), docs.schema)
        counts.append(docs.count())
    assert counts == sorted(counts, reverse=True) and counts[0] < 200
    labels = spark.read.parquet(f"{DATA}/labels.parquet")
    kept = docs.join(labels, "doc_id")
    assert kept.where("quality = 0").count() <= 2
    pieces = corpus_pipeline.STAGES[-1][1](spark, docs, DATA)
    assert pieces.select("doc_id").distinct().count() == docs.select("doc_id").distinct().count()
    whole = corpus_pipeline.run(spark, DATA)
    columns = ["doc_id", "doc_tokens"]
    assert sorted(map(tuple, whole.select(columns).distinct().collect())) == sorted(map(tuple, pieces.select(columns).distinct().collect()))


def test_stages_take_edges(spark, edges, nothing, tmp_path):
    for t in ("labels", "benchmark"):
        shutil.copy(f"{DATA}/{t}.parquet", tmp_path)
    for start in (edges, nothing):
        docs = start
        for _, stage in corpus_pipeline.STAGES[:-1]:
            docs = stage(spark, docs, str(tmp_path))
            assert docs.columns == start.columns
            docs = spark.createDataFrame(docs.collect(), start.schema)
        assert corpus_pipeline.STAGES[-1][1](spark, docs, str(tmp_path)).count() >= docs.count()
