"""The pipeline's stages: what goes, what stays, and the shape of the rows."""

import corpus_pipeline
from dyngraph.llm import queries


def test_stages_on_smallest_tables(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    seen = [docs.count()]
    for k, (name, stage) in enumerate(corpus_pipeline.STAGES):
        out = stage(spark, docs, sf)
        if k < len(corpus_pipeline.STAGES) - 1:
            assert out.columns == docs.columns, name
            docs = corpus_pipeline.written(out, "t")
            seen.append(docs.count())
    assert seen[0] >= seen[1] >= seen[2] == seen[3] > 0
    assert out.count() == docs.count() and "ids" in out.columns
    assert not docs.filter("text like '%AKIA____________________%'").count()


def test_queries_are_registered():
    assert [n for n in queries.QUERIES if n.startswith("op")] == [f for f in queries.QUERIES] and len(queries.QUERIES) == 10
