"""Tables of the shared folder go once nothing reads them."""

import os

import corpus_pipeline
from evenpart.plans import scratch


def test_release_deletes_what_cut_wrote(spark):
    a, b = scratch.cut(spark.range(5)), scratch.cut(spark.range(3))
    path = a._scratch
    scratch.release(a, spark.range(2))
    assert not os.path.exists(path) and b.count() == 3 and path not in [p for _, p in scratch._made]


def test_pipeline_keeps_its_last_table_only(spark, monkeypatch, tmp_path):
    spark.createDataFrame([(1, "a")], "doc_id long, text string").write.parquet(f"{tmp_path}/documents.parquet")
    made = []
    monkeypatch.setattr(corpus_pipeline, "cut", lambda df: made.append(scratch.cut(df)) or made[-1])
    monkeypatch.setattr(corpus_pipeline, "STAGES", [(str(i), lambda spark, docs, sf: docs) for i in range(3)])
    assert corpus_pipeline.run(spark, str(tmp_path)).count() == 1
    assert [os.path.exists(df._scratch) for df in made] == [False, False, True]
