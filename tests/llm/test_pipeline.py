"""The corpus pipeline, stage by stage against plain Python."""

import corpus_pipeline
from tests.llm.test_documents import brute_classes, fold


def test_stages_and_result(spark, small):
    docs = spark.read.parquet(f"{small}/documents.parquet")
    (_, language), (_, exact), (_, near), (_, mixing), (_, packing) = corpus_pipeline.STAGES
    known = language(spark, docs, small)
    assert known.columns == docs.columns and known.count() >= 0.95 * docs.count()
    unique = exact(spark, known, small)
    want = {}
    for r in known.collect():
        want[fold(r.text)] = max(r.doc_id, want.get(fold(r.text), -1))
    assert sorted(r.doc_id for r in unique.collect()) == sorted(want.values())
    single = near(spark, unique, small)
    assert {r.doc_id for r in single.collect()} == {i for i, (_, c) in brute_classes(unique.collect()).items() if i == c}
    mixed = mixing(spark, single, small)
    assert mixed.columns == docs.columns and {r.doc_id for r in mixed.collect()} <= {r.doc_id for r in single.collect()}
    whole = corpus_pipeline.run(spark, small)
    assert sorted(r.ids_crc32 for r in whole.collect()) == sorted(r.ids_crc32 for r in packing(spark, mixed, small).collect())


def test_awkward_and_empty_tables(spark, odd, none, tmp_path):
    """Null ids, texts, labels and sources, repeated rows, empty and long texts, clashing column names; and no rows at all."""
    from pyspark.sql import functions as F

    clashing = odd.withColumn("_row", F.lit(1)).withColumn("_text", F.lit("t")).withColumn("_key", F.lit(2)).withColumn("count", F.lit("c")).withColumn("sequence_id", F.lit(3))
    for name, docs in (("odd", clashing), ("none", none)):
        folder = str(tmp_path / name)
        docs.write.parquet(f"{folder}/documents.parquet")
        got = corpus_pipeline.run(spark, folder).collect()
        now = docs
        for stage_name, stage in corpus_pipeline.STAGES[:-1]:
            before, now = now, stage(spark, now, folder)
            assert now.columns == docs.columns, stage_name
            kept = {tuple(r) for r in now.collect()}
            assert kept <= {tuple(r) for r in before.collect()}, stage_name
        ids = {r.doc_id for r in now.collect()}
        assert {r.doc_id for r in got} == ids
        assert ids == ({None, 2, 7, 8, 10} if name == "odd" else set())
