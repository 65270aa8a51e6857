"""The pipeline's stages, each judged on its own input."""

from __future__ import annotations

import corpus_pipeline
from strata_descent.llm import mixing, ngram_join, personal_data, quality_rules
from strata_descent.llm.common import saved, table

DATA = "/root/testdata/sf0.001"


def test_stages(spark):
    docs = table(spark, DATA, "documents")
    columns = docs.columns
    for name, stage in corpus_pipeline.STAGES:
        before, docs = docs, saved(stage(spark, docs, DATA))
        if name != "pieces":
            assert docs.columns == columns
        if name == "quality_rules":
            assert docs.count() > 0
            kept = {r.doc_id for r in quality_rules.judge_quality(before, table(spark, DATA, "labels")).where("kept").collect()}
            assert {r.doc_id for r in docs.collect()} == kept
        if name == "ngram_join":
            assert {r.doc_id for r in docs.collect()} == {r.component_id for r in ngram_join.join_documents(before).collect()}
        if name == "personal_data":
            assert docs.count() == before.count()
            assert all(not personal_data.base_spans(r.text) for r in docs.collect())
        if name == "mixing":
            taken = {r.doc_id: r.taken for r in mixing.taken_words(before).where("taken > 0").collect()}
            assert {r.doc_id: len(r.text.split()) for r in docs.collect()} == taken
    assert docs.where("n_pieces > 0").count() == docs.count() > 0


def test_run_on_odd_rows(spark, tmp_path):
    """Rows without an id, without a text, that repeat others, and very long ones go through all stages; so does an empty table."""
    docs, labels = table(spark, DATA, "documents"), table(spark, DATA, "labels")
    some = docs.limit(40).collect()
    odd = [r.asDict() | {"doc_id": None} for r in some[:5]] + [some[6].asDict()] * 2 + [some[7].asDict() | {"text": None, "doc_id": None}, some[8].asDict() | {"text": "", "source": None}]
    odd += [some[9].asDict() | {"doc_id": 10**9, "text": " ".join(r.text for r in docs.limit(200).collect()[40:])}]
    rows = spark.createDataFrame([tuple(r[c] for c in docs.columns) for r in [*(x.asDict() for x in some), *odd]], docs.schema)
    for name, frame in (("odd", rows), ("empty", rows.where("doc_id < -1"))):
        folder = tmp_path / name
        frame.write.parquet(f"{folder}/documents.parquet")
        labels.write.parquet(f"{folder}/labels.parquet")
        out = corpus_pipeline.run(spark, str(folder))
        assert (out.count() > 10 and out.where("doc_id = 1000000000").count() == 1) if name == "odd" else out.count() == 0
