"""The pipeline's stages and the registered queries."""

import corpus_pipeline
from softlanes.llm import queries
from softlanes.llm.shared import load, materialise


def test_stages_run_in_order_and_keep_columns(spark, small):
    docs = load(spark, small, "documents")
    before = docs.count()
    assert [n for n, _ in corpus_pipeline.STAGES] == ["quality_classifier", "language_id", "exact_dedup", "simhash_near_dedup", "best_fit_packing"]
    for name, stage in corpus_pipeline.STAGES[:-1]:
        out = materialise(stage(spark, docs, small), name)
        assert out.columns == ["doc_id", "text", "lang", "source", "n_chars"]
        after = out.count()
        assert 0 < after <= before
        docs, before = out, after
    packed = corpus_pipeline.STAGES[-1][1](spark, docs, small)
    assert packed.select("doc_id").distinct().count() == before
    assert docs.groupBy("text").count().where("count > 1").count() == 0


def test_empty_documents_pass_every_stage(spark, small):
    docs = materialise(load(spark, small, "documents").where("false"), "none")
    for name, stage in corpus_pipeline.STAGES[:-1]:
        docs = materialise(stage(spark, docs, small), name)
        assert docs.count() == 0
    assert corpus_pipeline.STAGES[-1][1](spark, docs, small).count() == 0


def test_ten_operators_are_registered():
    names = sorted(queries.queries(), key=lambda n: int(n[2:].split("_")[0]))
    assert [n.split("_")[0] for n in names] == [f"op{i}" for i in range(1, 11)]
