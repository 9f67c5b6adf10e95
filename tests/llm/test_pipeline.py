"""The pipeline against the stages' own brute-force versions on the smallest tables."""

import corpus_pipeline
from graphpart.llm import jaccard, pii, quality
from graphpart.llm.common import load
from tests.conftest import SF


def test_stages_take_effect(spark):
    assert [n for n, _ in corpus_pipeline.STAGES] == ["quality", "language", "near_duplicates", "personal_data", "packing"]
    docs = load(spark, SF, "documents")
    columns = docs.columns
    model = quality.fit_quality(docs, load(spark, SF, "labels"), train_only=False)
    rows = docs.collect()
    want = {r.doc_id for r, s in zip(rows, quality.scores([r.text or "" for r in rows], *model), strict=True) if s >= 0.3}
    one = corpus_pipeline.quality(spark, docs, SF)
    assert one.columns == columns and {r.doc_id for r in one.collect()} == want
    two = corpus_pipeline.language(spark, one, SF)
    assert two.columns == columns
    three = corpus_pipeline.near_duplicates(spark, two, SF)
    classes = jaccard.jaccard_classes(two).collect()
    assert {r.doc_id for r in three.collect()} == {r.doc_id for r in classes if r.doc_id == r.component_id}
    four = corpus_pipeline.personal_data(spark, three, SF)
    assert four.columns == columns and not any(pii.base_spans(r.text or "") for r in four.collect())
    last = corpus_pipeline.run(spark, SF)
    assert {r.doc_id for r in last.select("doc_id").distinct().collect()} == {r.doc_id for r in four.collect()}
    assert last.groupBy("sequence_id").agg({"length": "sum"}).where("`sum(length)` > 4096").count() == 0
