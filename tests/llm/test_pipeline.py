"""The pipeline's stages against what they must keep."""

import corpus_pipeline
from bipercolate.llm import near_dups, pii, quality_rules
from bipercolate.llm.common import documents

SF = "/root/testdata/sf0.001"


def test_stages(spark):
    docs = documents(spark, SF)
    good = corpus_pipeline.quality(spark, docs, SF)
    verdicts = {r.doc_id: r.kept for r in quality_rules.measure(docs).collect()}
    assert {r.doc_id for r in good.collect()} == {i for i, kept in verdicts.items() if kept}
    single = corpus_pipeline.near_duplicates(spark, good, SF)
    assert {r.doc_id for r in single.collect()} == {r.component_id for r in near_dups.classes(good).collect()}
    clean = corpus_pipeline.personal_data(spark, single, SF)
    assert clean.count() == single.count() and pii.report(clean).agg({"n_email": "sum", "n_ip": "sum", "n_card": "sum", "n_phone": "sum"}).first()[0] == 0
    for stage in (good, single, clean, corpus_pipeline.source_mixing(spark, clean, SF)):
        assert stage.columns == docs.columns


def test_run(spark):
    packed = corpus_pipeline.run(spark, SF)
    assert packed.count() > 0 and "sequence_id" in packed.columns
