"""The pipeline's stages, one after the other, on the smallest tables."""

import corpus_pipeline

from rastertopo.llm import catalogue, near_dedup, toxicity
from rastertopo.llm.common import table, written

SF = "/root/testdata/sf0.001"


def test_stages(spark):
    docs, columns = table(spark, SF, "documents"), ["doc_id", "text", "lang", "source", "n_chars"]
    found = {}
    for name, stage in corpus_pipeline.STAGES:
        docs = written(stage(spark, docs, SF), "test-stage")
        found[name] = docs
        if name != "encoding":
            assert docs.columns == columns
    whole = table(spark, SF, "documents")
    model = toxicity.train(whole, table(spark, SF, "labels"))
    toxic = toxicity.score(whole, model).filter("score >= 0.5").select("doc_id")
    assert found["toxicity"].join(toxic, "doc_id", "left_semi").isEmpty()
    assert found["toxicity"].count() == whole.count() - toxic.count()
    classes = near_dedup.near_classes(found["line_dedup"])
    assert found["near_dedup"].count() == classes.select("class_id").distinct().count()
    assert found["encoding"].count() == found["mixing"].count()
    assert found["encoding"].filter("n_tokens <> size(ids)").isEmpty()
    again = written(corpus_pipeline.mixing(spark, found["near_dedup"], SF), "test-again")
    assert again.exceptAll(found["mixing"]).isEmpty()
    assert corpus_pipeline.STAGES[0][0] == "toxicity" and len(corpus_pipeline.STAGES) == 5


def test_empty_documents(spark):
    docs = table(spark, SF, "documents").limit(0)
    for _, stage in corpus_pipeline.STAGES:
        docs = stage(spark, docs, SF)
    assert docs.isEmpty()


def test_one_query_for_each_operator():
    numbers = sorted(int(n[2:].split("_")[0]) for n in catalogue.queries())
    assert numbers == list(range(1, 11)) and set(catalogue.oracle_sql()) <= set(catalogue.queries())
