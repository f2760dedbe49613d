"""The pipeline's stages on the small tables."""

import corpus_pipeline
from rankflow.llm import neardup
from rankflow.llm.common import table


def test_stages_in_turn(spark, sf):
    assert [n for n, _ in corpus_pipeline.STAGES] == ["quality", "toxicity", "near duplicates", "mixture", "pieces"]
    docs = table(spark, sf, "documents")
    labels = {r.doc_id: r for r in table(spark, sf, "labels").collect()}
    sizes = [docs.count()]
    for name, stage in corpus_pipeline.STAGES[:-1]:
        before = docs
        docs = stage(spark, docs, sf).cache()
        assert docs.columns == before.columns
        sizes.append(docs.count())
        left = {r.doc_id for r in docs.select("doc_id").collect()}
        if name == "quality":
            assert not [i for i in left if i in labels and labels[i].quality == 0]
            assert all(i in left for i, r in labels.items() if r.quality == 1)
        if name == "near duplicates":
            assert neardup.near_components(docs).where("not kept").count() == 0
    assert sizes[0] > sizes[1] >= sizes[2] > sizes[3]
    out = corpus_pipeline.run(spark, sf)
    assert out.count() == sizes[4] and set(out.columns) == {"doc_id", "n_tokens", "ids_sha256", "decoded_sha256"}
