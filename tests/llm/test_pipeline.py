"""The pipeline's stages: columns, decisions, and what stays."""

import sys

from mfaccel.llm import decontaminate, nbsvm, near_copies, toxicity
from mfaccel.llm.common import table

FOLDER = "/root/testdata/sf0.01"


def test_stages_decide_as_their_operators_do(spark):
    import corpus_pipeline

    assert [n for n, _ in corpus_pipeline.STAGES] == ["toxicity", "quality", "simhash", "decontamination", "bpe"]
    docs, labels, bench = (table(spark, FOLDER, n) for n in ("documents", "labels", "benchmark"))
    ids = lambda df: sorted(r.doc_id for r in df.select("doc_id").collect())
    clean = corpus_pipeline.STAGES[0][1](spark, docs, FOLDER)
    assert clean.columns == docs.columns and ids(clean) == ids(toxicity.score(docs, toxicity.fit(docs, labels)).where("NOT toxic"))
    good = corpus_pipeline.STAGES[1][1](spark, docs, FOLDER)
    assert ids(good) == ids(nbsvm.score(docs, nbsvm.fit(docs, labels)).where("predicted = 1"))
    single = corpus_pipeline.STAGES[2][1](spark, docs, FOLDER)
    assert ids(single) == ids(near_copies.keep_one(docs))
    free = corpus_pipeline.STAGES[3][1](spark, docs, FOLDER)
    assert ids(free) == ids(decontaminate.digest(decontaminate.flag(docs, bench)).where("NOT contaminated"))
    assert all(f.columns == docs.columns for f in (good, single, free))
    out = corpus_pipeline.run(spark, FOLDER)
    assert 0 < out.count() < 1000 and {"doc_id", "ids", "n_tokens"} <= set(out.columns)


def test_module_is_at_the_top():
    assert "corpus_pipeline" in sys.modules
