import collections
import tracemalloc

import corpus_pipeline
import numpy as np
from test_dedup import SPACE, sets_brute
from test_others import check_packing, ids_of

from skewmap.llm import langid

SF = "/root/testdata/sf0.001"


def test_stages_against_brute_force(spark, documents, texts):
    docs = documents
    kept = {}
    for name, stage in corpus_pipeline.STAGES[:-1]:
        out = stage(spark, docs, SF)
        assert out.columns == documents.columns
        docs = corpus_pipeline.common.materialise(out, name)
        kept[name] = [r["doc_id"] for r in docs.select("doc_id").collect()]
    assert set(kept["language_id"]) == {i for i, t in texts.items() if t and any(c.isalpha() for c in t)}
    first = {}
    for i in sorted(kept["language_id"]):
        first.setdefault(SPACE.sub(" ", texts[i]), i)
    assert set(kept["exact_dedup"]) == set(first.values())
    comps = sets_brute([(i, texts[i]) for i in kept["exact_dedup"]])
    assert set(kept["ngram_jaccard_join"]) == {i for i, (_, c) in comps.items() if c == i}
    counts = collections.Counter(kept["mixing"])
    assert set(counts) <= set(kept["ngram_jaccard_join"]) and max(counts.values()) <= 2
    rows = corpus_pipeline.STAGES[-1][1](spark, docs, SF).collect()
    check_packing(rows, ids_of(texts.items()))
    assert collections.Counter(r["doc_id"] for r in rows if r["piece"] == 0) == counts


def test_run(spark):
    assert corpus_pipeline.run(spark, SF).count() > 0


def test_edge_documents_pass_all_stages(spark, odd_docs):
    docs = odd_docs
    for name, stage in corpus_pipeline.STAGES:
        docs = corpus_pipeline.common.materialise(stage(spark, docs, SF), name)
    assert docs.count() > 0
    docs = odd_docs.limit(0)
    for name, stage in corpus_pipeline.STAGES:
        docs = corpus_pipeline.common.materialise(stage(spark, docs, SF), name)
    assert docs.count() == 0


def test_language_training_takes_little_of_the_driver():
    rng = np.random.default_rng(7)
    texts = {k: [bytes(rng.integers(97, 105, 1000, dtype=np.uint8)) for _ in range(1000)] for k in ("aa", "bb", "cc")}
    tracemalloc.start()
    langid.train(texts)
    peak = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    assert peak < 16 * 3_000_000, peak
