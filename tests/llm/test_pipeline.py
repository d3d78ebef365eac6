"""The pipeline's stages against plain versions of what they decide."""

import corpus_pipeline
from test_decontaminate import brute as contaminated
from test_jaccard import brute as classes

from treefacts.llm import quality, tokens


def test_run(spark, tiny):
    docs = {r.doc_id: r for r in spark.read.parquet(f"{tiny}/documents.parquet").collect()}
    good = {r.doc_id for r in quality.measure(spark.read.parquet(f"{tiny}/documents.parquet")).collect() if r.kept}
    found = classes({d: docs[d].text for d in good}, 5, 80)
    single = {d for d in good if found[d][1] == d}
    items = {r.item_id: r.text for r in spark.read.parquet(f"{tiny}/benchmark.parquet").collect()}
    dirty = {d for d in single if any(x in docs[d].text for x in items.values())}
    rows = corpus_pipeline.run(spark, tiny).collect()
    assert {r.doc_id for r in rows} == single - dirty
    e = tokens.encoder(tokens.tokenizer_path())
    assert all(r.n_tokens == len(e.whole(docs[r.doc_id].text)) // 2 + 1 for r in rows)
    assert sorted(r.start for r in rows)[0] == 0
    assert contaminated({}, items) == set()


def test_stages_keep_columns(spark, tiny):
    docs = spark.read.parquet(f"{tiny}/documents.parquet")
    for _, stage in corpus_pipeline.STAGES[:-1]:
        assert stage(spark, docs, tiny).columns == docs.columns
