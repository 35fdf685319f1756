"""The pipeline against its stages by brute force."""

import corpus_pipeline
from semgraph.llm import quality_model, secret_scan, simhash


def test_pipeline(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    model = quality_model.train(docs, spark.read.parquet(f"{sf}/labels.parquet"), condition=quality_model.fold() != 2)
    rows = {r.doc_id: r for r in docs.collect()}
    good = {i for i, s in zip(rows, quality_model.score_texts(model, [r.text or "" for r in rows.values()])) if s >= 0.7}
    fps = {i: simhash.fingerprint(rows[i].text or "") for i in good}
    left, kept = set(good), set()
    while left:
        group, todo = set(), [min(left)]
        kept.add(min(left))
        while todo:
            x = todo.pop()
            if x in left:
                left.discard(x)
                group.add(x)
                todo += [y for y in left if (fps[x] ^ fps[y]).bit_count() <= 4]
    one = corpus_pipeline.quality_stage(spark, docs, sf)
    two = corpus_pipeline.near_dedup_stage(spark, one, sf)
    three = corpus_pipeline.secret_stage(spark, two, sf)
    assert one.columns == two.columns == three.columns == docs.columns
    masked = {r.doc_id: r.text for r in three.collect()}
    assert set(masked) == kept
    forest = secret_scan.train()
    for i, t in masked.items():
        assert not [s for _, _, scores in secret_scan._judged(forest, [t], [rows[i].source]) for s in scores if s >= 0.5]
        assert ("[SECRET]" in t) or t == rows[i].text
    packed = corpus_pipeline.run(spark, sf)
    assert {r.doc_id for r in packed.select("doc_id").collect()} == kept
