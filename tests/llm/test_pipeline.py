"""The pipeline's stages one after the other, each against brute force on its own input."""

import re

import corpus_pipeline
from bitsort.llm.stages import written
from tests.llm.test_operators import jaccard_classes


def test_stages(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    columns, seen = docs.columns, {}
    for name, stage in corpus_pipeline.STAGES:
        out = written(stage(spark, docs, sf))
        seen[name] = (docs, out)
        docs = out
    names = [n for n, _ in corpus_pipeline.STAGES]
    for n in names[:-1]:
        assert seen[n][1].columns == columns
    rows = lambda df: [(r["doc_id"], r["text"]) for r in df.collect()]
    before, after = seen["ngram_jaccard_join"]
    assert {d for d, _ in rows(after)} == {c for _, _, c in jaccard_classes(rows(before), 5, 80)}
    before, after = seen["benchmark_decontamination"]
    bench = [r["text"] for r in spark.read.parquet(f"{sf}/benchmark.parquet").collect()]
    assert {d for d, _ in rows(after)} == {d for d, t in rows(before) if not any(b in t for b in bench)}
    before, after = seen["secret_scans"]
    assert {d for d, _ in rows(before)} == {d for d, _ in rows(after)}
    assert not [t for _, t in rows(after) if re.search("[0-9a-f]{16}", t)]
    before, after = seen["best_fit_packing"]
    assert {r["doc_id"] for r in after.collect()} == {d for d, _ in rows(before)}
    run = corpus_pipeline.run(spark, sf)
    key = ["doc_id", "piece", "start", "length", "ids_crc32"]
    assert sorted(tuple(r[k] for k in key) for r in run.collect()) == sorted(tuple(r[k] for k in key) for r in after.collect())
