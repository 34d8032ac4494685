"""The pipeline against a plain version of its stages."""

import zlib
from collections import Counter

import numpy as np
from test_operators import brute_components, brute_leaks, brute_lines

import corpus_pipeline
from textfactor.llm import langid, line_dedup, packing


def test_stages_against_brute_force(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    columns = docs.columns
    by_name = dict(corpus_pipeline.STAGES)

    one = by_name["language_id"](spark, docs, sf)
    model = langid.CompressionClassifier(langid.train(docs.where(langid.in_training()).select("doc_id", "text", "lang")))
    want = {r.doc_id for r in docs.collect() if (f := model.classify(r.text))[0] != "und" and f[1] >= 1 and f[2] >= model.least_score}
    assert {r.doc_id for r in one.collect()} == want and one.columns == columns and len(want) >= 0.97 * docs.count()

    before = [(r.doc_id, r.text) for r in one.collect()]
    two = by_name["line_dedup"](spark, one, sf)
    lines = {i: (n, gone, digest) for i, n, gone, digest in brute_lines(before)}
    assert {r.doc_id: line_dedup.kept_digest(r.text) for r in two.collect()} == {i: d for i, (n, gone, d) in lines.items() if gone == 0 or gone < n}
    assert two.columns == columns and all(r.n_chars == len(r.text) for r in two.collect())

    before = [(r.doc_id, r.text) for r in two.collect()]
    three = by_name["near_duplicates"](spark, two, sf)
    assert {r.doc_id for r in three.collect()} == {i for i, _, c in brute_components(before) if i == c}

    four = by_name["decontamination"](spark, three, sf)
    items = [(r.item_id, r.text) for r in spark.read.parquet(f"{sf}/benchmark.parquet").collect()]
    left = [(r.doc_id, r.text) for r in three.collect()]
    leaked = {left[k][0] for k, _ in brute_leaks(items, [t.encode() for _, t in left])}
    assert {r.doc_id for r in four.collect()} == {i for i, _ in left} - leaked and four.columns == columns

    five = by_name["packing"](spark, four, sf).collect()
    memo = packing.memo_of(packing.default_tokenizer())
    ids = {r.doc_id: np.frombuffer(memo.ids((r.text or "").encode()), "<u2").astype("<u4").tolist() + [1] for r in four.collect()}
    assert sum(p.length for p in five) == sum(map(len, ids.values()))
    assert all(zlib.crc32(np.array(ids[p.doc_id][p.start : p.start + p.length], "<u4").tobytes()) == p.ids_crc32 for p in five)
    assert max(Counter(p.sequence_id for p in five)) == (sum(p.length for p in five) - 1) // 2048


def test_run(spark, sf):
    assert corpus_pipeline.run(spark, sf).count() > 0
