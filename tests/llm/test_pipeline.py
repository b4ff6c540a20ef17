"""The pipeline against plain versions of its decisions."""

import brute
from tokenizers import Tokenizer

import corpus_pipeline as P
from corpusmill.llm import mixture_fit, quality_model, queries, secret_scan

SF = "/root/testdata/sf0.001"


def test_stages_one_by_one(spark, tmp_path):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    before = {r.doc_id: r for r in docs.collect()}
    kept = P.drop_low_quality(spark, docs, SF)
    assert kept.columns == docs.columns
    scores = {r.doc_id: r.predicted for r in quality_model.quality_scores(docs, queries._seen_labels(spark.read.parquet(f"{SF}/labels.parquet"))).collect()}
    rows = {r.doc_id: r for r in kept.collect()}
    assert set(rows) == {k for k, p in scores.items() if p} and all(before[k] == r for k, r in rows.items())

    kept.write.parquet(str(tmp_path / "a"))
    docs = spark.read.parquet(str(tmp_path / "a"))
    groups = brute.near_duplicates([(k, r.text) for k, r in rows.items()], size=5)
    unique = P.drop_near_copies(spark, docs, SF)
    assert {r.doc_id for r in unique.collect()} == {k for k, (_, c) in groups.items() if k == c}

    masked = P.mask_secrets(spark, unique, SF)
    assert masked.columns == docs.columns
    for r in masked.collect():
        assert r.text == secret_scan.redact_text(before[r.doc_id].text) and r.n_chars == len(r.text)
        assert brute.base_secrets(r.text)[:3] == (0, 0, 0)

    mixed = P.mix_sources(spark, masked, SF)
    copies = {r.doc_id: r.copies for r in mixture_fit.mix(masked).collect()}
    got = [r.doc_id for r in mixed.collect()]
    assert {k: got.count(k) for k in copies} == copies

    library = Tokenizer.from_file(queries.tokenizer_path())
    texts = {r.doc_id: r.text for r in masked.collect()}
    for r in P.tokenize(spark, mixed, SF).collect():
        assert r.n_tokens == len(library.encode(texts[r.doc_id], add_special_tokens=False).ids)


def test_run(spark):
    assert P.run(spark, SF).count() > 0
