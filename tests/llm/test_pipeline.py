"""Stages of the corpus pipeline: columns, decisions, and rows against brute force."""

import corpus_pipeline
from helpers import DATA
from rasterchain.llm import quality, sentencepiece_codec, simhash
from test_operators import brute_fingerprint, brute_quality, brute_repeats


def test_stages_one_by_one(spark, docs, rows, tmp_path):
    columns = docs.columns
    kept = corpus_pipeline.quality_stage(spark, docs, DATA)
    assert kept.columns == columns
    assert all(brute_quality(r["text"])[0] >= 50 for r in kept.collect())
    near = corpus_pipeline.near_duplicate_stage(spark, docs, DATA)
    assert near.columns == columns
    left = near.collect()
    assert len({r["doc_id"] for r in left}) == len(left)
    fps = [brute_fingerprint(r["text"]) for r in left]
    assert all((a ^ b).bit_count() > 3 for k, a in enumerate(fps) for b in fps[:k])
    cut = corpus_pipeline.passage_stage(spark, docs, DATA)
    assert cut.columns == columns and cut.count() == len(rows)
    sizes = sorted(b[0] - b[1] for b in brute_repeats([r[1] for r in rows]))
    assert all(r["n_chars"] == len(r["text"]) for r in cut.collect()) and sum(sizes) >= sum(len(r["text"].encode()) for r in cut.collect())
    mix = corpus_pipeline.mixing_stage(spark, docs, DATA)
    assert mix.columns == columns
    tokens = corpus_pipeline.token_stage(spark, docs, DATA)
    assert tokens.columns == ["doc_id", "n_tokens", "ids_sha256", "decoded_sha256"] and tokens.count() == len(rows)


def test_whole_pipeline(spark):
    docs = spark.read.parquet(f"{DATA}/documents.parquet")
    out = corpus_pipeline.run(spark, DATA)
    ids = {r["doc_id"] for r in out.collect()}
    kept = {r["doc_id"] for r in quality.quality_rules(docs).where("kept").collect()}
    assert ids and ids <= kept
    groups = simhash.simhash_groups(docs.where(docs.doc_id.isin(list(kept)))).collect()
    assert ids <= {r["component_id"] for r in groups}


def test_empty_table(spark, empty):
    out = empty
    for _, stage in corpus_pipeline.STAGES:
        out = stage(spark, out, DATA)
    assert out.count() == 0 and sentencepiece_codec.model_bytes()
