"""The pipeline against plain versions of its stages' decisions, on the smallest tables."""

import re

import pytest

corpus_pipeline = pytest.importorskip("corpus_pipeline")

from hybridrange.llm import exact_dedup, mixing, pieces, simhash, toxicity  # noqa: E402
from tests.llm.test_operators import linked, raw  # noqa: E402


def test_stages(spark, sf_dir, tmp_path):
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    names, kept = docs.columns, {}
    for name, stage in corpus_pipeline.STAGES:
        out = stage(spark, docs, sf_dir)
        out.write.parquet(f"{tmp_path}/{name}")
        before, docs = docs, spark.read.parquet(f"{tmp_path}/{name}")
        kept[name] = (before, docs)
        if name != "SentencePiece":
            assert docs.columns == names
    before, after = kept["toxicity"]
    model = toxicity.train(before, spark.read.parquet(f"{sf_dir}/labels.parquet"))
    assert {r.doc_id for r in after.collect()} == {r.doc_id for r in before.collect() if model.score(raw(r.text)) < 0.5}
    before, after = kept["exact dedup"]
    first = {}
    for r in sorted(before.collect(), key=lambda r: r.doc_id):
        first.setdefault(re.sub(r"[\x20\x09-\x0D]+", " ", r.text or ""), r.doc_id)
    assert {r.doc_id for r in after.collect()} == set(first.values())
    before, after = kept["SimHash near-dedup"]
    sets = {r.doc_id: set(simhash.shingle_hashes(raw(r.text), 5).tolist()) for r in before.collect()}
    pairs = [(a, b) for a in sets for b in sets if a < b and (len(sets[a] & sets[b]) >= 0.8 * len(sets[a] | sets[b]))]
    assert {r.doc_id for r in after.collect()} == set(linked(sets, pairs).values())
    before, after = kept["mixing"]
    copies = {r.doc_id: r.copies for r in mixing.mix(before).collect()}
    assert after.count() == sum(copies.values()) and all(copies[r.doc_id] == r["count"] for r in after.groupBy("doc_id").count().collect())
    before, after = kept["SentencePiece"]
    p, text = pieces.loaded(pieces.MODEL), {r.doc_id: r.text for r in before.collect()}
    assert all(r.exact and list(r.ids) == p.encode(text[r.doc_id]) for r in after.collect()) and after.count() == before.count()
    assert exact_dedup.normalise(b" a\t b\n") == b" a b "


def test_run_equals_the_stages(spark, sf_dir):
    out = corpus_pipeline.run(spark, sf_dir)
    assert out.columns == ["doc_id", "n_tokens", "ids", "exact"] and out.where("not exact").count() == 0
