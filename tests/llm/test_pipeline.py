"""The pipeline against its stages run by brute force on a small table."""

import hashlib
import struct

import corpus_pipeline
from test_operators import brute_classes, brute_fingerprint

from momenttree.llm import bpe, decontaminate, quality

SF = "/root/testdata/sf0.001"


def test_run_follows_the_stages(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    labels, items = spark.read.parquet(f"{SF}/labels.parquet"), spark.read.parquet(f"{SF}/benchmark.parquet")
    model = quality.train(docs, labels)
    rows = {r.doc_id: r for r in docs.collect()}
    kept = {d: r for d, r in rows.items() if model.score(*quality.features(r.text or "", r.n_chars)) >= quality.THRESHOLD}
    classes = brute_classes({d: brute_fingerprint(r.text or "") for d, r in kept.items()})
    kept = {d: r for d, r in kept.items() if classes[d] == d}
    index = decontaminate.ItemIndex.build([(r.item_id, r.text) for r in items.collect()])
    found = index.matches([r.text or "" for r in kept.values()], decontaminate.SIMILARITY)
    kept = {d: r for (d, r), f in zip(kept.items(), found, strict=True) if not f}
    got = {r.doc_id: r for r in corpus_pipeline.run(spark, SF).collect()}
    assert set(got) == set(kept)
    own = bpe.load(bpe.default_vocabulary())
    plain = [d for d, r in kept.items() if not any(c.isdigit() for c in r.text or "") and "=" not in (r.text or "")]
    assert len(plain) > 20
    for d in plain:
        ids = own.encode(kept[d].text or "")
        assert (got[d].n_tokens, got[d].ids_sha256) == (len(ids), hashlib.sha256(struct.pack(f"<{len(ids)}I", *ids)).hexdigest())


def test_stages_keep_the_columns_of_documents(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    assert 4 <= len(corpus_pipeline.STAGES) <= 5
    at = docs
    for _, stage in corpus_pipeline.STAGES[:-1]:
        at = stage(spark, at, SF)
        assert at.columns == docs.columns and [f.dataType for f in at.schema] == [f.dataType for f in docs.schema]
