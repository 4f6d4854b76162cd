"""The pipeline against a brute-force version of its stages, and on odd rows."""

import numpy as np
import public_tokenizers
from tokenizers import Tokenizer

import corpus_pipeline
from sparseloom.llm import quality, secret_scan
from sparseloom.llm.common import table

from .test_model_operators import brute_groups, slow_fingerprint
from .test_text_operators import brute_windows, checked_packing


def test_pipeline_equals_brute_force(spark, sf):
    docs = {r["doc_id"]: r["text"] for r in table(spark, sf, "documents").collect()}
    items = [tuple(r) for r in table(spark, sf, "benchmark").select("item_id", "text").collect()]
    model = quality.train(table(spark, sf, "documents"), table(spark, sf, "labels"))
    kept = {d: t for d, t in docs.items() if model.score(np.array([quality.features(t or "")]))[0] >= 0.3}
    ids = sorted(kept)
    groups = brute_groups([slow_fingerprint(kept[d]) for d in ids], ids)
    kept = {d: kept[d] for d, g in zip(ids, groups) if d == g}
    kept = {d: t for d, t in kept.items() if not brute_windows(t, items)[1]}
    kept = {d: secret_scan.redact(t, secret_scan.scan(t)[1]) for d, t in kept.items()}
    tokenizer = Tokenizer.from_file(public_tokenizers.path("word_bpe_49k.json"))
    want = {d: len(tokenizer.encode(t, add_special_tokens=False).ids) + 1 for d, t in kept.items()}
    rows = corpus_pipeline.run(spark, sf).collect()
    got: dict = {}
    for r in rows:
        got[r["doc_id"]] = got.get(r["doc_id"], 0) + r["length"]
    assert got == want and 0 < len(got) < len(docs)
    checked_packing(rows)


def test_stages_keep_columns_and_take_odd_rows(spark, sf, odd_docs, no_docs):
    for docs in (odd_docs, no_docs):
        for _, stage in corpus_pipeline.STAGES[:-1]:
            out = stage(spark, docs, sf)
            assert out.columns == docs.columns
            out.collect()
        corpus_pipeline.STAGES[-1][1](spark, docs, sf).collect()
