"""What the sampler's query and the pipeline's last stage hand on."""

import hashlib
import random

import numpy as np
from test_text_operators import words

import corpus_pipeline
from meshpack.llm import queries, sp_sampling


def _docs(spark):
    rng = random.Random(4)
    texts = [*(words(rng, 40) for _ in range(30)), "a", "", None, "x▁y", "né 漢字 \U0001f600"]
    return spark.createDataFrame([(i, t, "en", "s", len(t or "")) for i, t in enumerate(texts)], "doc_id long, text string, lang string, source string, n_chars long")


def test_encoding_keeps_all_samples(spark):
    """The stage draws as many segmentations as op7, one row a document."""
    docs = _docs(spark)
    flat = {}
    for r in sp_sampling.segmentations(docs).collect():
        flat.setdefault(r.doc_id, []).append((r.sample, r.log_prob, r.perturbed, r.log_inclusion, r.exact, r.ids_sha256, r.ids))
    got = {}
    for r in corpus_pipeline.encode(spark, docs, "").collect():
        assert r.doc_id not in got
        got[r.doc_id] = [(s.sample, s.log_prob, s.perturbed, s.log_inclusion, s.exact, s.ids_sha256, s.ids) for s in (r, *r.more)]
    assert got == flat and max(map(len, got.values())) == sp_sampling.K > 1
    assert len(got[31]) == 1  # the empty text has one segmentation


def test_op7_returns_the_segmentations(spark, tmp_path):
    docs = _docs(spark)
    docs.write.parquet(f"{tmp_path}/documents.parquet")
    text = {r.doc_id: (r.text or "").replace(sp_sampling.MARK, " ") for r in docs.collect()}
    v = sp_sampling.vocabulary(sp_sampling.tokenizer_path(sp_sampling.MODEL))
    for r in queries.op7_sp_sampling(spark, str(tmp_path)).collect():
        assert v.decode(r.ids) == text[r.doc_id] and r.exact and r.n_pieces == len(r.ids)
        assert hashlib.sha256(np.array(r.ids, "<i4").tobytes()).hexdigest() == r.ids_sha256
