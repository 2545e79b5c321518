"""The pipeline over planted documents, stage by stage against plain versions."""

import random

from test_text_operators import plain_components, plain_contamination, plain_fingerprint, plain_spans, words

import corpus_pipeline
from meshpack.llm import sp_sampling, toxicity


def test_pipeline(spark, tmp_path):
    rng = random.Random(20)
    clean = [words(rng, 60) for _ in range(300)]
    item = words(rng, 30)
    toxic = [f"{words(rng, 50)} vileist {words(rng, 5)} vileful" for _ in range(120)]
    texts = [*clean, *toxic, *clean[:20], *(f"{words(rng, 5)} {item} {words(rng, 5)}" for _ in range(5)), *(f"{c} password=hunter22x" for c in (words(rng, 40) for _ in range(5))), None, ""]
    rows = [(i, t, "en", "s0", len(t or "")) for i, t in enumerate(texts)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long")
    labels = spark.createDataFrame([(i, 1, int(300 <= i < 420)) for i in range(420)], "doc_id long, quality int, toxic int")
    docs.write.parquet(str(tmp_path / "documents.parquet"))
    labels.write.parquet(str(tmp_path / "labels.parquet"))
    spark.createDataFrame([(1, item)], "item_id long, text string").write.parquet(str(tmp_path / "benchmark.parquet"))

    at, sf = docs, str(tmp_path)
    seen = {}
    for name, stage in corpus_pipeline.STAGES:
        out = stage(spark, at, sf)
        out.write.parquet(str(tmp_path / f"stage-{name}"))
        at = spark.read.parquet(str(tmp_path / f"stage-{name}"))
        seen[name] = {r.doc_id: r for r in at.collect()}
        if name != "encoding":
            assert at.columns == docs.columns
    model = toxicity.trained(docs, labels)
    kernel = toxicity.scorer(model)
    score = dict(enumerate(kernel(texts)["score"]))
    left = {i for i in range(len(texts)) if score[i] < 0.7}
    assert set(seen["toxicity"]) == left and left >= set(range(300)) and not left & set(range(300, 420))
    left = set(plain_components({i: plain_fingerprint(texts[i]) for i in left}).values())
    assert set(seen["near_duplicates"]) == left and not left & set(range(420, 440))
    judged = {i: plain_contamination(texts[i], [(1, item)]) for i in left}
    left = {i for i, (n, h, _, _) in judged.items() if not (h > 0 and 20 * h >= n)}
    assert set(seen["decontamination"]) == left and not left & set(range(440, 445))
    assert set(seen["secrets"]) == left
    for i in left:
        text = seen["secrets"][i].text
        assert (text == texts[i]) == (not plain_spans(texts[i])) and (text is None or "hunter22x" not in text)
    v = sp_sampling.vocabulary(sp_sampling.tokenizer_path(sp_sampling.MODEL))
    assert {i: v.decode(r.ids) for i, r in seen["encoding"].items()} == {i: seen["secrets"][i].text or "" for i in left}
    assert {(r.doc_id, r.ids_sha256) for r in corpus_pipeline.run(spark, sf).collect()} == {(i, r.ids_sha256) for i, r in seen["encoding"].items()}
