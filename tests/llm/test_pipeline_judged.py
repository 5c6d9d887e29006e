"""Which rows the pipeline keeps, stage by stage, against plain versions."""

import corpus_pipeline
from vecmend.llm import language_id

from . import brute


def test_each_stage_keeps_what_its_plain_version_keeps(spark, tiny):
    docs = spark.read.parquet(f"{tiny}/documents.parquet")
    items = [tuple(r) for r in spark.read.parquet(f"{tiny}/benchmark.parquet").select("item_id", "text").collect()]
    rows = {r.doc_id: r.text for r in docs.collect()}
    stages = dict(corpus_pipeline.STAGES)

    accepted = {r.doc_id for r in language_id.identify(docs, language_id.fit_text_model(docs)).where("accepted").collect()}
    kept = {d: rows[d] for d in accepted}
    spoken = stages["language_id"](spark, docs, tiny).cache()
    assert {r.doc_id: r.text for r in spoken.collect()} == kept

    kept = {d: kept[d] for d, (_, c) in brute.groups(sorted(kept.items())).items() if c == d}
    single = stages["ngram_jaccard_join"](spark, spoken, tiny).cache()
    assert {r.doc_id: r.text for r in single.collect()} == kept

    judged = brute.contamination(sorted(kept.items()), items)
    kept = {d: kept[d] for d, verdict in zip(sorted(kept), judged, strict=True) if not verdict[-1]}
    clean = stages["benchmark_decontamination"](spark, single, tiny).cache()
    assert {r.doc_id: r.text for r in clean.collect()} == kept

    masked = stages["personal_data"](spark, clean, tiny).cache()
    texts = {r.doc_id: r.text for r in masked.collect()}
    assert texts.keys() == kept.keys() and all(texts[d] == kept[d] for d in kept if not brute.personal(kept[d])[1] and "[" not in (texts[d] or ""))
    assert all(brute.personal(t)[1] == "" for t in texts.values())

    whole = corpus_pipeline.run(spark, tiny)
    assert {r.doc_id: r.text for r in whole.collect()} == texts
