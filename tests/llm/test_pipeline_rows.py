"""Clean documents stay in the pipeline's filters where ids are null or repeat."""

import corpus_pipeline
from vecmend.llm import ngram_join

SCHEMA = "doc_id bigint, text string, lang string, source string, n_chars bigint"
A = "the quick brown fox jumps over the lazy dog near the river bank every single morning before the sun comes up"
B = "a long walk through quiet autumn forests gives people time to think about work and friends and family"


def frame(spark, rows):
    return spark.createDataFrame([(i, t, "en", "s", len(t or "")) for i, t in rows], SCHEMA).repartition(3)


def test_language_verdict_is_by_row(spark):
    rows = [(None, A), (None, B), (None, None), (None, "123"), (5, A), (5, "..."), (6, B)]
    kept = corpus_pipeline.identify_language(spark, frame(spark, rows), "").collect()
    assert sorted((r.doc_id or 0, r.text) for r in kept) == sorted([(0, A), (0, B), (5, A), (6, B)])


def test_near_copies_keep_null_ids_and_other_texts_of_an_id(spark):
    # id 3 has a copy of 1 and a text of its own; rows without id stand alone; one row repeats
    rows = [(1, A), (3, A), (3, B), (4, B), (None, A), (None, B), (7, "x y z unlike"), (7, "x y z unlike")]
    kept = ngram_join.keep_one_of_each(frame(spark, rows)).collect()
    assert sorted((r.doc_id or 0, r.text) for r in kept) == sorted([(1, A), (3, B), (0, A), (0, B), (7, "x y z unlike")])
