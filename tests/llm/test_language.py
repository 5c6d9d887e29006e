"""Each kind of evidence decides where the others say nothing, and labels that were not fitted are met."""

import numpy as np

from vecmend.llm import language_id as L
from vecmend.llm import queries as Q

SCHEMA = "doc_id bigint, text string, lang string, source string, n_chars bigint"


def test_labels_held_out(spark, tiny):
    docs = spark.read.parquet(f"{tiny}/documents.parquet")
    model = L.fit_text_model(docs.where("doc_id % 2 = 0"))
    held = docs.where("doc_id % 2 = 1")
    labels = {r.doc_id: r.lang for r in held.collect()}
    found = [r for r in L.identify(held, model).collect() if r.language]
    assert sum(r.language == labels[r.doc_id] for r in found) >= 0.97 * len(found) > 0


def test_sample_is_bounded_and_ties_are_equal_rows(spark):
    rows = [(None, "ab cd ef", "en", "s", 1)] * 50 + [(i, f"gh ij {i}", "de", "s", 1) for i in range(20)]
    model = L.fit_text_model(spark.createDataFrame(rows, SCHEMA).repartition(3), fit_rows=10)
    assert 1 <= len(model) <= 2 and all(len(v) == L.BUCKETS for v in model.values())


def flat(*names):
    """A model under which no text says anything but by its first marked bucket."""
    model = {n: np.full(L.BUCKETS, -9.0) for n in names}
    for n, word in zip(names, (b"aaaa", b"bbbb"), strict=False):
        model[n][np.unique(L.trigram_buckets(word))] = -1.0
    return model


def test_suffix_declared_and_parent_domain_decide(spark):
    model = flat("xx", "yy")
    rows = [(i, "aaaa aaaa aaaa", "x-A", f"http://h{i}.one.site.xn/p") for i in range(30)]
    rows += [(100 + i, "bbbb bbbb bbbb", "y-B", f"http://h{i}.two.site.yn/p") for i in range(30)]
    rows += [(200, "cccc", None, "http://q.r.else.xn/"), (201, "cccc", None, "http://q.r.else.yn/")]  # the suffix alone
    rows += [(202, "cccc", "yyy", None), (203, "cccc", "xxx", None)]  # the declared tag alone
    rows += [(204, None, "xxx", None), (205, "123", "xxx", "http://h1.one.site.xn/")]
    rows = [(i, t, d and {"x-A": "xxx", "y-B": "yyy"}.get(d, d), u) for i, t, d, u in rows]
    frame = spark.createDataFrame(rows, "doc_id bigint, text string, tag string, url string").repartition(4)
    got = {r.doc_id: r for r in L.identify(frame, model, declared_col="tag", host_col=None, url_col="url").collect()}
    assert (got[200].language, got[201].language, got[202].language, got[203].language) == ("xx", "yy", "yy", "xx")
    assert not got[204].accepted and not got[205].accepted and got[204].language is None
    # without tags and with one suffix, a new host follows the domain above it
    rows = [(i, "aaaa aaaa", f"http://a{i}.m.one.xn/") for i in range(30)] + [(50 + i, "bbbb bbbb", f"http://a{i}.m.two.xn/") for i in range(30)]
    rows += [(200, "cccc", "http://new.m.one.xn/"), (201, "cccc", "http://new.m.two.xn/")]
    got = {r.doc_id: r.language for r in L.identify(spark.createDataFrame(rows, "doc_id bigint, text string, url string"), model, host_col=None, url_col="url").collect()}
    assert (got[200], got[201]) == ("xx", "yy")


def test_repeated_rows_and_clashing_names(spark):
    model = flat("xx", "yy")
    rows = [(1, "aaaa", "h", "z", 0, 0), (1, "aaaa", "h", "z", 0, 0), (2, "bbbb" * 20000, None, None, 1, 1)]
    frame = spark.createDataFrame(rows, "doc_id bigint, text string, source string, language string, id int, part int")
    got = sorted((r.doc_id, r.language) for r in L.identify(frame, model).collect())
    assert got == [(1, "xx"), (1, "xx"), (2, "yy")]
    assert L.identify(frame.limit(0), model).count() == 0


def test_pages(spark, tiny):
    tags = {r.page_id: r.declared for r in L.page_evidence(spark.read.parquet(f"{tiny}/pages.parquet")).collect()}
    found = Q.pages_language(spark, tiny).collect()
    assert len(found) == len(tags) and sum(r.language == tags[r.page_id] for r in found if r.language) >= 0.9 * len(found)
