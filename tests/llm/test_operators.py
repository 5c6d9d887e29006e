"""Operators against plain versions: the small tables, and rows with every awkward case."""

import hashlib

import numpy as np
import pytest

pytest.importorskip("vecmend.llm")

from vecmend.llm import byte_bpe, decontaminate, html_extract, language_id, ngram_join, pii, quality_rules, suffix_dedup, token_counts  # noqa: E402
from vecmend.llm import queries as Q  # noqa: E402
from vecmend.llm.components import connected_components  # noqa: E402

from . import brute  # noqa: E402

LONG = "The same passage, of more than fifty bytes, stands in several documents of this table. "
ODD = [
    (1, None), (2, ""), (3, " \n\t "), (4, "one two"), (5, "one two"), (6, LONG + "alpha beta gamma"), (7, "Start. " + LONG), (8, LONG + "alpha beta gamma"),
    (9, "x" * 30000), (10, "aaaa " * 9000), (11, "mail a.b+c@d-e.example.org, 1.2.3.4, 999.1.1.1, +1 (499) 555-6503, 4111 1111 1111 1111 and a@b.co_x@d.ef"),
    (12, "äöü ßé 你好     l'été I've we'll  don't\r\n\r\n"), (13, "# * $ % & | < >\nline\nline\n\nline"), (14, "1 2 3 4 5 6 7 8 9 0 1 2 3 4 5 6 7 8 9 0 1 2"),
]
SCHEMA = "doc_id bigint, text string, lang string, source string, n_chars bigint, id string, n bigint"


@pytest.fixture(scope="module")
def odd(spark):
    return spark.createDataFrame([(i, t, "en" if i % 2 else None, "s" if i % 3 else None, len(t or ""), "x", 0) for i, t in ODD], SCHEMA).repartition(4).cache()


@pytest.fixture(scope="module")
def docs(spark, tiny):
    return [tuple(r) for r in spark.read.parquet(f"{tiny}/documents.parquet").select("doc_id", "text").collect()]


@pytest.fixture(scope="module")
def none(odd):
    return odd.limit(0)


def test_byte_bpe(spark, tiny, docs, odd, none):
    import public_tokenizers as P

    want = dict(zip([d for d, _ in docs], brute.bpe([t for _, t in docs]), strict=True))
    assert {r.doc_id: tuple(r)[1:4] for r in Q.op1_byte_bpe(spark, tiny).collect()} == want
    ranks = byte_bpe.read_ranks(P.path("byte_bpe_50k.tiktoken"))
    for leaf in (3, 64, 8192):
        got = {r.doc_id: (r.n_tokens, r.ids_sha256, r.decoded_sha256) for r in byte_bpe.round_trip_digest(odd, ranks, P.PATTERN, leaf=leaf).collect()}
        assert got == dict(zip([d for d, _ in ODD], brute.bpe([t for _, t in ODD]), strict=True))
    ids = byte_bpe.encode_documents(odd, ranks, P.PATTERN)
    assert {r.doc_id: bytes(r.bytes).decode() for r in byte_bpe.decode_ids(ids, ranks, P.PATTERN).collect()} == {d: t or "" for d, t in ODD}
    assert byte_bpe.round_trip_digest(none, ranks, P.PATTERN).count() == 0


def test_quality_rules(odd, none):
    got = {r.doc_id: (r.n_words, r.word_chars, r.n_symbols, r.n_dup_lines, r.n_repeat_words, r.base_failed) for r in quality_rules.judge(odd).collect()}
    assert got == {d: brute.rules(t) for d, t in ODD}
    assert quality_rules.judge(none).count() == 0


def test_host_verdict_takes_good_documents_of_a_bad_host(spark):
    good = " ".join(f"w{i}" for i in range(60))
    rows = [(i, "short", "en", "bad", 5, "", 0) for i in range(40)] + [(100, good, "en", "bad", 9, "", 0)] + [(200 + i, good + str(i), "en", "fine", 9, "", 0) for i in range(40)]
    kept = {r.doc_id for r in quality_rules.judge(spark.createDataFrame(rows, SCHEMA)).where("kept").collect()}
    assert kept == {200 + i for i in range(40)}


def test_token_counts(odd):
    pieces = ["▁", "▁a", "a", "aa", "aab", "b", "▁one", "▁t", "w", "o", "line", "▁li", "ne", "x"]
    got = {r.doc_id: r.n_tokens for r in token_counts.count_tokens(odd, pieces).collect()}
    assert got == {d: brute.pieces(t, set(pieces)) for d, t in ODD}


def test_token_counts_of_the_registered_query(spark, tiny, docs, none):
    import public_tokenizers as P

    pieces = token_counts.read_pieces(P.path("piece_bpe_32k.model"))
    few = dict(docs[:60])
    got = {r.doc_id: r.n_tokens for r in Q.op3_token_counts(spark, tiny).collect()}
    assert len(got) == len(docs) and {d: got[d] for d in few} == {d: brute.pieces(t, set(pieces)) for d, t in few.items()}
    assert token_counts.count_tokens(none, pieces).count() == 0


def test_a_bad_host_changes_verdicts_of_a_registered_query(spark, tiny):
    rows = Q.rules_by_length(spark, tiny).collect()
    assert any(not r.kept and not r.base_failed for r in rows) and any(r.kept for r in rows)


def test_proximity_query(spark, tiny, docs):
    items = [tuple(r) for r in spark.read.parquet(f"{tiny}/benchmark.parquet").select("item_id", "text").collect()]
    assert {(r.doc_id, r.item_id) for r in Q.benchmark_proximity(spark, tiny).collect()} == brute.together(docs, items, 100)


def test_personal_data(odd, none):
    found = pii.find_personal_data(odd).select("doc_id", pii.spans_text(pii.F.col("base")).alias("b")).collect()
    assert {r.doc_id: r.b for r in found} == {d: brute.personal(t)[1] for d, t in ODD}
    assert pii.find_personal_data(none).count() == 0
    text = {r.doc_id: r.text for r in pii.redact(odd).collect()}
    assert text[11].startswith("mail [EMAIL], [IP], 999.1.1.1, [PHONE], [CARD] and [EMAIL]") and text[1] is None and text[4] == "one two"


def test_discovery_follows_trusted_patterns(spark):
    rows = [(i, f"member 4{i:02d}1 call phoneline +1 499 555-65{i:02d} now") for i in range(20)] + [(50, "call phoneline 4995556677 now"), (51, "the number 4995556678 here")]
    docs = spark.createDataFrame(rows, "doc_id bigint, text string")
    got = {r.doc_id: r.s for r in pii.find_personal_data(docs).select("doc_id", pii.spans_text(pii.F.col("spans")).alias("s")).collect()}
    assert got[50] == "phone:15:25" and got[51] == ""


def test_ngram_join(spark, tiny, docs, odd, none):
    got = {r.doc_id: (r.n_shingles, r.component_id) for r in Q.op6_ngram_join(spark, tiny).collect()}
    assert got == brute.groups(docs)
    assert {r.doc_id: (r.n_shingles, r.component_id) for r in ngram_join.jaccard_groups(odd).collect()} == brute.groups(ODD)
    kept = {r.doc_id for r in ngram_join.keep_one_of_each(odd.union(odd)).collect()}
    assert kept == {d for d, (_, c) in brute.groups(ODD).items() if c == d}
    assert ngram_join.keep_one_of_each(odd.union(odd)).count() == len(kept)
    assert ngram_join.jaccard_groups(none).count() == 0


def test_similar_sets_share_a_signature():
    rng = np.random.default_rng(3)
    none = np.zeros(0, dtype=np.uint64)
    for size in (1, 2, 4, 7, 8, 15, 31, 60, 127, 300, 1000):
        for _ in range(20):
            a = np.unique(rng.integers(0, 1 << 63, size, dtype=np.uint64))
            cut = rng.permutation(a)[: max(1, int(np.ceil(0.875 * size)))]
            b = np.unique(np.concatenate([cut, rng.integers(0, 1 << 63, size // 9, dtype=np.uint64)]))
            both = len(np.intersect1d(a, b))
            if 100 * both >= 75 * (len(a) + len(b) - both):
                for common in (none, a[::3], b):
                    shared = np.intersect1d(*(s[0] for s in (ngram_join.signatures(a, common), ngram_join.signatures(b, common))), return_indices=True)
                    bands = ngram_join.signatures(a, common)[1][shared[1]]
                    assert any((bands == x).sum() >= ngram_join.shared_at_least(int(x)) for x in np.unique(bands))


def test_components(spark):
    edges = spark.createDataFrame([(i, i + 1) for i in range(1, 40)] + [(100, 101), (103, 101), (7, 7)], "u bigint, v bigint")
    got = {r.node: r.component for r in connected_components(edges).collect()}
    assert got == {i: 1 for i in range(1, 41)} | {100: 100, 101: 100, 103: 100}


def test_decontamination(spark, tiny, docs, odd, none):
    items = [tuple(r) for r in spark.read.parquet(f"{tiny}/benchmark.parquet").select("item_id", "text").collect()]
    got = {r.doc_id: tuple(r)[1:] for r in Q.op7_decontamination(spark, tiny).collect()}
    assert got == dict(zip([d for d, _ in docs], brute.contamination(docs, items), strict=True))
    bench = [(1, "one two"), (2, None), (3, LONG + LONG), (4, "alpha beta"), (5, "1 2 3 4 5 6 7 8 9 0 1 2 3 4")]
    frame = spark.createDataFrame(bench, "item_id bigint, text string")
    want = brute.contamination(ODD, bench)
    for most in (10**6, 3):
        found = decontaminate.find_contamination(odd, frame, max_terms=most).collect()
        assert {r.doc_id: (r.n_words, r.n_hit, r.n_items, r.items_sha256, r.contaminated) for r in found} == dict(zip([d for d, _ in ODD], want, strict=True))
    clean = {r.doc_id for r in decontaminate.clean_documents(odd, frame).collect()}
    assert clean == {d for (d, _), w in zip(ODD, want, strict=True) if not w[-1]}
    assert decontaminate.find_contamination(odd, frame.limit(0)).where("n_hit > 0").count() == 0
    for span in (1, 2, 3, 20):
        assert {(r.doc_id, r.item_id) for r in decontaminate.proximity_matches(odd, frame, span, max_terms=20).collect()} == brute.together(ODD, bench, span)
    named = frame.select(decontaminate.F.concat(decontaminate.F.lit("item"), "item_id").alias("item_id"), "text")
    assert {r.item_id for r in decontaminate.proximity_matches(odd, named, 3).collect()} == {f"item{i}" for _, i in brute.together(ODD, bench, 3)}


def test_suffix_dedup(spark, tiny, docs, odd, none):
    got = {r.doc_id: tuple(r)[1:] for r in Q.op8_suffix_dedup(spark, tiny).collect()}
    assert got == brute.repeats(docs)
    assert {r.doc_id: tuple(r)[1:] for r in suffix_dedup.remove_repeats(odd).collect()} == brute.repeats(ODD)
    assert suffix_dedup.remove_repeats(none).count() == 0
    kept = {r.doc_id: bytes(r.kept) for r in suffix_dedup.remove_repeats(odd, with_text=True).collect()}
    assert kept[8] == b"" and hashlib.sha256(kept[6]).hexdigest() == brute.repeats(ODD)[6][3]


def test_language_id(spark, tiny, odd, none):
    labels = {r.doc_id: r.lang for r in spark.read.parquet(f"{tiny}/documents.parquet").collect()}
    found = Q.op10_language_id(spark, tiny).collect()
    assert sum(r.language == labels[r.doc_id] for r in found) >= 0.98 * len(found)
    model = language_id.fit_text_model(spark.read.parquet(f"{tiny}/documents.parquet").where("doc_id % 2 = 0"))
    held = spark.read.parquet(f"{tiny}/documents.parquet").where("doc_id % 2 = 1")
    alone = language_id.identify(held, model, declared_col=None, host_col=None).collect()
    assert sum(r.language == labels[r.doc_id] for r in alone) >= 0.95 * len(alone)
    got = {r.doc_id: r.accepted for r in language_id.identify(odd, model).collect()}
    assert len(got) == len(ODD) and not got[1] and not got[2]
    assert language_id.identify(none, model).count() == 0 and language_id.identify(odd, {}).where("accepted").count() == 0


PAGE = """<!DOCTYPE html><html><head><title>T</title><script>var x="</p>";</script></head><body><nav><ul><li>Home<li>Menu</ul></nav><!-- ad -->
<div class="ad">Buy</div>{0}<footer>&copy; host</footer></body></html>"""


def test_html_extract(spark):
    pages = [
        (1, "http://a.b/1", PAGE.format("<article><h1>Head &amp; line</h1><p>One <b>bold<br>text<p>Two\n  lines<div class='comments'><p>a reader</p></div></article>")),
        (2, "http://a.b/2", PAGE.format("<div id=main-body><p>Plain &lt;text&gt;</p></div>")), (3, None, None), (4, "bad", ""), (5, "http://a.b/5", "just text &eacute;"),
    ] + [(10 + i, f"http://c.d/{i}", f"<body><div class=x>Same line on every page</div><div class=y><p>Own words {i} {i * 7}</p></div></body>") for i in range(20)]
    frame = spark.createDataFrame(pages, "page_id bigint, url string, html string")
    got = {r.page_id: (r.text, r.n_chars) for r in html_extract.extract(frame).collect()}
    assert got[1][0] == "Head & line\n\nOne bold text\n\nTwo lines" and got[2][0] == "Plain <text>" and got[3] == ("", 0) and got[4] == ("", 0) and got[5] == ("just text é", 11)
    assert all(got[10 + i][0] == f"Own words {i} {i * 7}" for i in range(20))


def test_pipeline(spark, tiny):
    pipeline = pytest.importorskip("corpus_pipeline")
    before = spark.read.parquet(f"{tiny}/documents.parquet")
    for _, stage in pipeline.STAGES[:-1]:
        assert stage(spark, before, tiny).columns == before.columns
    out = pipeline.run(spark, tiny)
    rows = out.collect()
    assert set(before.columns) < set(out.columns) and 0 < len(rows) <= before.count()
    want = brute.bpe([r.text for r in rows])
    assert [(r.n_tokens, r.ids_sha256, r.decoded_sha256) for r in rows] == want
