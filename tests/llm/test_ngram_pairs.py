"""Pairs that the n-gram join compares in groups that resemble each other, and rows that share an id."""

import random

import pytest

from vecmend.llm import ngram_join as J

from . import brute


def group(n, own, seed=1):
    """``n`` texts of 200 words, each with ``own`` words of its own in places of its own."""
    r = random.Random(seed)
    base = [f"w{r.randrange(10**6)}" for _ in range(200)]
    rows = []
    for i in range(n):
        words = list(base)
        for p in r.sample(range(200), own):
            words[p] = f"o{i}x{p}"
        rows.append((i + 10, " ".join(words)))
    return rows


@pytest.mark.parametrize("own", (2, 8))
def test_pairs_grow_with_the_group_not_with_its_square(spark, monkeypatch, own):
    sent = []
    check = J._check

    def counted(docs, pairs):
        pairs = J.durable(pairs)
        sent.append(pairs.count())
        return check(docs, pairs)

    monkeypatch.setattr(J, "_check", counted)
    totals = []
    for n in (40, 160):
        sent.clear()
        rows = group(n, own)
        got = {r.doc_id: (r.n_shingles, r.component_id) for r in J.jaccard_groups(spark.createDataFrame(rows, "doc_id bigint, text string").repartition(4)).collect()}
        assert got == brute.groups(rows)
        assert len({c for _, c in got.values()}) == (1 if own == 2 else n)
        totals.append(sum(sent))
    assert totals[1] <= 6 * totals[0] and totals[1] < 160 * 159 / 4


def test_chain_of_edits_is_found_whole(spark):
    # neighbours are similar, ends are not; and a far group shares a passage with all
    r = random.Random(4)
    words = [f"a{i}" for i in range(120)]
    rows = []
    for i in range(40):
        words = list(words)
        words[r.randrange(120)] = f"b{i}"
        rows.append((100 - i, " ".join(words)))
    passage = " ".join(f"a{i}" for i in range(30))
    rows += [(200 + i, passage + " " + " ".join(f"c{i}_{j}" for j in range(100))) for i in range(40)]
    got = {x.doc_id: (x.n_shingles, x.component_id) for x in J.jaccard_groups(spark.createDataFrame(rows, "doc_id bigint, text string").repartition(3)).collect()}
    assert got == brute.groups(rows)


def test_texts_under_one_id_are_documents_of_their_own(spark):
    a, b = " ".join(f"x{i}" for i in range(30)), " ".join(f"y{i}" for i in range(30))
    rows = [(5, a), (5, b), (3, b), (9, a), (9, a), (None, a), (None, b)]
    got = sorted(((r.doc_id, r.component_id) for r in J.jaccard_groups(spark.createDataFrame(rows, "doc_id bigint, text string")).collect()), key=str)
    assert got == sorted([(5, 5), (5, 3), (3, 3), (9, 5), (9, 5), (None, None), (None, None)], key=str)
