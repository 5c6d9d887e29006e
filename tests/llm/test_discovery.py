"""Discovery of personal data by the words around it, beside a plain version of the rounds."""

import math
import re
from collections import defaultdict

from vecmend.llm import pii

from . import brute


def test_unseen_values_do_not_sink_a_pattern(spark):
    rows = [(i, f"tel +49 30 555{i:04d} now") for i in range(80)] + [(100 + i, f"tel 3055{i:04d} now") for i in range(20)]
    # a word that leads emails as often as phones
    rows += [(200 + i, f"reach a{i}@b.org or reach +49 40 777{i:04d} soon") for i in range(20)] + [(300, "reach 40777123 later"), (301, "lot 40777124 later")]
    got = spans(spark, rows)
    assert all(got[100 + i] == "phone:4:12" for i in range(20)) and got[300] == got[301] == ""


def spans(spark, rows):
    docs = spark.createDataFrame(rows, "doc_id bigint, text string").repartition(2)
    return {r.doc_id: r.s for r in pii.find_personal_data(docs).select("doc_id", pii.spans_text(pii.F.col("spans")).alias("s")).collect()}


PLANTED = (
    [(i, f"contact user{i}@mail.org today") for i in range(8)] + [(10 + i, f"contact user{i} (at) mail (dot) org today") for i in range(4)] + [(15, "contact admin@intranet today")]
    + [(20 + i, f"server 10.0.0.{i} answered") for i in range(8)] + [(30, "server 2001:db8:0:1:ff:12 answered"), (31, "clock 12:34:56:07 answered")]
    # known by the word after only, and from there by a word before that no seed has
    + [(40 + i, f"w{i} +49 30 700{i:04d} extension") for i in range(8)] + [(50 + i, f"dial 3070{i:04d} extension") for i in range(6)] + [(60, "dial 30701234 please")]
    + [(70 + i, f"card {n} valid") for i, n in enumerate(("4111 1111 1111 1111", "5500 0000 0000 0004", "4012 8888 8888 1881", "4222 2222 2222 2", "5105 1051 0510 5100", "4000 0000 0000 0002"))]
    + [(80, "card 4111 1111 1111 1112 valid"), (81, "order 4111 1111 1111 1113 shipped"), (90, None), (91, "")]
)


def plain(rows):
    """All spans by the same rounds, with dictionaries."""
    kinds, digits = list(pii.KINDS), lambda v: len(re.sub("[^0-9]", "", v))

    def fits(k, v):
        number = re.fullmatch("[0-9 .-]+", v) is not None
        return {"email": bool(re.search(r"@|at[)\]]", v)), "ip": ":" in v, "card": number and 12 <= digits(v) <= 19, "phone": number and 8 <= digits(v) <= 15}[k]

    def around(text, a, b):
        bare = lambda w: re.sub(r'[#*$%&|<>,.;:()"]+', "", w).lower()
        left = re.search(r"([^ \x09-\x0D]+)[ \x09-\x0D]*$", text[max(0, a - 40) : a])
        right = re.match(r"[ \x09-\x0D]*([^ \x09-\x0D]+)", text[b : b + 40])
        left, right = (bare(m[1]) if m else "" for m in (left, right))
        return [w for w, ok in ((("<", left), left), ((">", right), right), (("<>", left, right), left and right)) if ok]

    seen, graph, base = [], {}, {}
    for doc, text in rows:
        text = text or ""
        own = [(k, int(a), int(b)) for k, a, b in (x.split(":") for x in brute.personal(text)[1].split(",") if x)]
        base[doc] = own
        free = [(None, m.start(), m.end()) for p, _ in pii.CANDIDATES for m in re.finditer(p, text) if not any(a < m.end() and m.start() < b for _, a, b in own)]
        for k, a, b in own + free:
            for w in around(text, a, b):
                graph[w, text[a:b]] = graph.get((w, text[a:b])) or k
                seen.append((doc, k, a, b, text[a:b], w))
    known = dict(graph)
    while True:
        trusted = {}
        for w in {w for w, _ in known}:
            own = [(v, k) for (x, v), k in known.items() if x == w]
            for kind in kinds:
                n = sum(k == kind for _, k in own)
                contrary = sum(k != kind and (k is not None or not fits(kind, v)) for v, k in own)
                if n >= pii.MIN_SEEDS and (n + 0.5) / (n + contrary + 1) >= pii.MIN_CONFIDENCE:
                    trusted[w, kind] = (n + 0.5) / (n + contrary + 1)
        score = defaultdict(float)
        for (w, v), k in graph.items():
            if k is None:
                for kind in kinds:
                    if (w, kind) in trusted and fits(kind, v):
                        score[v, kind] += math.log1p(-min(trusted[w, kind], 0.999))
        best = {}
        for (v, kind), s in score.items():
            if 1 - math.exp(s) >= pii.MIN_CONFIDENCE:
                best[v] = max(best.get(v, (0, -1)), (1 - math.exp(s), kinds.index(kind)))
        new = {(w, v): k or (kinds[best[v][1]] if v in best else None) for (w, v), k in known.items()}
        if new == known:
            break
        known = new
    found = {}
    for doc, k, a, b, v, w in seen:
        if k is None:
            for kind in kinds:
                if (w, kind) in trusted and fits(kind, v):
                    found[doc, a, b] = max(found.get((doc, a, b), (0, -1)), (trusted[w, kind], kinds.index(kind)))
    out = {}
    for doc, _ in rows:
        every = [(a, kinds.index(k), b) for k, a, b in base[doc]] + [(a, k, b) for (d, a, b), (_, k) in found.items() if d == doc]
        out[doc] = ",".join(f"{kinds[k]}:{a}:{b}" for a, k, b in sorted(every))
    return out


def test_planted_identifiers_of_all_kinds_match_the_plain_version(spark):
    got, want = spans(spark, PLANTED), plain(PLANTED)
    assert got == want
    assert all(got[10 + i].startswith("email:8:") for i in range(4)) and got[15] == "email:8:22" and got[30] == "ip:7:25"
    assert all(got[50 + i] == "phone:5:13" for i in range(6)) and got[60] == "phone:5:13"
    assert got[80].startswith("card:5:") and got[81] == "" and got[90] == got[91] == ""


def test_repeats_nulls_and_clashing_columns(spark):
    rows = [(None, "tel +49 30 5551234", "a", 1, "w"), (None, "tel +49 30 5551234", "a", 1, "w"), (1, None, "a", 1, "w"), (1, "x" * 100_000, "a", 1, "w")]
    frame = spark.createDataFrame(rows, "doc_id bigint, text string, base string, start int, word string")
    got = pii.find_personal_data(frame).collect()
    assert sorted(len(r.spans) for r in got) == [0, 0, 1, 1] and pii.find_personal_data(frame.limit(0)).count() == 0
    assert sorted(len(r.text or "") for r in pii.redact(frame).collect()) == [0, 11, 11, 100_000]
