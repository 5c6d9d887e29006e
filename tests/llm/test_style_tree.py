"""The site style tree against a plain version, and pages on which it decides."""

import math
from collections import Counter, defaultdict

from vecmend.llm import html_extract as H

SCHEMA = "page_id bigint, url string, html string"


def plain_tree(pages):
    """(host, path) -> importance, from all pages at once."""
    rows = set()
    for _, url, page in pages:
        host = url.split("/")[2] if url and "://" in url else None
        if host is None:
            continue
        blocks, nodes = H.parse(page or "")
        whole = tuple(b[3] for b in blocks)
        rows |= {(host, path, whole, style, tuple(b[3] for b in blocks[a:z])) for path, style, a, z in nodes if a < z}
    styles, contents = defaultdict(Counter), defaultdict(Counter)
    for host, path, _, style, content in rows:
        styles[host, path][style] += 1
        contents[host, path][content] += 1
    out = {}
    for key, own in styles.items():
        m = sum(own.values())
        if m < H.MIN_PAGES:
            continue
        presentation = -sum(c / m * math.log(c / m) for c in own.values()) / math.log(m)
        content = 1 - sum(math.log(c) for c in contents[key].values()) / len(contents[key]) / math.log(m)
        weight = H.GAMMA ** len(own)
        out[key] = (1 - weight) * presentation + weight * content
    return out


def pages_without_articles():
    """Three hosts whose pages declare nothing: the same banner and closing text, and bodies of their own."""
    out = []
    for h in range(3):
        for i in range(4 + 5 * h):
            body = "".join(f"<p>Sentence {i} {j} of host {h} with own words {i * 31 + j}</p>" for j in range(1 + i % 3))
            out.append((100 * h + i, f"http://h{h}.org/{i}", f"<body><div class=a><p>Always the same welcome of {h}</p></div><div class=b>{body}</div><div class=c><span>Closing words of {h}</span></div></body>"))
    return out


def texts(spark, rows):
    return {r.page_id: r.text for r in H.extract(spark.createDataFrame(rows, SCHEMA).repartition(3)).collect()}


def test_tree_matches_plain_version(spark, tiny):
    real = [tuple(r) for r in spark.read.parquet(f"{tiny}/pages.parquet").select("page_id", "url", "html").collect()]
    for rows in (pages_without_articles(), [(i, u.lower().split("?")[0], h) for i, u, h in real]):
        want = plain_tree(rows)
        got = {(r.host, r.path): r.importance for r in H.style_tree(spark.createDataFrame(rows, SCHEMA)).collect()}
        assert got.keys() == want.keys() and all(abs(got[k] - want[k]) < 1e-9 for k in want)


def test_tree_decides_where_nothing_is_declared(spark):
    rows = pages_without_articles()
    got = texts(spark, rows)
    for page_id, _, _ in rows:
        h, i = divmod(page_id, 100)
        assert got[page_id] == "\n\n".join(f"Sentence {i} {j} of host {h} with own words {i * 31 + j}" for j in range(1 + i % 3))


def test_no_text_is_lost(spark):
    body = "".join(f"<p>Paragraph {i} of the real body with a good number of words in it.</p>" for i in range(6))
    rows = [
        (1, "http://a.org/", f'<div class="content no-sidebar">{body}</div>'), (2, "http://b.org/", f'<div class="has-sidebar"><article>{body}</article></div>'),
        (3, "http://c.org/", f'<article><p>Before</p><svg width="1" /><p>After <math/>too</p>{body}</article>'), (4, "http://d.org/", f"<article>A teaser</article><div class=body>{body}</div>"),
        (5, "http://e.org/", f"<article>{body}</article><div class=sidebar>Links</div>"), (6, "http://f.org/", "<p>Start</p><script>never closed"),
    ]
    got = texts(spark, rows)
    whole = "\n\n".join(f"Paragraph {i} of the real body with a good number of words in it." for i in range(6))
    assert got[1] == got[2] == got[5] == whole and got[3] == "Before\n\nAfter too\n\n" + whole and whole in got[4] and got[6] == "Start"


def test_repeats_empty_table_clashing_columns_and_long_pages(spark):
    long = "<article>" + "<p>word and word</p>" * 20000 + "</article>"
    rows = [(1, "http://a.org/1", long, "x", 1, "y")] * 2 + [(2, None, None, "x", 1, "y"), (3, "http://a.org/2", "", "x", 1, "y")]
    frame = spark.createDataFrame(rows, SCHEMA + ", host string, part int, low string")
    got = sorted((r.page_id, r.n_chars) for r in H.extract(frame).collect())
    assert got == [(1, 20000 * 13 + 19999 * 2), (1, 20000 * 13 + 19999 * 2), (2, 0), (3, 0)]
    assert H.extract(frame.limit(0)).count() == 0
