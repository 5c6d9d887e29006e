"""Main text of web pages by a site style tree, with declared roles as prior.

Pages of one host are merged into a tree: nodes are element paths with their
class names.  For each node, the entropy of its presentation styles (child tag sequences)
and of its contents over the host's distinct pages gives its importance; both
are weighted by how many styles the node shows.  Branches of low
importance are cut from each page.  Roles are the prior: elements that declare themselves to be navigation,
advert, comment, form and so on go, and a declared main part (``article``, ``main``) stays even where
importance is low, since copies of one article on a host would look like furniture.  Everything else
is for the tree to decide.  On a host with a single page there is no tree; there a
declared main part that holds most of the page's text stands alone.
"""

from __future__ import annotations

import html as html_lib
import re
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import durable, in_slices

#: Weight of a single style, least importance that is kept, and distinct pages below which entropy is not defined.
GAMMA, LEAST, MIN_PAGES = 0.9, 0.25, 2

# HTML element classes and naming habits.
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
RAW = frozenset("script style noscript template textarea title iframe svg math object canvas audio video noframes xmp".split())
BLOCK = frozenset(
    "address article aside blockquote body caption center dd details dialog dir div dl dt fieldset figcaption figure footer form "
    "h1 h2 h3 h4 h5 h6 head header hgroup hr html legend li main menu nav ol p pre section summary table tbody td tfoot th thead tr ul".split()
)
NOISE_TAGS = frozenset("nav footer aside form button select option label dialog menu head fieldset".split())
NOISE_ROLES = frozenset("navigation banner contentinfo complementary search form dialog alertdialog alert menu menubar toolbar tablist status note".split())
NOISE_NAMES = frozenset(
    "ad ads adv advert adverts advertisement advertising adsense sponsor sponsored promo promoted promotion banner sidebar sidenav aside menu menus nav navbar navigation "
    "breadcrumb breadcrumbs footer cookie cookies consent gdpr notice notices notification popup modal overlay newsletter subscribe subscription signup login "
    "share sharing social comment comments commentlist disqus replies respond related recommended recommendations toolbar pagination pager copyright masthead topbar alert widget tags".split()
)
HEADER_NAMES = frozenset("header head top".split())
#: Before a noise name they say that the element lies beside such a part, or has none.
NOT_ITSELF = frozenset("no not non has have with without hide hides show shows".split())
CLOSES = {
    "li": ("li",), "dt": ("dt", "dd"), "dd": ("dt", "dd"), "tr": ("tr", "td", "th"), "td": ("td", "th"), "th": ("td", "th"), "option": ("option",),
    "tbody": ("thead", "tbody", "tr", "td", "th"), "tfoot": ("tbody", "tr", "td", "th"),
}
SCOPE = {"li": ("ul", "ol", "menu"), "dt": ("dl",), "dd": ("dl",), "tr": ("table",), "td": ("table", "tr"), "th": ("table", "tr"), "tbody": ("table",), "tfoot": ("table",), "option": ("select",)}
ENDS_PARAGRAPH = BLOCK - {"td", "th", "tr", "tbody", "thead", "tfoot", "caption", "legend", "body", "html", "head", "summary", "figcaption"}

TOKEN = re.compile(r"<!--.*?(?:-->|\Z)|<(/?)([a-zA-Z][^\s/>]*+)((?:[^>\"']++|\"[^\"]*\"|'[^']*')*+)>|<(/?)([a-zA-Z][^\s/>]*+)([^>]*)>|<[!?][^>]*>", re.S)
ATTRIBUTE = re.compile(r"([^\s=\"'/>]+)(?:\s*=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s\"'>]+)))?")
NAME = re.compile(r"[A-Z]?[a-z]+|[A-Z]+")


class Element:
    """An open element; ``noise``, ``main`` and ``paragraph`` hold for it and all that it lies in."""

    __slots__ = ("tag", "path", "noise", "main", "paragraph", "children", "start", "end")

    def __init__(self, tag: str, path: str, noise: bool, main: bool, paragraph: int, start: int):
        self.tag, self.path, self.noise, self.main, self.paragraph, self.start = tag, path, noise, main, paragraph, start
        self.children: list[str] = []
        self.end = None


def _attributes(raw: str) -> dict[str, str]:
    return {m[1].lower(): html_lib.unescape(m[2] or m[3] or m[4] or "") for m in ATTRIBUTE.finditer(raw)}


def _names(value: str) -> set[str]:
    """Words of class names and ids, without those that a word like ``no`` or ``has`` refers to."""
    out = set()
    for token in value.split():
        words = [n.lower() for n in NAME.findall(token)]
        out.update(w for i, w in enumerate(words) if not (i and words[i - 1] in NOT_ITSELF))
    return out


def _declared(tag: str, attributes: dict[str, str], inside_main: bool) -> tuple[bool, bool]:
    """Whether an element declares itself to be furniture, and to be the main part."""
    role = attributes.get("role", "").lower()
    names = _names(attributes.get("class", "")) | _names(attributes.get("id", ""))
    main = tag in ("article", "main") or role in ("main", "article") or attributes.get("itemprop", "").lower() == "articlebody"
    noise = tag in NOISE_TAGS or role in NOISE_ROLES or bool(names & NOISE_NAMES) or "hidden" in attributes or attributes.get("aria-hidden", "").lower() == "true"
    noise = noise or bool(re.search(r"display\s*:\s*none|visibility\s*:\s*hidden", attributes.get("style", "").lower()))
    if tag in ("body", "html"):
        noise = False
    if not inside_main and not main and (tag == "header" or names & HEADER_NAMES and tag != "h1"):
        noise = True
    return noise, main and not noise


#: Bytes of path lists that are broadcast, and parts into which a host's pages are dealt where they are not.
BROADCAST_BYTES, HOST_PARTS = 64 << 20, 32
#: Start tags whose roles are remembered at once.
KNOWN_TAGS = 20_000


def _start_tag(tag: str, raw: str, inside_main: bool, known: dict) -> tuple[bool, bool, str]:
    """Declared noise, declared main part, and label of a start tag; pages repeat few of them."""
    key = (tag, raw, inside_main)
    found = known.get(key)
    if found is None:
        attributes = _attributes(raw) if raw else {}
        label = tag + "".join(f".{n.lower()}" for n in sorted(set(NAME.findall(attributes.get("class", "")))))
        found = (*_declared(tag, attributes, inside_main), label)
        if len(known) >= KNOWN_TAGS:
            known.clear()
        known[key] = found
    return found


def parse(page: str, known: dict | None = None) -> tuple[list[tuple[str, bool, bool, str]], list[tuple[str, str, int, int]]]:
    """Blocks (path, noise, main, text) in page order, and nodes (path, style, first block, end of blocks).

    ``known`` remembers start tags from one page to the next.
    """
    known = {} if known is None else known
    blocks: list[tuple[str, bool, bool, str]] = []
    nodes: list[Element] = []
    stack = [Element("", "", False, False, 0, 0)]
    pending: list[str] = []
    search = TOKEN.search

    def flush() -> None:
        text = "".join(pending)
        pending.clear()
        text = " ".join((html_lib.unescape(text) if "&" in text else text).split())
        if text:
            inner = stack[-1]
            blocks.append((inner.path, inner.noise, inner.main, text))

    def close_to(depth: int) -> None:
        for e in stack[depth:]:
            e.end = len(blocks)
        del stack[depth:]

    def innermost(tag: str) -> int:
        return next((i for i in range(len(stack) - 1, 0, -1) if stack[i].tag == tag), 0)

    at = 0
    while at < len(page):
        m = search(page, at)
        if not m:
            pending.append(page[at:])
            break
        if m.start() > at:
            pending.append(page[at : m.start()])
        at = m.end()
        closing, tag, raw, closing_odd, tag_odd, raw_odd = m.groups()
        tag = (tag or tag_odd or "").lower()
        if not tag:
            continue
        block = tag in BLOCK
        if block and pending:
            flush()
        if closing or closing_odd:
            depth = len(stack) - 1 if stack[-1].tag == tag else innermost(tag)
            if depth and (block or not any(e.tag in BLOCK for e in stack[depth:])):
                close_to(depth)
            continue
        if block:
            depth = stack[-1].paragraph
            if depth and tag in ENDS_PARAGRAPH and not any(e.tag in ("td", "th", "table", "button") for e in stack[depth:]):
                close_to(depth)
            if tag in CLOSES:
                scope = SCOPE[tag]
                for i in range(len(stack) - 1, 0, -1):
                    if stack[i].tag in scope:
                        break
                    if stack[i].tag in CLOSES[tag]:
                        close_to(i)
                        break
        if tag in ("br", "hr", "wbr", "img"):
            pending.append(" " if tag != "wbr" else "")
        if tag in RAW and not (tag in ("svg", "math") and (raw or raw_odd or "").endswith("/")):
            end = re.compile(rf"</{re.escape(tag)}\s*>", re.I).search(page, at)
            at = end.end() if end else len(page)
            continue
        raw = raw or raw_odd or ""
        outer = stack[-1]
        if tag in VOID or raw.endswith("/"):
            outer.children.append(tag)
            continue
        noise, main, label = _start_tag(tag, raw, outer.main, known)
        outer.children.append(label)
        element = Element(tag, f"{outer.path}/{label}" if block else outer.path, outer.noise or noise, outer.main or main, len(stack) if tag == "p" else outer.paragraph, len(blocks))
        stack.append(element)
        if block:
            nodes.append(element)
    if pending:
        flush()
    close_to(1)
    return blocks, [(e.path, ",".join(e.children), e.start, e.end) for e in nodes]


def main_text(blocks: list[tuple[str, bool, bool, str]], low: set[str] | None) -> str:
    """Blocks without furniture and without branches of low importance (``low``; None on hosts without a tree).

    If low importance would take everything, it takes nothing.
    """
    rest = [(path, main, text) for path, noise, main, text in blocks if not noise]
    if low is None:
        declared = [text for _, main, text in rest if main]
        whole = sum(len(text) for _, _, text in rest)
        kept = declared if 2 * sum(map(len, declared)) >= whole else []
    else:
        kept = [text for path, main, text in rest if main or not any(path == x or path.startswith(f"{x}/") for x in low)]
    return "\n\n".join(kept or [text for _, _, text in rest])


def _host(url: F.Column) -> F.Column:
    return F.nullif(F.lower(F.regexp_extract(F.coalesce(url, F.lit("")), r"^[A-Za-z][A-Za-z0-9+.-]*://(?:[^/?#@]*@)?([^/?#:]+)", 1)), F.lit(""))


def style_tree(pages: DataFrame) -> DataFrame:
    """(host, path, n_pages, n_styles, importance) over each host's distinct pages.

    With m distinct pages of a node, a style or content seen on c of them
    has probability c/m; entropies are taken to the base m.  Presentation:
    the entropy of the style distribution.  Content: one less the mean over distinct contents
    of their own spread, log(c)/log(m).  The more styles a node has, the
    more its presentation weighs.  Pages with the same blocks count once.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from hashlib import blake2b

        digest = lambda x: blake2b(x, digest_size=8).digest()
        number = lambda x: int.from_bytes(x, "little", signed=True)
        known: dict = {}
        styles: dict[str, int] = {}
        for batch in batches:
            rows: set[tuple] = set()
            for host, page in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                blocks, nodes = parse(page or "", known)
                # a node's content is the run of its blocks, whose digests lie side by side
                texts = b"".join(digest(b[3].encode("utf-8", "surrogatepass")) for b in blocks)
                whole = number(digest(texts))
                for path, style, first, end in nodes:
                    if first < end:
                        if style not in styles:
                            if len(styles) >= KNOWN_TAGS:
                                styles.clear()
                            styles[style] = number(digest(style.encode("utf-8", "surrogatepass")))
                        rows.add((host, whole, path, styles[style], number(digest(texts[8 * first : 8 * end]))))
            table = list(zip(*rows, strict=True)) or [[]] * 5
            types = [pa.string(), pa.int64(), pa.string(), pa.int64(), pa.int64()]
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(table, types, strict=True)], names=["host", "page", "path", "style", "content"])

    source = pages.select(_host(F.col("url")).alias("host"), "html").where(F.col("host").isNotNull())
    seen = source.mapInArrow(in_slices(run), "host string, page bigint, path string, style bigint, content bigint")
    # one row for each distinct page, node and variant; then two levels of counts, no group is gathered
    variants = seen.distinct().groupBy("host", "path", "style", "content").agg(F.count(F.lit(1)).alias("c"))
    variants = durable(variants)
    styles = variants.groupBy("host", "path", "style").agg(F.sum("c").alias("c"))
    style_sums = styles.groupBy("host", "path").agg(F.sum("c").alias("n_pages"), F.count(F.lit(1)).alias("n_styles"), F.sum(F.col("c") * F.log("c")).alias("s"))
    contents = variants.groupBy("host", "path", "content").agg(F.sum("c").alias("c"))
    content_sums = contents.groupBy("host", "path").agg(F.avg(F.log("c")).alias("spread"))
    tree = style_sums.where(F.col("n_pages") >= MIN_PAGES).join(content_sums, ["host", "path"])
    m = F.log(F.col("n_pages").cast("double"))
    presentation = 1 - F.col("s") / (F.col("n_pages") * m)
    content = 1 - F.col("spread") / m
    weight = F.pow(F.lit(GAMMA), F.col("n_styles"))
    return tree.select("host", "path", "n_pages", "n_styles", ((1 - weight) * presentation + weight * content).alias("importance"))


def extract(pages: DataFrame, least: float = LEAST) -> DataFrame:
    """Per page row: page_id, url, text, n_chars.

    Null or empty html gives the empty text.  A page without a host in its url
    is judged by its own declarations.  An unclosed script or style takes the rest of its page, as in a browser.
    Repeated rows give repeated results, an empty table an empty one, and other columns are ignored.
    """
    tree = style_tree(pages)
    # paths of one host's template, few beside its pages; a table of checked size goes to the pages, and beyond that
    # size a host's pages are dealt to several tasks, so that no task gets all pages of a hot host
    low = durable(tree.groupBy("host").agg(F.sort_array(F.collect_set(F.when(F.col("importance") < least, F.col("path")))).alias("low")))
    held = low.agg(F.sum(F.length("host") + F.aggregate("low", F.lit(0), lambda n, x: n + F.length(x) + 8))).first()[0] or 0
    source = pages.select("page_id", "url", "html", _host(F.col("url")).alias("host"))
    if held <= BROADCAST_BYTES:
        joined = source.join(F.broadcast(low), "host", "left")
    else:
        dealt_pages = source.withColumn("part", F.pmod(F.xxhash64("page_id", "url"), F.lit(HOST_PARTS)))
        joined = dealt_pages.join(low.withColumn("part", F.explode(F.sequence(F.lit(0).cast("bigint"), F.lit(HOST_PARTS - 1).cast("bigint")))), ["host", "part"], "left")
    joined = joined.select("page_id", "url", "html", "low")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        known: dict = {}
        for batch in batches:
            for i in range(0, batch.num_rows, 256):
                part = batch.slice(i, 256)
                texts = [main_text(parse(page or "", known)[0], None if low is None else set(low)) for page, low in zip(part.column(2).to_pylist(), part.column(3).to_pylist(), strict=True)]
                yield pa.RecordBatch.from_arrays([part.column(0), part.column(1), pa.array(texts, pa.string()), pa.array([len(t) for t in texts], pa.int64())], names=["page_id", "url", "text", "n_chars"])

    kinds = dict(pages.dtypes)
    return joined.mapInArrow(in_slices(run), f"page_id {kinds['page_id']}, url {kinds['url']}, text string, n_chars bigint")
