"""Personal data by bootstrapped contextual extraction, in DataFrame expressions only.

Seeds are the spans of four strict patterns.  The words around seeds become
lexical patterns: the word before, the word after, and both.  Identifier-like strings that no strict pattern accepts are
candidates: strings of digits (phones and cards), addresses without a full domain or with a spelled-out sign (emails), and
groups of hexadecimal digits (ips of the longer kind).  Patterns and distinct instances form a bipartite graph;
in each round a pattern is scored by its known instances against those that contradict
it, an instance by the patterns it stands in, and instances over the threshold are
known from then on, until no more are found.  Candidates under a pattern of high
confidence are the discovered spans.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import bound, durable

KINDS = ("email", "ip", "card", "phone")
#: Fixed patterns of the contract.  Possessive loops and look-behinds only keep the regular
#: expression engine from trying again what must fail; they accept the same spans.
PATTERNS = {
    "email": r"(?:(?<![A-Za-z0-9._%+-])|\G)[A-Za-z0-9._%+-]++@[A-Za-z0-9-]++(?:\.[A-Za-z0-9-]++)++",
    "ip": r"(?<![0-9])[0-9]++(?:\.[0-9]++){3}",
    "card": r"(?<![0-9])(?<![0-9][ -])[0-9](?:[ -]?[0-9]){11,}+",
    "phone": r"\+[0-9][ ().0-9-]+[0-9]",
}
IP_PART = r"0*(?:25[0-5]|2[0-4][0-9]|1?[0-9]?[0-9])"
#: Candidates for discovery, with a text that they cannot do without (null: none): strings of 8 to 19 digits, addresses with
#: any sign and domain, and four groups or more of up to four hexadecimal digits.
CANDIDATES = (
    (r"(?<![A-Za-z0-9+.])[0-9](?:[ .-]?[0-9]){7,18}+(?![A-Za-z0-9])", None),
    (r"(?<![A-Za-z0-9._%+-])[A-Za-z0-9._%+-]++ ?(?:@|[(\[]at[)\]]) ?[A-Za-z0-9-]++(?: ?(?:\.|[(\[]dot[)\]]) ?[A-Za-z0-9-]++)*+", "@|[(\\[]at[)\\]]"),
    (r"(?<![A-Za-z0-9:])[0-9A-Fa-f]{1,4}+(?:::?[0-9A-Fa-f]{1,4}){3,7}+(?![A-Za-z0-9:])", ":[0-9A-Fa-f]+:[0-9A-Fa-f]*:"),
)

MIN_SEEDS = 5
MIN_CONFIDENCE = 0.9


def _digits(x: Column) -> Column:
    return F.regexp_replace(x, "[^0-9]", "")


def _luhn(digits: Column) -> Column:
    n = F.length(digits)

    def add(total: Column, i: Column) -> Column:
        d = F.substring(digits, n - i, F.lit(1)).cast("int")
        return total + F.when(i % 2 == 0, d).when(d > 4, 2 * d - 9).otherwise(2 * d)

    return F.aggregate(F.sequence(F.lit(0), n - 1), F.lit(0), add) % 10 == 0


def _valid(kind: str, found: Column) -> Column:
    n = F.length(_digits(found))
    if kind == "ip":
        return found.rlike(rf"^{IP_PART}(?:\.{IP_PART}){{3}}$")
    if kind == "card":
        return F.when(n.between(12, 19), bound("d", _luhn, _digits(found))).otherwise(F.lit(False))
    if kind == "phone":
        return n.between(9, 15)
    return F.lit(True)


def _none() -> Column:
    return F.array().cast("array<struct<start:int,kind:int,end:int>>")


def _spans(text: Column, number: int, pattern: str, valid) -> Column:
    """Accepted matches as (start, kind number, end) in code points.

    Spark returns matches without places; the places follow from the
    lengths of the pieces between matches.
    """

    def placed(both: Column) -> Column:
        def step(acc: Column, j: Column) -> Column:
            found = F.get(both["found"], j)
            start = acc["at"] + F.length(F.get(both["gaps"], j))
            end = start + F.length(found)
            span = F.struct(start.alias("start"), F.lit(number).alias("kind"), end.alias("end"))
            out = F.when(valid(found), F.concat(acc["out"], F.array(span))).otherwise(acc["out"])
            return F.struct(end.alias("at"), out.alias("out"))

        begin = F.struct(F.lit(0).alias("at"), _none().alias("out"))
        return F.aggregate(F.sequence(F.lit(0), F.size(both["found"]) - 1), begin, step)["out"]

    def located(found: Column) -> Column:
        both = F.struct(found.alias("found"), F.split(text, pattern, -1).alias("gaps"))
        return F.when(F.size(found) == 0, _none()).otherwise(bound("p", placed, both))

    return bound("s", located, F.regexp_extract_all(text, F.lit(pattern), F.lit(0)))


def seed_spans(text: Column) -> Column:
    """All accepted spans of the strict patterns, ordered by start and then kind."""
    needs = {"email": "@", "phone": "+"}
    parts = []
    for number, kind in enumerate(KINDS):
        own = _spans(text, number, PATTERNS[kind], lambda x, k=kind: _valid(k, x))
        parts.append(F.when(F.contains(text, F.lit(needs[kind])), own).otherwise(_none()) if kind in needs else own)
    return F.sort_array(F.concat(*parts))


def spans_text(spans: Column) -> Column:
    """kind:start:end of each span, comma-joined."""
    names = F.array(*[F.lit(k) for k in KINDS])
    return F.array_join(F.transform(spans, lambda s: F.concat_ws(":", F.get(names, s["kind"]), s["start"].cast("string"), s["end"].cast("string"))), ",")


def _with_context(text: Column, spans: Column) -> Column:
    """Spans with their value and the patterns around them: ``< word`` before, ``> word`` after, and both."""

    def bare(word: Column) -> Column:
        return F.lower(F.regexp_replace(word, r"[#*$%&|<>,.;:()\"]+", ""))

    def one(s: Column) -> Column:
        before = F.substring(text, F.greatest(s["start"] - 39, F.lit(1)), F.least(s["start"], F.lit(40)))
        left = bare(F.regexp_extract(before, r"([^ \x09-\x0D]+)[ \x09-\x0D]*$", 1))
        right = bare(F.regexp_extract(F.substring(text, s["end"] + 1, F.lit(40)), r"^[ \x09-\x0D]*([^ \x09-\x0D]+)", 1))
        value = F.substring(text, s["start"] + 1, s["end"] - s["start"])
        around = F.array(
            F.when(left != "", F.concat(F.lit("< "), left)), F.when(right != "", F.concat(F.lit("> "), right)),
            F.when((left != "") & (right != ""), F.concat(F.lit("< "), left, F.lit(" > "), right)),
        )
        return F.struct(s["start"].alias("start"), s["end"].alias("end"), s["kind"].alias("kind"), value.alias("value"), F.array_compact(around).alias("words"))

    return F.transform(spans, one)


def _candidates(text: Column) -> Column:
    parts = []
    for pattern, needs in CANDIDATES:
        own = _spans(text, -1, pattern, lambda x: F.lit(True))
        parts.append(own if needs is None else F.when(text.rlike(needs), own).otherwise(_none()))
    return F.concat(*parts)


def scan(df: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, text_key, base, seeds, candidates) of each row.

    text_key tells apart rows that share an id.
    """
    text = F.coalesce(F.col(text_col), F.lit(""))
    src = df.select(F.col(id_col).alias("doc_id"), text.alias("text"))
    src = src.select("doc_id", F.xxhash64("text").alias("text_key"), "text", seed_spans(F.col("text")).alias("base"), _candidates(F.col("text")).alias("raw"))
    free = F.filter("raw", lambda c: ~F.exists("base", lambda b: (b["start"] < c["end"]) & (c["start"] < b["end"])))
    return src.select("doc_id", "text_key", "base", _with_context(F.col("text"), F.col("base")).alias("seeds"), _with_context(F.col("text"), free).alias("candidates"))


def _fits(kind: Column, value: Column) -> Column:
    """Whether a candidate could be of a kind at all."""
    n, digits = F.length(_digits(value)), value.rlike("^[0-9 .-]+$")
    shapes = {"email": value.rlike("@|at[)\\]]"), "ip": value.rlike(":"), "card": digits & n.between(12, 19), "phone": digits & n.between(8, 15)}
    return F.coalesce(*[F.when(kind == i, shapes[k]) for i, k in enumerate(KINDS)], F.lit(False))


def discover(scanned: DataFrame, min_seeds: int = MIN_SEEDS, min_confidence: float = MIN_CONFIDENCE) -> DataFrame:
    """(doc_id, text_key, start, end, kind) of candidates under trusted patterns.

    The graph holds distinct (pattern, value) pairs, so copies of a document add
    nothing.  A pattern has a kind; it needs ``min_seeds``
    distinct known values.  Its confidence is the smoothed share of these among them and
    its contradicting values: those known as another kind, and unknown
    ones that could not be of the kind.  Unknown values that could be say nothing.  A value's confidence is the
    noisy-or over its patterns; the kind with the best pattern counts.
    """
    rows = scanned.select("doc_id", "text_key", F.explode(F.concat("seeds", "candidates")).alias("x")).select("doc_id", "text_key", "x.*").withColumn("word", F.explode("words")).drop("words")
    graph = durable(rows.groupBy("word", "value").agg(F.max("kind").alias("kind")))
    known, n_known = graph, graph.where("kind >= 0").count()
    numbers = range(len(KINDS))
    while True:
        own = [F.count_if(F.col("kind") == k).alias(f"known_{k}") for k in numbers]
        against = [F.count_if((F.col("kind") != k) & ((F.col("kind") >= 0) | ~_fits(F.lit(k), F.col("value")))).alias(f"against_{k}") for k in numbers]
        totals = known.groupBy("word").agg(*own, *against)
        each = F.array(*[F.struct(F.lit(k).alias("as_kind"), F.col(f"known_{k}").alias("n"), F.col(f"against_{k}").alias("contrary")) for k in numbers])
        scored = totals.select("word", F.explode(each).alias("k")).select("word", "k.*").where(F.col("n") >= min_seeds)
        trusted = durable(scored.withColumn("confidence", (F.col("n") + 0.5) / (F.col("n") + F.col("contrary") + 1)).where(F.col("confidence") >= min_confidence).select("word", "as_kind", "confidence"))
        scores = (
            graph.where(F.col("kind") < 0).join(trusted, "word").where(_fits(F.col("as_kind"), F.col("value")))
            .groupBy("value", "as_kind").agg((1 - F.exp(F.sum(F.log1p(-F.least("confidence", F.lit(0.999)))))).alias("score")).where(F.col("score") >= min_confidence)
            .groupBy("value").agg(F.max_by("as_kind", F.struct("score", "as_kind")).alias("new_kind"))
        )
        # what is known stays known, so the rounds end
        known = durable(known.join(scores, "value", "left").select("word", "value", F.when(F.col("kind") >= 0, F.col("kind")).otherwise(F.coalesce("new_kind", F.lit(-1))).alias("kind")))
        before, n_known = n_known, known.where("kind >= 0").count()
        if n_known == before:
            break
    found = rows.where(F.col("kind") < 0).join(trusted, "word").where(_fits(F.col("as_kind"), F.col("value")))
    return found.groupBy("doc_id", "text_key", "start", "end").agg(F.max_by("as_kind", F.struct("confidence", "as_kind")).alias("kind"))


def find_personal_data(df: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, text_key, base, spans) of each row: strict spans, and all spans.

    Null texts have none.  Rows that share an id are told apart by text; equal rows get equal spans.
    """
    scanned = durable(scan(df, id_col, text_col))
    span = F.struct(F.col("start"), F.col("kind"), F.col("end"))
    extra = discover(scanned).groupBy("doc_id", "text_key").agg(F.sort_array(F.collect_set(span)).alias("extra")).withColumnsRenamed({"doc_id": "__id", "text_key": "__key"})
    joined = scanned.join(extra, F.col("doc_id").eqNullSafe(F.col("__id")) & (F.col("text_key") == F.col("__key")), "left")
    return joined.select("doc_id", "text_key", "base", F.sort_array(F.concat("base", F.coalesce("extra", _none()))).alias("spans"))


def mask(text: Column, spans: Column) -> Column:
    """The text with each span replaced by its kind in square brackets; overlapping spans are masked as one."""
    names = F.array(*[F.lit(f"[{k.upper()}]") for k in KINDS])

    def merged(acc: Column, s: Column) -> Column:
        last = F.element_at(acc, -1)
        grown = F.struct(last["start"].alias("start"), last["kind"].alias("kind"), F.greatest(last["end"], s["end"]).alias("end"))
        return F.when((F.size(acc) > 0) & (s["start"] < F.when(F.size(acc) > 0, last["end"])), F.concat(F.slice(acc, 1, F.size(acc) - 1), F.array(grown))).otherwise(F.concat(acc, F.array(s)))

    def build(m: Column) -> Column:
        def piece(s: Column, j: Column) -> Column:
            end = F.coalesce(F.get(m, j - 1)["end"], F.lit(0))
            return F.concat(F.substring(text, end + 1, s["start"] - end), F.get(names, s["kind"]))

        tail = F.element_at(m, -1)["end"]
        return F.concat(F.array_join(F.transform(m, piece), ""), F.substring(text, tail + 1, F.length(text)))

    whole = bound("m", build, F.aggregate(spans, _none(), merged))
    return F.when(text.isNull() | spans.isNull() | (F.size(spans) == 0), text).otherwise(whole)


def redact(df: DataFrame) -> DataFrame:
    """Documents with personal data masked and n_chars counted anew; every row and column stays."""
    found = find_personal_data(df).where(F.size("spans") > 0).select(F.col("doc_id").alias("__id"), F.col("text_key").alias("__key"), "spans").dropDuplicates(["__id", "__key"])
    keyed = df.withColumn("__own", F.xxhash64(F.coalesce("text", F.lit(""))))
    joined = keyed.join(found, F.col("doc_id").eqNullSafe(F.col("__id")) & (F.col("__own") == F.col("__key")), "left")
    text = mask(F.col("text"), F.col("spans"))
    changed = joined.withColumn("text", text)
    if "n_chars" in df.columns:
        changed = changed.withColumn("n_chars", F.when(F.col("spans").isNotNull(), F.length("text").cast(dict(df.dtypes)["n_chars"])).otherwise(F.col("n_chars")))
    return changed.select(*df.columns)
