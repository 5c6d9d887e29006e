"""Chat formatting by quotation linking, in DataFrame expressions only.

Lines that start with ``>`` marks are quotations; the number of marks is the
level.  A run of lines of one level, up to a line without text, is a passage; its line breaks
become spaces, so that a passage that a mail client wrapped anew stays the same.
A passage, its pairs of neighbouring sentences and its sentences are hashed, and joined,
within a conversation, to the latest earlier message that wrote the same.  A message replies to
the message that most of its quoted text of the lowest level comes from; the quotations themselves are dropped.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import durable

MARKS = r"^[ \x09]*(?:>[ \x09]*)+"
#: A sentence with its end marks, or end marks alone, or text without any.
SENTENCE = r"[^.!?]*[.!?]+|[^.!?]+"
#: Turns that one bitmap of origins covers.
SPAN = 60
_OPEN, _SHUT = "\x02", "\x03"


def level(line: Column) -> Column:
    """Quote level of a line: the number of marks before its text."""
    return F.length(F.regexp_replace(F.regexp_extract(line, MARKS, 0), "[^>]", ""))


def normal(line: Column) -> Column:
    """Marks off, lower case, white space to one space."""
    bare = F.regexp_replace(line, MARKS, "")
    return F.lower(F.trim(F.regexp_replace(bare, r"[ \x09-\x0D]+", " ")))


def units(text: Column) -> Column:
    """What of a passage is hashed: the whole, neighbouring sentences, sentences; each with its length."""
    sentences = F.filter(F.transform(F.regexp_extract_all(text, F.lit(SENTENCE), F.lit(0)), lambda x: F.trim(x)), lambda x: x != "")

    def all_of(s: Column) -> Column:
        pairs = F.transform(F.slice(s, 2, F.greatest(F.size(s), F.lit(1))), lambda x, i: F.concat_ws(" ", F.get(s, i), x))
        return F.concat(F.array(text), pairs, s)

    found = F.get(F.transform(F.array(sentences), all_of), F.lit(0))
    return F.transform(found, lambda u: F.struct(F.xxhash64(u).alias("hash"), F.length(u).alias("n")))


def parse(messages: DataFrame) -> DataFrame:
    """(conv_id, turn, role, body, max_level, own, quoted).

    ``body`` is the text without quoted lines, ``own`` the units (hash, length) of its
    passages, ``quoted`` the (level, hash, length) of those of quoted passages.
    """
    text = F.translate(F.coalesce(F.col("text"), F.lit("")), _OPEN + _SHUT, "")
    src = messages.select("conv_id", "turn", "role", F.split(text, "\n", -1).alias("lines"))
    src = src.withColumn("parts", F.transform("lines", lambda x: F.struct(level(x).alias("level"), x.alias("line"), normal(x).alias("norm"))))

    def marked(p: Column, i: Column) -> Column:
        before = F.get("parts", i - 1)
        goes_on = (i > 0) & (before["level"] == p["level"]) & (before["norm"] != "")
        return F.when(p["norm"] == "", "").when(goes_on, F.concat(F.lit(" "), p["norm"])).otherwise(F.concat(F.lit(_OPEN), p["level"].cast("string"), F.lit(_SHUT), p["norm"]))

    runs = F.filter(F.split(F.array_join(F.transform("parts", marked), ""), _OPEN, -1), lambda r: r != "")
    src = src.withColumn("runs", F.transform(runs, lambda r: F.struct(F.substring_index(r, _SHUT, 1).cast("int").alias("level"), units(F.substring_index(r, _SHUT, -1)).alias("units"))))
    own = F.flatten(F.transform(F.filter("runs", lambda r: r["level"] == 0), lambda r: r["units"]))
    quoted = F.flatten(F.transform(F.filter("runs", lambda r: r["level"] > 0), lambda r: F.transform(r["units"], lambda u: F.struct(r["level"].alias("level"), u["hash"].alias("hash"), u["n"].alias("n")))))
    body = F.array_join(F.transform(F.filter("parts", lambda p: p["level"] == 0), lambda p: p["line"]), "\n")
    deepest = F.coalesce(F.array_max(F.transform("parts", lambda p: p["level"])), F.lit(0))
    return src.select("conv_id", "turn", "role", F.trim(body).alias("body"), deepest.alias("max_level"), F.array_distinct(own).alias("own"), F.array_distinct(quoted).alias("quoted"))


def _origins(quotes: DataFrame, own: DataFrame) -> DataFrame:
    """Quotes with ``origin``, the latest earlier turn that wrote the same, if any.

    Turns are held as bitmaps of 60, so a unit that many turns write and many quote gives few rows
    to sort, and each quote meets one row: no pairs of a hot unit are formed.
    """
    block = F.floor(F.col("turn") / SPAN)
    bit = F.expr(f"shiftleft(1L, cast(pmod(turn, {SPAN}) as int))")
    asked = quotes.select("conv_id", "hash", block.alias("block"), F.lit(0).cast("bigint").alias("bit"), F.lit(None).cast("bigint").alias("turn"))
    wrote = own.join(quotes.select("conv_id", "hash").distinct(), ["conv_id", "hash"], "left_semi").select("conv_id", "hash", block.alias("block"), bit.alias("bit"), F.col("turn").cast("bigint"))
    maps = asked.union(wrote).groupBy("conv_id", "hash", "block").agg(F.bit_or("bit").alias("bits"), F.max("turn").alias("last"))
    before = Window.partitionBy("conv_id", "hash").orderBy("block").rowsBetween(Window.unboundedPreceding, -1)
    maps = maps.withColumn("before", F.max("last").over(before)).drop("last")
    met = quotes.withColumn("block", block).join(maps, ["conv_id", "hash", "block"])
    lower = F.col("bits").bitwiseAND(F.expr(f"shiftleft(1L, cast(pmod(turn, {SPAN}) as int)) - 1"))
    highest = F.length(F.bin(lower)) - 1
    return met.withColumn("origin", F.when(lower != 0, F.col("block") * SPAN + highest).otherwise(F.col("before"))).drop("block", "bits", "before").where(F.col("origin").isNotNull())


def _pad(turn: Column) -> Column:
    return F.lpad(turn.cast("string"), 19, "0")


def _paths(parents: DataFrame) -> DataFrame:
    """(conv_id, turn, path): turns of all ancestors and the own one, from rows (conv_id, turn, parent).

    Each round appends to every path that of its upper end, so the rounds grow with the logarithm of the depth.
    """
    paths = durable(parents.select("conv_id", "turn", _pad(F.col("turn")).alias("path"), F.col("parent").alias("up")))
    while not paths.where("up is not null").isEmpty():
        above = paths.select("conv_id", F.col("turn").alias("up"), F.col("path").alias("above"), F.col("up").alias("next"))
        paths = durable(
            paths.join(above, ["conv_id", "up"], "left")
            .select("conv_id", "turn", F.when(F.col("up").isNull(), F.col("path")).otherwise(F.concat_ws(".", F.coalesce("above", _pad(F.col("up"))), "path")).alias("path"), F.col("next").alias("up"))
        )
    return paths.drop("up")


def link(messages: DataFrame) -> DataFrame:
    """One row per message: conv_id, turn, role, body, parent_turn, quote_level, n_links, order_key.

    parent_turn is null where nothing quoted is found in an earlier turn of the same
    conversation; ties go to the latest origin.  n_links counts the quoted units that were found.  order_key is the path of turns
    from the first message down, so that sorted by it every reply stands below the message that it quotes, with
    whatever replies to it; it grows with the depth of the thread.  Turns are whole numbers, not negative.  Null texts are empty
    messages, a null conversation or turn links to nothing, repeated rows give repeated results, rows that share a turn
    have the parent that their quotations give together, an empty table gives an empty one, and other columns are ignored.
    """
    parsed = durable(parse(messages))
    own = parsed.select("conv_id", "turn", F.explode("own.hash").alias("hash")).distinct()
    quotes = parsed.select("conv_id", "turn", F.explode("quoted").alias("q")).select("conv_id", "turn", "q.*").where("conv_id is not null and turn is not null").distinct()
    votes = _origins(quotes, own).groupBy("conv_id", "turn", "origin").agg(F.min("level").alias("level"), F.sum("n").alias("weight"), F.count(F.lit(1)).alias("n"))
    # lowest level first, then most text, then the latest message
    best = votes.groupBy("conv_id", "turn").agg(F.max(F.struct((-F.col("level")).alias("near"), "weight", "origin"))["origin"].alias("parent"), F.sum("n").alias("n_links"))
    best = durable(best)
    linked = parsed.join(best, ["conv_id", "turn"], "left").join(_paths(best), ["conv_id", "turn"], "left")
    return linked.select(
        "conv_id", "turn", "role", "body", F.col("parent").alias("parent_turn"), F.col("max_level").cast("int").alias("quote_level"),
        F.coalesce("n_links", F.lit(0)).cast("bigint").alias("n_links"), F.coalesce("path", _pad(F.col("turn"))).alias("order_key"),
    )


def with_quotations(messages: DataFrame) -> DataFrame:
    """(conv_id, turn, role, text): every message but the first quotes the one before it, and from the third on that one's quotation too.

    Line breaks of what is quoted fall after other words than in the original.
    """
    text, key = F.coalesce(F.col("text"), F.lit("")), ["conv_id", "turn"]
    wrapped = lambda marks: F.regexp_replace(F.translate(F.col("said"), "\n", " "), r"((?:[^ ]+ +){7}[^ ]+) +", "$1\n" + marks)
    prior = []
    said = messages.select("conv_id", "turn", text.alias("said"))
    for n in (2, 1):
        prior.append(said.select("conv_id", (F.col("turn") + n).alias("turn"), F.concat(F.lit("> " * n), wrapped("> " * n), F.lit("\n")).alias(f"q{n}")))
    rows = messages.select(*key, "role", text.alias("own"))
    for p in prior:
        rows = rows.join(p, key, "left")
    return rows.select(*key, "role", F.concat(F.coalesce("q2", F.lit("")), F.coalesce("q1", F.lit("")), "own").alias("text"))
