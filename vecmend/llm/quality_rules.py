"""Quality rules with host verdicts, in DataFrame expressions only.

Document rules give a failure per document.  Failures are summed by host, each
host's rate is shrunk by a beta prior that is fitted to all hosts by moments,
and the host's verdict is joined back to its documents.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import bound, durable

BLANK = r"[ \x09-\x0D]+"
MIN_WORDS = 50
MAX_REPEAT_PERCENT = 50
#: A host is refused when its shrunk failure rate is above this share.
HOST_LIMIT = 0.5
#: Prior observations where the hosts' rates show no spread.
FLAT_STRENGTH = 10.0


def words_of(text: Column) -> Column:
    return F.array_remove(F.split(text, BLANK), "")


def _repeat_words(words: Column) -> Column:
    """Words that lie in a 3-word window found twice or more; sorts the windows, so n log n."""
    n = F.size(words)

    def covered(places: Column) -> Column:
        step = F.transform(places, lambda p, j: F.least(F.lit(3), F.coalesce(F.get(places, j + 1) - p, F.lit(3))))
        return F.aggregate(step, F.lit(0).cast("bigint"), lambda a, x: a + x)

    def repeated(ranked: Column) -> Column:
        def place(x: Column, j: Column) -> Column:
            return F.when((F.get(ranked, j - 1)["k"] == x["k"]) | (F.get(ranked, j + 1)["k"] == x["k"]), x["i"])

        return bound("c", covered, F.sort_array(F.filter(F.transform(ranked, place), lambda p: p.isNotNull())))

    def window(i: Column) -> Column:
        return F.struct(F.concat_ws(" ", F.get(words, i), F.get(words, i + 1), F.get(words, i + 2)).alias("k"), i.alias("i"))

    # a sequence never runs backwards here: both ends are kept at 0 for short texts
    windows = F.transform(F.sequence(F.lit(0), F.greatest(n - 3, F.lit(0))), window)
    return F.when(n < 4, F.lit(0).cast("bigint")).otherwise(bound("r", repeated, F.sort_array(windows)))


def document_rules(df: DataFrame, id_col: str = "doc_id", text_col: str = "text", host_col: str = "source") -> DataFrame:
    """(id, host, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, base_failed), one row per input row.

    A null text has no words and fails; a null host is kept as null.
    """
    text = F.coalesce(F.col(text_col), F.lit(""))
    src = df.select(F.col(id_col).alias("doc_id"), F.col(host_col).cast("string").alias("host"), text.alias("text"))
    words = bound("w", lambda w: F.struct(F.size(w).cast("bigint").alias("n"), _repeat_words(w).alias("r")), words_of(F.col("text")))
    lines = bound("l", lambda x: (F.size(x) - F.size(F.array_distinct(x))).cast("bigint"), F.filter(F.split("text", "\n", -1), lambda x: x.rlike(r"[^ \x09-\x0D]")))
    out = src.select(
        "doc_id", "host", words.alias("w"),
        F.length(F.regexp_replace("text", BLANK, "")).cast("bigint").alias("word_chars"),
        (F.length("text") - F.length(F.regexp_replace("text", r"[#*$%&|<>]+", ""))).cast("bigint").alias("n_symbols"),
        lines.alias("n_dup_lines"),
    )
    out = out.select("doc_id", "host", F.col("w.n").alias("n_words"), "word_chars", "n_symbols", "n_dup_lines", F.col("w.r").alias("n_repeat_words"))
    failed = (F.col("n_words") < MIN_WORDS) | (100 * F.col("n_repeat_words") > MAX_REPEAT_PERCENT * F.col("n_words"))
    return out.withColumn("base_failed", failed)


def host_verdicts(rules: DataFrame, limit: float = HOST_LIMIT) -> DataFrame:
    """(host, n_docs, n_failed, shrunk_rate, host_ok) of every non-null host.

    The beta prior's mean and strength come from the mean and variance of the
    hosts' rates; with no spread, or one host, a flat strength is used.
    """
    hosts = rules.where(F.col("host").isNotNull()).groupBy("host").agg(
        F.count(F.lit(1)).alias("n_docs"), F.sum(F.col("base_failed").cast("bigint")).alias("n_failed")
    )
    rate = F.col("n_failed") / F.col("n_docs")
    fit = hosts.agg(F.avg(rate).alias("m"), F.var_samp(rate).alias("v")).first()
    mean, spread = fit["m"] or 0.0, fit["v"] or 0.0
    strength = mean * (1 - mean) / spread - 1 if spread > 0 else FLAT_STRENGTH
    strength = strength if strength > 0 else FLAT_STRENGTH
    shrunk = (F.col("n_failed") + F.lit(mean * strength)) / (F.col("n_docs") + F.lit(strength))
    return hosts.withColumn("shrunk_rate", shrunk).withColumn("host_ok", F.col("shrunk_rate") <= limit)


def judge(df: DataFrame, limit: float = HOST_LIMIT, host_col: str = "source") -> DataFrame:
    """Rules, host verdicts and ``kept`` for every document row.

    The rules are computed once and written to the checkpoint folder.  Only the
    narrow rows are joined with the hosts, and Spark splits a hot host.
    Documents without a host are judged by their own rules alone.
    """
    rules = durable(document_rules(df, host_col=host_col))
    joined = rules.join(host_verdicts(rules, limit), "host", "left")
    return joined.withColumn("kept", ~F.col("base_failed") & F.coalesce("host_ok", F.lit(True)))
