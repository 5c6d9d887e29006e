"""The registered queries of this subpackage and their SQL."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import byte_bpe, chat_quotes, decontaminate, html_extract, language_id, ngram_join, pii, quality_rules, suffix_dedup, token_counts
from .common import table


def op1_byte_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    import public_tokenizers

    ranks = byte_bpe.read_ranks(public_tokenizers.path("byte_bpe_50k.tiktoken"))
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    return byte_bpe.round_trip_digest(docs, ranks, public_tokenizers.PATTERN, return_text=False)


def op2_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    judged = quality_rules.judge(table(spark, sf_dir, "documents"))
    return judged.select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept")


def rules_by_length(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The same rules with steps of length as hosts, some of which are bad enough to take good documents with them."""
    docs = table(spark, sf_dir, "documents").withColumn("step", F.concat(F.lit("s"), F.least(F.floor(F.col("n_chars") / 400), F.lit(9))))
    judged = quality_rules.judge(docs, host_col="step")
    return judged.select("doc_id", "n_words", "base_failed", "kept")


def benchmark_proximity(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(doc_id, item_id): documents that hold all words of a benchmark item within a hundred words."""
    return decontaminate.proximity_matches(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"), 100)


def op3_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    import public_tokenizers

    pieces = token_counts.read_pieces(public_tokenizers.path("piece_bpe_32k.model"))
    return token_counts.count_tokens(table(spark, sf_dir, "documents"), pieces)


def op4_html_extraction(spark: SparkSession, sf_dir: str) -> DataFrame:
    return html_extract.extract(table(spark, sf_dir, "pages"))


def op5_personal_data(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = pii.find_personal_data(table(spark, sf_dir, "documents"))
    kinds = F.transform("base", lambda s: s["kind"])
    counts = [(F.size(kinds) - F.size(F.array_remove(kinds, i))).cast("bigint").alias(f"n_{k}") for i, k in enumerate(pii.KINDS)]
    return found.select("doc_id", *counts, F.sha2(pii.spans_text(F.col("base")), 256).alias("base_sha256"), pii.spans_text(F.col("spans")).alias("spans"))


def op6_ngram_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    return ngram_join.jaccard_groups(table(spark, sf_dir, "documents")).select("doc_id", "n_shingles", "component_id", "class_id")


def op7_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = decontaminate.find_contamination(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))
    return found.select("doc_id", "n_words", "n_hit", "n_items", "items_sha256", "contaminated")


def op8_suffix_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return suffix_dedup.remove_repeats(table(spark, sf_dir, "documents"))


def op9_chat_formatting(spark: SparkSession, sf_dir: str) -> DataFrame:
    return chat_quotes.link(table(spark, sf_dir, "conversations"))


def quoted_conversations(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The conversations again, with quotations put in: each message quotes the one or two before it."""
    return chat_quotes.link(chat_quotes.with_quotations(table(spark, sf_dir, "conversations")))


def op10_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    # the labels train the text model; they are not evidence for the rows judged
    model = language_id.fit_text_model(docs)
    return language_id.identify(docs, model).select("doc_id", "language", F.round("posterior", 6).alias("posterior"), "accepted")


def pages_language(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All four kinds of evidence on pages: words, declared language, suffix, and host under its domains."""
    model = language_id.fit_text_model(table(spark, sf_dir, "documents"))
    pages = language_id.page_evidence(table(spark, sf_dir, "pages"))
    found = language_id.identify(pages, model, id_col="page_id", declared_col="declared", host_col=None, url_col="url")
    return found.select("page_id", "language", F.round("posterior", 6).alias("posterior"), "accepted")


#: Words as the contract has them, windows of three, and the host verdict by moments.
OP2_SQL = r"""
WITH d AS (
  SELECT doc_id, source AS host, coalesce(text, '') AS t,
         list_filter(regexp_split_to_array(coalesce(text, ''), '[ \x09-\x0D]+'), lambda w: w <> '') AS w
  FROM documents
), k AS (
  SELECT doc_id, host, t, w, len(w) AS n,
         [w[i] || ' ' || w[i + 1] || ' ' || w[i + 2] FOR i IN range(1, len(w) - 1)] AS g,
         list_filter(string_split(t, chr(10)), lambda x: regexp_matches(x, '[^ \x09-\x0D]')) AS lines
  FROM d
), p AS (
  SELECT doc_id, unnest(g) AS v, unnest(range(len(g))) AS i FROM k WHERE n >= 4
), r AS (
  SELECT doc_id, i FROM (SELECT doc_id, i, count(*) OVER (PARTITION BY doc_id, v) AS c FROM p) WHERE c > 1
), m AS (
  SELECT doc_id, count(DISTINCT j) AS n_repeat_words FROM (SELECT doc_id, unnest([i, i + 1, i + 2]) AS j FROM r) GROUP BY doc_id
), b AS (
  SELECT k.doc_id, host, n::BIGINT AS n_words, length(regexp_replace(t, '[ \x09-\x0D]+', '', 'g'))::BIGINT AS word_chars,
         (length(t) - length(regexp_replace(t, '[#*$%&|<>]+', '', 'g')))::BIGINT AS n_symbols,
         (len(lines) - len(list_distinct(lines)))::BIGINT AS n_dup_lines, coalesce(n_repeat_words, 0)::BIGINT AS n_repeat_words
  FROM k LEFT JOIN m ON k.doc_id = m.doc_id
), f AS (
  SELECT *, (n_words < 50 OR 100 * n_repeat_words > 50 * n_words) AS base_failed FROM b
), h AS (
  SELECT host, count(*) AS n, sum(base_failed::INT) AS bad FROM f WHERE host IS NOT NULL GROUP BY host
), s AS (
  SELECT avg(bad / n) AS mu, coalesce(var_samp(bad / n), 0) AS v FROM h
), q AS (
  SELECT mu, CASE WHEN v > 0 AND mu * (1 - mu) / v - 1 > 0 THEN mu * (1 - mu) / v - 1 ELSE 10 END AS strength FROM s
), o AS (
  SELECT host, (bad + mu * strength) / (n + strength) <= 0.5 AS host_ok FROM h, q
)
SELECT doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, base_failed, (NOT base_failed AND coalesce(host_ok, TRUE)) AS kept
FROM f LEFT JOIN o USING (host)
"""

#: Quotations over messages ``m``: passages and their sentences as texts, the latest earlier message that wrote them,
#: the vote for the lowest level, most text and latest message, and paths of ancestors.
LINK_SQL = r"""
r AS (
  SELECT row_number() OVER () AS rid, conv_id, turn, role, string_split(coalesce(text, ''), chr(10)) AS lines FROM m
), l AS (
  SELECT rid, unnest(lines) AS line, unnest(range(len(lines))) AS i FROM r
), n AS (
  SELECT rid, line, i, length(regexp_replace(regexp_extract(line, '^[ \x09]*(?:>[ \x09]*)+'), '[^>]', '', 'g')) AS level,
         lower(trim(regexp_replace(regexp_replace(line, '^[ \x09]*(?:>[ \x09]*)+', ''), '[ \x09-\x0D]+', ' ', 'g'))) AS norm
  FROM l
), b AS (
  SELECT rid, max(level)::INT AS quote_level, trim(coalesce(string_agg(line, chr(10) ORDER BY i) FILTER (level = 0), '')) AS body FROM n GROUP BY rid
), f AS (
  SELECT *, (norm <> '' AND (lag(norm, 1, '') OVER w = '' OR lag(level) OVER w <> level))::INT AS fresh FROM n WINDOW w AS (PARTITION BY rid ORDER BY i)
), g AS (
  SELECT *, sum(fresh) OVER (PARTITION BY rid ORDER BY i) AS run FROM f
), p AS (
  SELECT rid, run, level, string_agg(norm, ' ' ORDER BY i) AS passage FROM g WHERE norm <> '' GROUP BY rid, run, level
), s AS (
  SELECT *, list_filter(list_transform(regexp_extract_all(passage, '[^.!?]*[.!?]+|[^.!?]+'), lambda x: trim(x)), lambda x: x <> '') AS parts FROM p
), u AS (
  SELECT rid, level, unnest([passage] || [parts[k] || ' ' || parts[k + 1] FOR k IN range(1, len(parts))] || parts) AS unit FROM s
), t AS (
  SELECT DISTINCT r.conv_id, r.turn, u.level, u.unit FROM u JOIN r USING (rid)
), o AS (
  SELECT q.conv_id, q.turn, q.level, q.unit, max(w.turn) AS origin
  FROM t q JOIN t w ON q.conv_id = w.conv_id AND q.unit = w.unit AND w.level = 0 AND w.turn < q.turn WHERE q.level > 0 GROUP BY ALL
), v AS (
  SELECT conv_id, turn, origin, min(level) AS level, sum(length(unit)) AS weight, count(*) AS n FROM o GROUP BY ALL
), z AS (
  SELECT conv_id, turn, arg_max(origin, (-level, weight, origin)) AS parent, sum(n)::BIGINT AS n_links FROM v GROUP BY ALL
), c AS (
  SELECT conv_id, turn, parent AS up, lpad(parent::VARCHAR, 19, '0') || '.' || lpad(turn::VARCHAR, 19, '0') AS path FROM z
  UNION ALL
  SELECT c.conv_id, c.turn, z.parent, lpad(z.parent::VARCHAR, 19, '0') || '.' || c.path FROM c JOIN z ON c.conv_id = z.conv_id AND c.up = z.turn
), d AS (
  SELECT conv_id, turn, max_by(path, length(path)) AS path FROM c GROUP BY ALL
)
SELECT r.conv_id, r.turn, r.role, b.body, z.parent AS parent_turn, b.quote_level, coalesce(z.n_links, 0)::BIGINT AS n_links, coalesce(d.path, lpad(r.turn::VARCHAR, 19, '0')) AS order_key
FROM r JOIN b USING (rid) LEFT JOIN z ON r.conv_id = z.conv_id AND r.turn = z.turn LEFT JOIN d ON r.conv_id = d.conv_id AND r.turn = d.turn
"""
OP9_SQL = "WITH RECURSIVE m AS (SELECT conv_id, turn, role, text FROM conversations), " + LINK_SQL
QUOTED_SQL = (
    r"""
WITH RECURSIVE w AS (
  SELECT conv_id, turn, role, coalesce(text, '') AS text,
         '> ' || regexp_replace(replace(coalesce(text, ''), chr(10), ' '), '((?:[^ ]+ +){7}[^ ]+) +', '\1' || chr(10) || '> ', 'g') || chr(10) AS q1,
         '> > ' || regexp_replace(replace(coalesce(text, ''), chr(10), ' '), '((?:[^ ]+ +){7}[^ ]+) +', '\1' || chr(10) || '> > ', 'g') || chr(10) AS q2
  FROM conversations
), m AS (
  SELECT w.conv_id, w.turn, w.role, coalesce(b.q2, '') || coalesce(a.q1, '') || w.text AS text
  FROM w LEFT JOIN w a ON a.conv_id = w.conv_id AND a.turn + 1 = w.turn LEFT JOIN w b ON b.conv_id = w.conv_id AND b.turn + 2 = w.turn
), """
    + LINK_SQL
)

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    f.__name__: f
    for f in (
        op1_byte_bpe, op2_quality_rules, op3_token_counts, op4_html_extraction, op5_personal_data,
        op6_ngram_join, op7_decontamination, op8_suffix_dedup, op9_chat_formatting, op10_language_id, pages_language, quoted_conversations, rules_by_length, benchmark_proximity,
    )
}

RULES_SQL = OP2_SQL.replace("source AS host", "'s' || least(n_chars // 400, 9) AS host").replace("SELECT doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, base_failed,", "SELECT doc_id, n_words, base_failed,")
ORACLE_SQL: dict[str, str] = {"op2_quality_rules": OP2_SQL, "rules_by_length": RULES_SQL, "op9_chat_formatting": OP9_SQL, "quoted_conversations": QUOTED_SQL}
