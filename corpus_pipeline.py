"""Corpus pipeline: five stages over documents, each written as Parquet and read again.

A stage that ends in Python writes its rows itself: whoever writes them otherwise would hand Python batches of 64 MB.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from vecmend.llm import byte_bpe, decontaminate, language_id, ngram_join, pii
from vecmend.llm.common import durable, forget_since, table, tables_written


def identify_language(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents whose language is accepted; the rejected go.

    The verdict is carried by doc_id and a hash of what it was found from, so that
    rows that share an id, or have none, are judged one by one.  Null and empty texts and texts without letters are
    rejected, equal rows share a verdict, an empty table stays empty, and columns beside those read go through unchanged.
    """
    read = [x for c in ("text", "lang", "source") for x in (F.col(c), F.col(c).isNull())]
    keyed = docs.withColumn("__row", F.struct(F.col("doc_id").alias("id"), F.xxhash64(*read).alias("key")))
    found = language_id.identify(keyed, language_id.fit_text_model(docs), id_col="__row")
    gone = durable(found.where("not accepted").select("__row").distinct())
    side = ngram_join._sized(gone).withColumnRenamed("__row", "__gone")
    same = keyed["__row"]["id"].eqNullSafe(side["__gone"]["id"]) & (keyed["__row"]["key"] == side["__gone"]["key"])
    return keyed.join(side, same, "left_anti").select(*docs.columns)


def join_near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of similar documents, that with the smallest id.

    Equal rows stay once, other texts of an id are documents of their own, and rows without an id all stay.
    """
    return ngram_join.keep_one_of_each(docs)


def drop_contaminated(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that no benchmark passage contaminates, row by row; null and empty texts hold no passage and stay."""
    return durable(decontaminate.clean_documents(docs, table(spark, sf_dir, "benchmark")))


def mask_personal_data(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """All documents, with personal data masked; null texts stay null and equal texts are masked alike."""
    return pii.redact(docs)


def encode_bytes(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """All documents with their token counts and digests of ids and decoded bytes; a null text counts as empty, and every row stays."""
    import public_tokenizers

    ranks = byte_bpe.read_ranks(public_tokenizers.path("byte_bpe_50k.tiktoken"))
    return durable(byte_bpe.round_trip_digest(docs, ranks, public_tokenizers.PATTERN))


STAGES = [
    ("language_id", identify_language),
    ("ngram_jaccard_join", join_near_copies),
    ("benchmark_decontamination", drop_contaminated),
    ("personal_data", mask_personal_data),
    ("byte_bpe", encode_bytes),
]

#: Language scores, discovery of patterns and token ids have no SQL form; tests use brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over documents, each written in the shared folder and read again.

    When a stage is written, what it and its predecessor left in between is deleted.
    """
    docs, mark = table(spark, sf_dir, "documents"), tables_written(spark)
    for _, stage in STAGES[:-1]:
        docs = durable(stage(spark, docs, sf_dir))
        forget_since(spark, mark)
    return STAGES[-1][1](spark, docs, sf_dir)
