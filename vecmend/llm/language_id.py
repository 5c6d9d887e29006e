"""Language identification by Bayesian fusion of four kinds of evidence.

1. Text: naive Bayes over hashed byte trigrams, fitted on a bounded sample of
   labelled rows and tempered, since neighbouring trigrams are not independent.
2. Markup: the language a page or record declares, through a confusion table
   that is estimated by grouped aggregation over the whole corpus.
3. Address suffix: the last label of the host name, same kind of table.
4. Host: a prior from the host's own rows, smoothed towards the domain above it,
   that towards the registered domain, and that towards the corpus (Dirichlet at each level).

A document is rejected if its text has no letters or its best posterior stays
under ``min_posterior``.  The label that the text model is fitted on is never evidence
for the rows judged, unless the caller names it as a declaration.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import durable, in_slices, utf8

#: Labelled rows at most from which the text model is fitted.
FIT_ROWS = 2000
BUCKETS = 1 << 14
#: Effective observations a text may contribute at most, and share of trigrams that count as independent.
TEXT_SHARE, TEXT_MOST = 0.25, 200.0
MIN_POSTERIOR = 0.5
#: Bytes of host priors that are broadcast, and parts into which a host's rows are dealt where they are not.
BROADCAST_BYTES, HOST_PARTS = 64 << 20, 32

_LOW = np.array([c + 32 if 65 <= c <= 90 else c for c in range(256)], dtype=np.uint32)
_LETTER = np.array([c >= 128 or chr(c).isalpha() for c in range(256)])


def trigram_buckets(text: bytes) -> np.ndarray:
    """Hash buckets of the byte trigrams that hold at least two letters."""
    raw = np.frombuffer(b" " + text + b" ", dtype=np.uint8)
    letter = _LETTER[raw]
    low = np.where(letter, _LOW[raw], 32).astype(np.uint32)
    code = (low[:-2] << 16) | (low[1:-1] << 8) | low[2:]
    code = code[(letter[:-2].astype(np.int8) + letter[1:-1] + letter[2:]) >= 2]
    return ((code * np.uint32(2654435761)) >> np.uint32(32 - 14)).astype(np.int32)


def fit_text_model(labelled: DataFrame, label_col: str = "lang", text_col: str = "text", id_col: str = "doc_id", fit_rows: int = FIT_ROWS) -> dict[str, np.ndarray]:
    """Log probability of each trigram bucket by language.

    Fitted on the ``fit_rows`` rows with the smallest id hashes; counted on the
    executors, so that only one table of fixed size comes to the driver.
    """
    rows = labelled.where(F.col(label_col).isNotNull() & F.col(text_col).isNotNull()).select(
        F.col(label_col).cast("string").alias("label"), F.col(text_col).alias("text"), F.xxhash64(F.col(id_col), F.col(label_col), F.col(text_col)).alias("order")
    )
    # only hashes are sorted; rows that tie at the last one are equal rows
    least = rows.select("order").orderBy("order").limit(fit_rows).agg(F.max("order").alias("last"), F.count(F.lit(1)).alias("n"), F.array_agg("order").alias("all")).first()
    if not least["n"]:
        return {}
    tied = sum(x == least["last"] for x in least["all"])
    sample = rows.where(F.col("order") < least["last"]).union(rows.where(F.col("order") == least["last"]).limit(tied))

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        totals: dict[str, np.ndarray] = {}
        for batch in batches:
            for label, text in zip(batch.column(0).to_pylist(), utf8(batch.column(1)), strict=True):
                have = totals.setdefault(label, np.zeros(BUCKETS, dtype=np.int64))
                have += np.bincount(trigram_buckets(text), minlength=BUCKETS)
        yield pa.RecordBatch.from_arrays([pa.array(list(totals), pa.string()), pa.array([x.tobytes() for x in totals.values()], pa.binary())], names=["label", "counts"])

    totals: dict[str, np.ndarray] = {}
    for row in sample.select("label", "text").repartition(8).mapInArrow(count, "label string, counts binary").toLocalIterator():
        totals[row["label"]] = totals.get(row["label"], 0) + np.frombuffer(row["counts"], dtype=np.int64)
    return {k: np.log((v + 0.5) / (v.sum() + 0.5 * BUCKETS)) for k, v in sorted(totals.items())}


def text_scores(df: DataFrame, model: dict[str, np.ndarray], keep: list[str], text_col: str = "text") -> DataFrame:
    """Columns ``keep`` with letters (count of usable trigrams) and scores (tempered log likelihood by language)."""
    languages = list(model)
    shared = df.sparkSession.sparkContext.broadcast(np.stack([model[k] for k in languages], axis=1) if languages else np.zeros((BUCKETS, 0)))
    width, share, most = len(languages), TEXT_SHARE, TEXT_MOST
    source = df.select(*[F.col(c) for c in keep], F.col(text_col).alias("__text"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        table = np.ascontiguousarray(shared.value)
        for batch in batches:
            letters, scores = [], []
            for text in utf8(batch.column(len(keep))):
                total, n = np.zeros(width), 0
                counts = np.bincount(trigram_buckets(text), minlength=BUCKETS)
                n = int(counts.sum())
                if n and width:
                    total = counts @ table
                letters.append(n)
                scores.append((total / max(n, 1) * min(most, share * n)).tolist())
            yield pa.RecordBatch.from_arrays([*(batch.column(i) for i in range(len(keep))), pa.array(letters, pa.int64()), pa.array(scores, pa.list_(pa.float64()))], names=[*keep, "letters", "scores"])

    fields = ", ".join(f"`{c}` {t}" for c, t in source.dtypes[:-1])
    return source.mapInArrow(in_slices(run), f"{fields}, letters bigint, scores array<double>")


def _best(languages: list[str], scores: Column) -> Column:
    """Language of the largest score; the first in the alphabet wins ties."""
    return F.get(F.array(*[F.lit(x) for x in languages]), (F.array_position(scores, F.array_max(scores)) - 1).cast("int"))


def _joined(rows: DataFrame, table: DataFrame, key: str, width: int) -> DataFrame:
    """Rows with the table's columns for their ``key``.

    A table of checked size goes to the rows; beyond it, a key's rows are dealt to several tasks.
    """
    table = durable(table)
    held = table.agg(F.sum(F.length(key) + 16 + 8 * width)).first()[0] or 0
    if held <= BROADCAST_BYTES:
        return rows.join(F.broadcast(table), key, "left")
    parts = F.explode(F.sequence(F.lit(0).cast("bigint"), F.lit(HOST_PARTS - 1).cast("bigint")))
    return rows.withColumn("part", F.pmod(F.xxhash64("id", "letters"), F.lit(HOST_PARTS))).join(table.withColumn("part", parts), [key, "part"], "left").drop("part")


def identify(
    df: DataFrame,
    model: dict[str, np.ndarray],
    id_col: str = "doc_id",
    text_col: str = "text",
    declared_col: str | None = None,
    host_col: str | None = "source",
    url_col: str | None = None,
    min_posterior: float = MIN_POSTERIOR,
    strength: float = 20.0,
) -> DataFrame:
    """Per row: id_col, language, posterior, letters, accepted.

    ``declared_col`` holds declared languages (tags are cut to their first part), ``url_col`` addresses, which
    give the suffix and, where ``host_col`` is None, the host.  The tables of declared values, suffixes and hosts stay
    distributed and are joined back; corpus counts are one row.  Null evidence is left out of the product.  A null or
    letterless text has language null and is rejected; with an empty model
    every row is.  Repeated rows give repeated results, an empty table an empty one; other columns are ignored.
    """
    languages = list(model)
    width, none = len(languages), F.lit(None).cast("string")
    address = F.lower(F.regexp_extract(F.col(url_col), r"^[A-Za-z][A-Za-z0-9+.-]*://(?:[^/?#@]*@)?([^/?#:]+)", 1)) if url_col else none
    evidence = df.select(
        F.col(id_col).alias("id"), F.col(text_col).alias("text"),
        (F.regexp_extract(F.lower(F.col(declared_col).cast("string")), "^[a-z]{2,3}", 0) if declared_col else none).alias("declared"),
        (F.col(host_col).cast("string") if host_col else address).alias("host"),
        F.regexp_extract(address, r"\.([a-z]+)$", 1).alias("suffix"),
    ).withColumns({c: F.nullif(c, F.lit("")) for c in ("declared", "host", "suffix")})
    scored = text_scores(evidence, model, ["id", "declared", "host", "suffix"])
    if not languages:
        return scored.select(F.col("id").alias(id_col), F.lit(None).cast("string").alias("language"), F.lit(0.0).alias("posterior"), "letters", F.lit(False).alias("accepted"))
    scored = durable(scored.withColumn("guess", F.when(F.col("letters") > 0, _best(languages, F.col("scores")))))
    usable = scored.where(F.col("guess").isNotNull())
    each = [F.sum((F.col("guess") == x).cast("double")) for x in languages]
    totals = usable.agg(*each).first()
    corpus = [((n or 0) + 1.0) / (sum(x or 0 for x in totals) + width) for n in totals]
    base = F.array(*[F.lit(p) for p in corpus])

    def counts_by(column: str) -> DataFrame:
        return usable.where(F.col(column).isNotNull()).groupBy(column).agg(F.array(*each).alias("n"))

    fused = scored.withColumn("joint", F.col("scores"))
    for column, given in (("declared", declared_col), ("suffix", url_col)):
        if not given:
            continue
        # log p(value | language), additively smoothed over the values seen
        counts = counts_by(column)
        seen = counts.agg(F.count(F.lit(1)), *[F.sum(F.get("n", F.lit(i))) for i in range(width)]).first()
        table = counts.select(column, F.array(*[F.log((F.get("n", F.lit(i)) + 1.0) / ((seen[i + 1] or 0) + seen[0] + 1.0)) for i in range(width)]).alias("likely"))
        fused = _joined(fused, table, column, width)
        fused = fused.withColumn("joint", F.when(F.col("likely").isNull(), F.col("joint")).otherwise(F.zip_with("joint", "likely", lambda a, b: a + b))).drop("likely")

    def smoothed(counts: Column, above: Column) -> Column:
        total = F.aggregate(counts, F.lit(0.0), lambda a, x: a + x)
        return F.zip_with(counts, above, lambda n, p: (n + strength * p) / (total + strength))

    # a level that holds no more than the one below it is skipped, so that no row counts twice
    labels = F.split("host", r"\.")
    hosts = counts_by("host").withColumn("domain", F.when(F.size(labels) > 3, F.array_join(F.slice(labels, -3, 3), "."))).withColumn("site", F.when(F.size(labels) > 2, F.array_join(F.slice(labels, -2, 2), ".")))
    for level in ("domain", "site"):
        above = hosts.where(F.col(level).isNotNull()).groupBy(level).agg(F.array(*[F.sum(F.get("n", F.lit(i))) for i in range(width)]).alias(f"{level}_n"))
        hosts = hosts.join(above, level, "left")
    prior = base
    for counts in ("site_n", "domain_n", "n"):
        prior = F.when(F.col(counts).isNull(), prior).otherwise(smoothed(F.col(counts), prior))
    fused = _joined(fused, hosts.select("host", prior.alias("prior")), "host", width)
    fused = fused.withColumn("joint", F.zip_with("joint", F.coalesce("prior", base), lambda a, p: a + F.log(p)))
    top = F.array_max("joint")
    fused = fused.withColumn("posterior", 1 / F.aggregate(F.transform("joint", lambda x: F.exp(x - top)), F.lit(0.0), lambda a, x: a + x))
    known = F.col("letters") > 0
    return fused.select(
        F.col("id").alias(id_col),
        F.when(known, _best(languages, F.col("joint"))).alias("language"),
        F.when(known, F.col("posterior")).otherwise(F.lit(0.0)).alias("posterior"),
        "letters",
        (known & (F.col("posterior") >= min_posterior)).alias("accepted"),
    )


def page_evidence(pages: DataFrame) -> DataFrame:
    """(page_id, url, declared, text): the language that the markup declares, and the words between tags."""
    html = F.coalesce("html", F.lit(""))
    bare = F.regexp_replace(F.regexp_replace(html, r"(?is)<(script|style)\b.*?</\1\s*>|<!--.*?-->", " "), r"<[^>]*>", " ")
    declared = F.regexp_extract(html, r"(?i)<html\b[^>]*?\blang\s*=\s*[\"']?([A-Za-z-]+)", 1)
    return pages.select("page_id", "url", F.nullif(declared, F.lit("")).alias("declared"), bare.alias("text"))
