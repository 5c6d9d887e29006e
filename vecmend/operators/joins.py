"""Joins by time: the latest row before, and all rows within a span."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def as_of(left: DataFrame, right: DataFrame, by: str, at: str, value: str, alias: str) -> DataFrame:
    """Left rows with ``alias``, the value of the latest right row of the same key at or before their time; null where none is.

    Both sides are sorted once by key and time, in place of a range join; of right rows at one time the greatest value counts.
    """
    latest = right.groupBy(by, at).agg(F.max(value).alias(alias)).select(by, at, alias, F.lit(0).alias("__side"))
    rows = left.withColumn(alias, F.lit(None).cast(dict(latest.dtypes)[alias])).withColumn("__side", F.lit(1))
    order = Window.partitionBy(by).orderBy(at, "__side").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    both = rows.unionByName(latest, allowMissingColumns=True)
    return both.withColumn(alias, F.last(alias, ignorenulls=True).over(order)).where("__side = 1").drop("__side")


def within_span(left: DataFrame, right: DataFrame, by: str, at: str, seconds: int) -> DataFrame:
    """Pairs of rows of one key whose right time lies in (left time, left time + seconds]; right columns get the suffix ``_r``.

    Time is cut into blocks of that length, so that a left row meets two blocks by an equi-join.
    """
    block = lambda c: F.floor(F.unix_seconds(F.col(c).cast("timestamp")) / seconds)
    one = left.withColumn("__block", F.explode(F.array(block(at), block(at) + 1)))
    two = right.withColumn("__block", block(at))
    two = two.select(*[F.col(c).alias(c if c in (by, "__block") else f"{c}_r") for c in two.columns])
    gap = F.unix_micros(F.col(f"{at}_r").cast("timestamp")) - F.unix_micros(F.col(at).cast("timestamp"))
    return one.join(two, [by, "__block"]).where((gap > 0) & (gap <= seconds * 1_000_000)).drop("__block")
