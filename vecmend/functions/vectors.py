"""Vector expressions on array columns, and their SQL functions."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

METRICS = ("cosine", "ip", "l2")


def as_double(v: Column) -> Column:
    return v.cast("array<double>")


def dot(a: Column, b: Column) -> Column:
    return F.aggregate(F.zip_with(as_double(a), as_double(b), lambda x, y: x * y), F.lit(0.0), lambda s, x: s + x)


def norm(v: Column) -> Column:
    return F.sqrt(dot(v, v))


def l2(a: Column, b: Column) -> Column:
    return F.sqrt(F.aggregate(F.zip_with(as_double(a), as_double(b), lambda x, y: (x - y) * (x - y)), F.lit(0.0), lambda s, x: s + x))


def distance(a: Column, b: Column, metric: str = "cosine") -> Column:
    """Cosine distance, inner product shifted to one less the product, or Euclidean distance."""
    if metric == "l2":
        return l2(a, b)
    if metric == "ip":
        return 1 - dot(a, b)
    return 1 - dot(a, b) / (norm(a) * norm(b))


def scale(v: Column, by: Column) -> Column:
    return F.transform(as_double(v), lambda x: x * by)


def _once(value: Column, body) -> Column:
    """``body`` of a value that is found once a row: Catalyst repeats an expression wherever it is named, and in a lambda for each element."""
    return F.get(F.transform(F.array(value), body), F.lit(0))


def normalise(v: Column) -> Column:
    return _once(as_double(v), lambda x: _once(norm(x), lambda n: F.when(n > 0, scale(x, 1 / n)).otherwise(x)))


def add(a: Column, b: Column) -> Column:
    return F.zip_with(as_double(a), as_double(b), lambda x, y: x + y)


def prefix(v: Column, m: int) -> Column:
    """First coordinates of a truncatable embedding, normalised again."""
    return normalise(F.slice(v, 1, m))


def combine(*parts: Column) -> Column:
    """Mean of the parts of a multi-part item, normalised."""
    total = parts[0]
    for p in parts[1:]:
        total = add(total, p)
    return normalise(scale(total, F.lit(1.0 / len(parts))))


def canonical(v: Column) -> Column:
    """Coordinates in millionths, comma-joined: the text that a query's key hashes."""
    return F.array_join(F.transform(as_double(v), lambda x: F.floor(x * 1000000 + 0.5).cast("string")), ",")


def key_md5(v: Column) -> Column:
    return F.md5(canonical(v))


def hash32(text: Column) -> Column:
    """Uniform 32-bit integer of a text, from its md5."""
    return F.conv(F.substring(F.md5(text), 1, 8), 16, 10).cast("bigint")


def uniform(text: Column) -> Column:
    """Uniform number in (0, 1) of a text."""
    return (hash32(text) + 0.5) / 4294967296.0


def assert_dim(df: DataFrame, column: str = "vec") -> int:
    """The one dimension of a vector column; raises if rows differ."""
    row = df.agg(F.min(F.size(column)).alias("lo"), F.max(F.size(column)).alias("hi")).first()
    if row["lo"] != row["hi"]:
        raise ValueError(f"vectors of {row['lo']} to {row['hi']} coordinates")
    return row["lo"] or 0


def register(spark: SparkSession) -> None:
    """SQL functions that Catalyst inlines: vec_dot, vec_norm, vec_l2, vec_cos and canon_key."""
    arg = "a ARRAY<DOUBLE>, b ARRAY<DOUBLE>"
    total = "aggregate(zip_with(a, b, (x, y) -> {}), 0.0D, (s, x) -> s + x)"
    for name, args, body in (
        ("vec_dot", arg, total.format("x * y")),
        ("vec_l2", arg, f"sqrt({total.format('(x - y) * (x - y)')})"),
        ("vec_norm", "a ARRAY<DOUBLE>", "sqrt(aggregate(a, 0.0D, (s, x) -> s + x * x))"),
        ("vec_cos", arg, "1 - vec_dot(a, b) / (vec_norm(a) * vec_norm(b))"),
        ("canon_key", "a ARRAY<DOUBLE>", "md5(array_join(transform(a, x -> cast(floor(x * 1000000 + 0.5) AS STRING)), ','))"),
    ):
        kind = "STRING" if name == "canon_key" else "DOUBLE"
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {name}({args}) RETURNS {kind} RETURN {body}")
