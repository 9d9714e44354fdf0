"""Vector arithmetic on arrays of doubles."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def dot(a: str | Column, b: str | Column) -> Column:
    return F.aggregate(F.zip_with(a, b, lambda x, y: x * y), F.lit(0.0), lambda s, x: s + x)


def squared_distance(a: str | Column, b: str | Column) -> Column:
    return F.aggregate(F.zip_with(a, b, lambda x, y: (x - y) * (x - y)), F.lit(0.0), lambda s, x: s + x)


def norm(a: str | Column) -> Column:
    return F.sqrt(dot(a, a))


def cosine(a: str | Column, b: str | Column) -> Column:
    return dot(a, b) / (norm(a) * norm(b))


def mean_by(df: DataFrame, keys: list[str], vector: str, out: str) -> DataFrame:
    """Mean vector of each group: partial sums per dimension, so what is shuffled is groups x dimensions."""
    long = df.select(*keys, F.posexplode(vector).alias("dim", "x")).groupBy(*keys, "dim").agg(F.avg("x").alias("x"))
    return long.groupBy(*keys).agg(F.transform(F.array_sort(F.collect_list(F.struct("dim", "x"))), lambda e: e["x"]).alias(out))


def phi(logits: str | Column) -> Column:
    """Largest softmax score, stabilised by the largest logit."""
    logits = F.col(logits) if isinstance(logits, str) else logits
    return 1.0 / F.aggregate(logits, F.lit(0.0), lambda s, v: s + F.exp(v - F.array_max(logits)))
