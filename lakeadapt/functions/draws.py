"""Seeded draws as pure expressions of the row: a retried task, another plan and another engine give the same."""

from __future__ import annotations

import hashlib

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def draw(seed: str, *columns: str | Column) -> Column:
    """A whole number below 2**32 from the seed and the columns."""
    parts = [F.col(c) if isinstance(c, str) else c for c in columns]
    return F.conv(F.substring(F.md5(F.concat_ws(":", F.lit(seed), *[p.cast("string") for p in parts])), 1, 8), 16, 10).cast("long")


def uniform(seed: str, *columns: str | Column) -> Column:
    return draw(seed, *columns) / F.lit(4294967296.0)


def smallest(df: DataFrame, n: int, seed: str, key: str) -> DataFrame:
    """n rows drawn without replacement: those of the smallest draw (a top-k, not a sort)."""
    return df.orderBy(draw(seed, key), key).limit(n)


def sql_draw(seed: str, *columns: str) -> str:
    text = " || ':' || ".join([f"'{seed}'", *[f"CAST({c} AS VARCHAR)" for c in columns]])
    return f"CAST('0x' || substr(md5({text}), 1, 8) AS BIGINT)"


def rank(seed: str, ident: str) -> int:
    """`draw` of one id, in Python."""
    return int(hashlib.md5(f"{seed}:{ident}".encode()).hexdigest()[:8], 16)


def drawn(ids: list[str], n: int, seed: str) -> list[str]:
    """`smallest` of a list of ids."""
    return sorted(ids, key=lambda i: (rank(seed, i), i))[: max(0, n)]
