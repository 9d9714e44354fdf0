"""Reproducible shuffle into shards: a Feistel permutation with cycle walking over dense row numbers.

Rows are numbered from 0 by (doc_id, text checksum, size), nulls first. The permutation works on a grid of a x b >= n
cells, about the square root of n on each side; images outside 0..n-1 are walked on until they fall inside, so it is a
bijection of 0..n-1. Position p goes to shard p mod k, slot p div k: counts differ by one at most, slots have no gap,
and anyone who knows n, seed and k can compute the place of row i without the data, or invert it.

Defined cases: null texts have size 8 and checksum 0; rows that repeat are interchangeable; an empty table gives no
rows; fewer rows than shards leave the last shards empty. Equal texts get places of their own.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from lakeadapt.llm.common import number_rows, of_type, utf8_bytes

#: A prime below 2**31: products of two residues stay inside 64 bits.
PRIME = 2147483647
ROUNDS = 6


def round_keys(seed: int) -> list[tuple[int, int, int]]:
    """Multiplier, offset and shift of each round, by a Lehmer sequence from the seed."""
    x, keys = seed % (PRIME - 2) + 1, []
    for _ in range(ROUNDS):
        triple = []
        for _ in range(3):
            x = x * 48271 % PRIME
            triple.append(x)
        keys.append(tuple(triple))
    return keys


def grid(n: int) -> tuple[int, int]:
    a = max(1, int(np.ceil(np.sqrt(n))))
    return a, max(1, -(-n // a))


def _once(x: np.ndarray, a: int, b: int, keys) -> np.ndarray:
    left, right = x // b, x % b
    for k, (mul, add, shift) in enumerate(keys):
        src = right if k % 2 == 0 else left
        f = (src * mul + add) % PRIME * ((src + shift) % PRIME) % PRIME
        if k % 2 == 0:
            left = (left + f) % a
        else:
            right = (right + f) % b
    return left * b + right


def permute(x: np.ndarray, n: int, seed: int) -> np.ndarray:
    """The image of each row number in 0..n-1."""
    (a, b), keys = grid(n), round_keys(seed)
    out = _once(x.astype(np.int64), a, b, keys)
    while (outside := out >= n).any():
        out[outside] = _once(out[outside], a, b, keys)
    return out


def shard_rows(docs: DataFrame, shards: int = 24, seed: int = 7) -> DataFrame:
    """documents -> doc_id, size, text_crc32, law, shard, slot, grown_shard, row_no."""
    docs = of_type(docs, {"doc_id": "long", "text": "string"})
    slim = docs.select(
        "doc_id",
        (utf8_bytes("text") + 8).alias("size"),
        F.crc32(F.encode(F.coalesce("text", F.lit("")), "UTF-8")).alias("text_crc32"),
    )
    numbered, n = number_rows(slim, ["doc_id", "text_crc32", "size"], "row_no")

    @F.pandas_udf("long")
    def place(row_no: pd.Series) -> pd.Series:
        return pd.Series(permute(row_no.to_numpy(), n, seed))

    return numbered.withColumn("_p", place("row_no")).select(
        "doc_id",
        "size",
        "text_crc32",
        F.lit("rows").alias("law"),
        (F.col("_p") % shards).cast("int").alias("shard"),
        F.expr(f"_p div {shards}").alias("slot"),
        F.lit(None).cast("int").alias("grown_shard"),
        "row_no",
    )


def op8_feistel_shards(spark: SparkSession, sf_dir: str) -> DataFrame:
    return shard_rows(spark.read.parquet(f"{sf_dir}/documents.parquet"))
