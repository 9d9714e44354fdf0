"""Joins that SQL lacks or that need care at scale."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

def in_ranges(rows: DataFrame, ranges: DataFrame, value: str) -> DataFrame:
    """rows with lo <= value < hi of ranges(lo, hi, ...): an equi-join on powers of ten, then the exact test.

    A range is listed once per power of ten it touches, so no side is multiplied by more than the digits of its bounds.
    """
    power = lambda c: F.floor(F.log10(F.greatest(F.col(c) if isinstance(c, str) else c, F.lit(1.0)))).cast("int")
    listed = ranges.withColumn("_b", F.explode(F.sequence(power("lo"), power("hi"))))
    return rows.withColumn("_b", power(value)).join(F.broadcast(listed), "_b").where((F.col(value) >= F.col("lo")) & (F.col(value) < F.col("hi"))).drop("_b")


def as_of(left: DataFrame, right: DataFrame, key: str, at: str, carry: str, ident: str) -> DataFrame:
    """For each left row the `carry` of the last right row at or before it (same key; of equal times the largest carry).

    One union and one window: no row meets more than its own key's rows, and each key is read in time order once.
    """
    both = left.select(key, at, F.lit(1).alias("_side"), F.lit(None).cast(right.schema[carry].dataType).alias(carry), F.col(ident).alias("_id")).unionByName(
        right.select(key, at, F.lit(0).alias("_side"), carry, F.lit(None).cast(left.schema[ident].dataType).alias("_id"))
    )
    w = Window.partitionBy(key).orderBy(at, "_side", F.col(carry).asc_nulls_first()).rowsBetween(Window.unboundedPreceding, 0)
    return both.withColumn("_c", F.last(carry, ignorenulls=True).over(w)).where("_side = 1").select(F.col("_id").alias(ident), F.col("_c").alias(carry))


#: Vectors of a block: a task holds two blocks and their products.
BLOCK = 2048
NO_TAG = -(2**63)


def blocks(rows: DataFrame, size: int = BLOCK) -> DataFrame:
    """rows(id, hidden, tags) -> ids, tags, x: up to `size` vectors a row, as bytes. `tags` are longs that go with a vector; rows
    without a vector are left out."""

    def packed(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for at in range(0, len(batch), size):
                b = batch.slice(at, size)
                values = [b.column("id"), b.column("tags").flatten(), b.column("hidden").flatten()]
                yield pa.RecordBatch.from_arrays([pa.array([v.to_numpy(zero_copy_only=False).tobytes()], pa.binary()) for v in values], ["ids", "tags", "x"])

    ready = rows.select(F.col("id").cast("long"), F.col("hidden").cast("array<double>"), F.col("tags").cast("array<long>")).where("id IS NOT NULL AND hidden IS NOT NULL")
    return ready.mapInArrow(packed, "ids binary, tags binary, x binary")


def block_pairs(left: DataFrame, right: DataFrame) -> DataFrame:
    """Every block of `left` beside every block of `right`: blocks of `right` are dealt into slots, those of `left` go to each. So
    nothing but blocks is shuffled, and neither side has to fit into one machine."""
    parts = int(left.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    slots = F.sequence(F.lit(0), F.lit(parts - 1))
    a = left.select(*[F.col(c).alias(f"a_{c}") for c in left.columns], F.explode(slots).alias("slot")).repartition(parts, "slot")
    b = right.select(*[F.col(c).alias(f"b_{c}") for c in right.columns], F.expr(f"cast(pmod(xxhash64(ids), {parts}) AS int)").alias("slot")).repartition(parts, "slot")
    return a.hint("merge").join(b, "slot").drop("slot")


def unpacked(pair: dict, side: str) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    ids = np.frombuffer(pair[f"{side}_ids"], np.int64)
    return ids, np.frombuffer(pair[f"{side}_tags"], np.int64).reshape(len(ids), -1), np.frombuffer(pair[f"{side}_x"], np.float64).reshape(len(ids), -1)


def in_order(terms: np.ndarray) -> np.ndarray:
    """Sums over the last axis, added one after another as a sum over an array is."""
    return terms.cumsum(-1)[..., -1]


def nearest_in_blocks(pairs: DataFrame, k: int, closeness: Callable, exactly: Callable, allowed: Callable | None = None) -> DataFrame:
    """Pairs of blocks -> query, found, value, tag: of each query the k rows of the block with the largest value, ties to the smaller
    id. `closeness` values a block at once, up to 1e-8; `exactly` settles what that leaves open. None of them is its own neighbour."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for pair in (row for n in range(len(batch)) for row in batch.slice(n, 1).to_pylist()):
                ask, ask_tags, q = unpacked(pair, "a")
                ids, tags, x = unpacked(pair, "b")
                out = []
                for at in range(0, len(ask), 256):
                    some = slice(at, at + 256)
                    near = np.nan_to_num(closeness(q[some], x), nan=-np.inf)
                    open_ = ask[some, None] != ids[None, :]
                    if allowed is not None:
                        open_ &= allowed(ask_tags[some], tags)
                    near = np.where(open_, near, -np.inf)
                    least = -np.partition(-near, k - 1, axis=1)[:, k - 1] - 2e-8 if len(ids) > k else np.full(len(near), -np.inf)
                    for i in range(len(near)):
                        here = np.flatnonzero(open_[i] & (near[i] >= least[i]))
                        value = exactly(q[at + i], x[here])
                        best = np.lexsort((ids[here], -np.nan_to_num(value, nan=-np.inf)))[:k]
                        out.append((np.full(len(best), ask[at + i]), ids[here[best]], value[best], tags[here[best], 0]))
                yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(c)) for c in zip(*out)], ["query", "found", "value", "tag"])

    near = pairs.mapInArrow(run, "query long, found long, value double, tag long")
    w = Window.partitionBy("query").orderBy(F.nanvl("value", F.lit(float("-inf"))).desc(), "found")
    return near.withColumn("k", F.row_number().over(w)).where(F.col("k") <= k)


def _cosines(q: np.ndarray, x: np.ndarray) -> np.ndarray:
    with np.errstate(divide="ignore", invalid="ignore"):
        return q @ x.T / (np.linalg.norm(q, axis=1)[:, None] * np.linalg.norm(x, axis=1)[None, :])


def _cosine(q: np.ndarray, x: np.ndarray) -> np.ndarray:
    with np.errstate(divide="ignore", invalid="ignore"):
        return np.round(in_order(q * x) / (np.sqrt(in_order(q * q)) * np.sqrt(in_order(x * x))), 9)


def knn(queries: DataFrame, rows: DataFrame, k: int) -> DataFrame:
    """vec_id, hidden: the k nearest by cosine of each query, exactly; a stated query set against all rows. Blocks of queries
    meet blocks of rows as matrices, and a pair of blocks passes on k rows a query."""
    label = F.coalesce(F.col("label").cast("long"), F.lit(NO_TAG)) if "label" in rows.columns else F.lit(0)
    packed = [blocks(df.select(F.col("vec_id").alias("id"), "hidden", F.array(tag).alias("tags"))) for df, tag in ((queries, F.lit(0)), (rows, label))]
    near = nearest_in_blocks(block_pairs(*packed), k, _cosines, _cosine)
    named = [F.nullif("tag", F.lit(NO_TAG)).alias("label")] if "label" in rows.columns else []
    return near.select("query", "found", "k", F.col("value").alias("sim"), *named)


def knn_lsh(queries: DataFrame, rows: DataFrame, k: int, bucket: float = 0.9, tables: int = 8, most: float = 1.4) -> DataFrame:
    """The k nearest of those that share a bucket of random projections with the query and lie nearer than `most`. The
    codes travel with the blocks and are compared there: with wide buckets nearly all pairs share one, and listing them
    table by table fills the disks."""
    from pyspark.ml.feature import BucketedRandomProjectionLSH
    from pyspark.ml.functions import array_to_vector, vector_to_array

    model = BucketedRandomProjectionLSH(inputCol="v", outputCol="h", bucketLength=bucket, numHashTables=tables, seed=3).fit(rows.select(array_to_vector("hidden").alias("v")))

    def coded(df: DataFrame) -> DataFrame:
        hashed = model.transform(df.where("hidden IS NOT NULL").select("vec_id", "hidden", array_to_vector("hidden").alias("v")))
        return blocks(hashed.select(F.col("vec_id").alias("id"), "hidden", F.transform("h", lambda v: vector_to_array(v)[0].cast("long")).alias("tags")))

    def share(a: np.ndarray, b: np.ndarray) -> np.ndarray:
        return np.logical_or.reduce([a[:, t, None] == b[None, :, t] for t in range(a.shape[1])])

    def nearness(q: np.ndarray, x: np.ndarray) -> np.ndarray:
        return 2 * q @ x.T - (q * q).sum(1)[:, None] - (x * x).sum(1)[None, :]

    near = nearest_in_blocks(block_pairs(coded(queries), coded(rows)), k, nearness, lambda q, x: -in_order((q - x) ** 2), share)
    return near.where(F.sqrt(-F.col("value")) < most).select("query", "found", "k")
