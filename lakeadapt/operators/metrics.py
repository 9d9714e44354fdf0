"""Accuracy measures over truth(column_id, type_name) joined with pred."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from lakeadapt.operators.joins import block_pairs, blocks, unpacked

#: Sums that a task holds before it passes them on.
HELD = 1 << 22


def _safe(a: Column, b: Column) -> Column:
    return F.when(b == 0, 0.0).otherwise(a / b)


def per_type(rows: DataFrame) -> DataFrame:
    """type_name, pred -> tp, fp, fn, precision, recall, f1, support per type of truth or prediction; 0 where undefined."""
    hit = F.col("type_name") == F.col("pred")
    as_truth = rows.select(F.col("type_name").alias("t"), hit.cast("int").alias("tp"), F.lit(0).alias("fp"), (~hit).cast("int").alias("fn"))
    as_pred = rows.where(~hit).select(F.col("pred").alias("t"), F.lit(0), F.lit(1), F.lit(0))
    sums = as_truth.union(as_pred).groupBy("t").agg(*[F.sum(c).alias(c) for c in ("tp", "fp", "fn")])
    return sums.select(
        F.col("t").alias("type_name"), "tp", "fp", "fn", (F.col("tp") + F.col("fn")).alias("support"),
        F.round(_safe(F.col("tp"), F.col("tp") + F.col("fp")), 6).alias("precision"),
        F.round(_safe(F.col("tp"), F.col("tp") + F.col("fn")), 6).alias("recall"),
        F.round(_safe(2 * F.col("tp"), 2 * F.col("tp") + F.col("fp") + F.col("fn")), 6).alias("f1"),
    )


def sw_f1(types: DataFrame) -> DataFrame:
    return types.agg(F.round(F.sum(F.col("f1") * F.col("support")) / F.sum("support"), 6).alias("sw_f1"))


def ma_f1(types: DataFrame, known: DataFrame, over: str = "union") -> DataFrame:
    """over: `union` of truth and valid predictions, types with `support`, or the whole `typeset`."""
    valid = types.join(F.broadcast(known.select("type_name")), "type_name", "left_semi")
    if over == "support":
        valid = valid.where("support > 0")
    if over == "typeset":
        valid = known.select("type_name").join(types, "type_name", "left").withColumn("f1", F.coalesce("f1", F.lit(0.0)))
    return valid.agg(F.round(F.avg("f1"), 6).alias("ma_f1"), F.count("*").alias("n_types"))


def ood_rate(rows: DataFrame, known: DataFrame) -> DataFrame:
    marked = rows.join(F.broadcast(known.select(F.col("type_name").alias("pred"), F.lit(1).alias("_in"))), "pred", "left")
    return marked.agg(F.round(F.avg(F.when(F.col("_in").isNull(), 1.0).otherwise(0.0)), 6).alias("ood_rate"), F.count("*").alias("n"))


def avg_gain(results: DataFrame, method: str, base: str) -> DataFrame:
    """method, budget, value: the mean over budgets of the relative gain (not the gain of the means)."""
    a = results.where(F.col("method") == method).select("transfer", "budget", F.col("value").alias("a"))
    b = results.where(F.col("method") == base).select("transfer", "budget", F.col("value").alias("b"))
    return a.join(b, ["transfer", "budget"]).groupBy("transfer").agg(F.round(F.avg(F.col("a") / F.col("b") - 1), 6).alias("gain"), F.count("*").alias("n_budgets"))


def judge_quality(judged: DataFrame) -> DataFrame:
    """Accuracy and abstention of the judge, the base rate of right labels, precision and recall of its `no`."""
    right, no = F.col("type_name") == F.col("pred"), F.col("decision") == "no"
    good = (right & (F.col("decision") == "yes")) | (~right & no)
    mean = lambda c: F.round(F.avg(c.cast("double")), 6)
    return judged.agg(
        F.count("*").alias("n"), mean(good).alias("accuracy"), mean(F.col("decision") == "unknown").alias("abstained"), mean(right).alias("base_rate"),
        F.round(_safe(F.count_if(no & ~right), F.count_if(no)), 6).alias("no_precision"),
        F.round(_safe(F.count_if(no & ~right), F.count_if(~right)), 6).alias("no_recall"),
    )


def silhouette_exact(rows: DataFrame, distance: str = "euclidean") -> DataFrame:
    """rows(column_id, cluster, hidden): mean silhouette from all pairs, at any number of rows; `silhouette_fast` is the cheap form
    for lakes. Blocks of rows meet blocks of rows as matrices, and a task passes on one sum a row and cluster. Ids are told
    apart by 64-bit hashes, clusters are whole numbers."""
    packed = blocks(rows.select(F.xxhash64("column_id").alias("id"), "hidden", F.array(F.col("cluster").cast("long")).alias("tags")))

    def far(q: np.ndarray, x: np.ndarray) -> np.ndarray:
        if distance != "euclidean":
            return 1 - q @ x.T / (np.linalg.norm(q, axis=1)[:, None] * np.linalg.norm(x, axis=1)[None, :])
        return np.sqrt(np.maximum((q * q).sum(1)[:, None] - 2 * q @ x.T + (x * x).sum(1)[None, :], 0))

    def summed(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: dict[tuple, list[np.ndarray]] = {}

        def given() -> pa.RecordBatch:
            parts = [(np.frombuffer(ids, np.int64), np.frombuffer(own, np.int64), np.full(len(n), c), d, n) for (ids, own, c), (d, n) in held.items()]
            every = [np.concatenate(x) for x in zip(*parts)]
            every = [x[every[4] > 0] for x in every]
            held.clear()
            return pa.RecordBatch.from_arrays([pa.array(x) for x in every], ["id", "own", "other", "d", "n"])

        for batch in batches:
            for pair in (row for n in range(len(batch)) for row in batch.slice(n, 1).to_pylist()):
                ids, _, q = unpacked(pair, "a")
                found, tags, x = unpacked(pair, "b")
                d, other = far(q, x), ids[:, None] != found[None, :]
                for c in np.unique(tags):
                    here = tags[:, 0] == c
                    new = np.where(other, d, 0)[:, here].sum(1), other[:, here].sum(1)
                    old = held.get((pair["a_ids"], pair["a_tags"], c))
                    held[pair["a_ids"], pair["a_tags"], c] = [a + b for a, b in zip(old, new)] if old else list(new)
            if sum(len(n) for _, n in held.values()) > HELD:
                yield given()
        if held:
            yield given()

    sums = block_pairs(packed, packed).mapInArrow(summed, "id long, own long, other long, d double, n long")
    means = sums.groupBy("id", "own", "other").agg((F.sum("d") / F.sum("n")).alias("d"))
    per = means.groupBy("id").agg(F.min(F.when(F.col("own") == F.col("other"), F.col("d"))).alias("x"), F.min(F.when(F.col("own") != F.col("other"), F.col("d"))).alias("y"))
    s = F.when(F.col("x").isNull() | F.col("y").isNull(), 0.0).otherwise((F.col("y") - F.col("x")) / F.greatest("x", "y"))
    return per.agg(F.round(F.avg(s), 6).alias("silhouette"), F.count("*").alias("n"))


def silhouette_fast(rows: DataFrame) -> float:
    """Squared-Euclidean silhouette from per-cluster sums, one pass."""
    from pyspark.ml.evaluation import ClusteringEvaluator
    from pyspark.ml.functions import array_to_vector

    ready = rows.select(F.col("cluster").cast("int").alias("prediction"), array_to_vector("hidden").alias("features"))
    return ClusteringEvaluator(distanceMeasure="squaredEuclidean").evaluate(ready)


def calibration(scored: DataFrame, bins: int = 10) -> DataFrame:
    """Mean confidence and accuracy per confidence bin."""
    at = F.least(F.floor(F.col("phi") * bins), F.lit(bins - 1)).cast("int")
    right = (F.col("pred") == F.col("type_name")).cast("double")
    return scored.groupBy(at.alias("bin")).agg(F.count("*").alias("n"), F.round(F.avg("phi"), 6).alias("confidence"), F.round(F.avg(right), 6).alias("accuracy"))


def purity(assigned: DataFrame, weak: DataFrame, scored: DataFrame) -> DataFrame:
    """Share of wrong columns in weak clusters and in the others: the assumption behind spreading flags."""
    marked = assigned.join(F.broadcast(weak.select("cluster").distinct().withColumn("weak", F.lit(True))), "cluster", "left").join(scored, "column_id")
    wrong = (F.col("pred") != F.col("type_name")).cast("double")
    return marked.groupBy(F.coalesce("weak", F.lit(False)).alias("weak")).agg(F.count("*").alias("n"), F.round(F.avg(wrong), 6).alias("wrong_share"))


def long_tail(types: DataFrame, buckets: int = 3) -> DataFrame:
    """F1 by support bucket, rarest first."""
    from pyspark.sql.window import Window

    ranked = types.where("support > 0").withColumn("bucket", F.ntile(buckets).over(Window.orderBy("support", "type_name")))  # one row per type
    return ranked.groupBy("bucket").agg(F.round(F.avg("f1"), 6).alias("ma_f1"), F.sum("support").alias("support"), F.count("*").alias("n_types"))


def labels_to_reach(results: DataFrame, threshold: float) -> DataFrame:
    return results.groupBy("transfer", "method").agg(F.min(F.when(F.col("value") > threshold, F.col("n_labels"))).alias("n_labels"))


def forgetting(scored: DataFrame, regions: DataFrame) -> DataFrame:
    """Per region of the truth: recall, and how often its types are predicted."""
    hit = (F.col("pred") == F.col("type_name")).cast("double")
    return scored.join(F.broadcast(regions), "type_name").groupBy("region").agg(F.count("*").alias("n"), F.round(F.avg(hit), 6).alias("recall"))
