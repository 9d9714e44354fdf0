"""Output layers as tables (type_name, w array<double>): prototypes, realignment, scoring."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from lakeadapt.functions.draws import uniform
from lakeadapt.functions.vectors import dot, mean_by, phi


def prototypes(labelled: DataFrame) -> DataFrame:
    """labelled(type_name, hidden) -> head: the mean vector of each type."""
    return mean_by(labelled, ["type_name"], "hidden", "w")


def fresh(types: DataFrame, width: int, seed: int, scale: float = 0.1) -> DataFrame:
    """A random head: every weight is a function of (seed, type, dimension)."""
    dims = types.select("type_name", F.explode(F.sequence(F.lit(0), F.lit(width - 1))).alias("dim"))
    drawn = dims.withColumn("x", (uniform(str(seed), "type_name", "dim") * 2 - 1) * scale)
    return drawn.groupBy("type_name").agg(F.transform(F.array_sort(F.collect_list(F.struct("dim", "x"))), lambda e: e["x"]).alias("w"))


def realign(head: DataFrame, target_types: DataFrame, width: int, seed: int) -> DataFrame:
    """Target head: a shared type keeps its source vector, an unseen one starts at random, a source-only one is left behind."""
    kept = target_types.join(F.broadcast(head), "type_name", "left")
    return kept.join(F.broadcast(fresh(target_types, width, seed).withColumnRenamed("w", "_new")), "type_name").select(
        "type_name", F.coalesce("w", "_new").alias("w"), F.col("w").isNotNull().alias("copied")
    )


def realign_report(head: DataFrame, target_types: DataFrame) -> DataFrame:
    both = head.select("type_name", F.lit(1).alias("s")).join(target_types.select("type_name", F.lit(1).alias("t")), "type_name", "full_outer")
    return both.agg(
        F.count_if(F.col("s").isNotNull() & F.col("t").isNotNull()).alias("copied"),
        F.count_if(F.col("s").isNull()).alias("fresh"),
        F.count_if(F.col("t").isNull()).alias("released"),
    )


def predict(columns: DataFrame, head: DataFrame, scale: float) -> DataFrame:
    """columns(column_id, hidden, ...) -> with pred and phi. The head is n_t rows and goes to every task."""
    rows = F.broadcast(head.agg(F.array_sort(F.collect_list(F.struct("type_name", "w"))).alias("_head")))
    scored = columns.crossJoin(rows).withColumn("_s", F.transform("_head", lambda h: F.struct(F.round(dot("hidden", h["w"]) * scale, 9).alias("v"), h["type_name"].alias("t"))))
    top = F.array_max(F.transform("_s", lambda e: e["v"]))
    best = F.array_min(F.transform(F.filter("_s", lambda e: e["v"] == top), lambda e: e["t"]))
    return scored.withColumn("pred", best).withColumn("phi", phi(F.transform("_s", lambda e: e["v"]))).drop("_head", "_s")
