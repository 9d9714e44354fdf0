"""From flagged columns to a batch of labels: clusters, pool, draw, ledger, replay, stopping."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from lakeadapt.functions.draws import draw, smallest
from lakeadapt.functions.vectors import mean_by, squared_distance


def lloyd(columns: DataFrame, k: int, rounds: int, seed: str) -> DataFrame:
    """columns(column_id, hidden) -> column_id, cluster. k x m numbers reach the driver each round, never the columns.

    The centres go to every row as one array of k vectors, and the nearest is found in the row: nothing is shuffled but the
    partial sums of k x m means.
    """
    spark = columns.sparkSession
    seeds = smallest(columns.select("column_id", "hidden"), k, seed, "column_id").collect()
    centres = dict(enumerate(r["hidden"] for r in sorted(seeds, key=lambda r: r["column_id"])))

    def assign() -> DataFrame:
        rows = spark.createDataFrame([([(c, list(v)) for c, v in centres.items()],)], "_centres array<struct<cluster:int,centre:array<double>>>")  # k x m numbers
        far = F.transform("_centres", lambda c: F.struct(F.round(squared_distance("hidden", c["centre"]), 9).alias("d"), c["cluster"].alias("cluster")))
        return columns.select("column_id", "hidden").crossJoin(F.broadcast(rows)).select("column_id", F.array_min(far)["cluster"].alias("cluster"), "hidden")

    for _ in range(rounds - 1):
        for r in mean_by(assign(), ["cluster"], "hidden", "centre").collect():
            centres[r["cluster"]] = r["centre"]  # an empty cluster keeps its centre
    return assign().select("column_id", "cluster")


def weak_pool(assigned: DataFrame, flagged_ids: DataFrame) -> DataFrame:
    """Columns of every cluster that holds a flagged one."""
    weak = assigned.join(F.broadcast(flagged_ids.select("column_id")), "column_id", "left_semi").select("cluster").distinct()
    return assigned.join(F.broadcast(weak), "cluster", "left_semi")


def batch(pool: DataFrame, used: DataFrame, size: int, left: int, seed: str) -> DataFrame:
    return smallest(pool.join(F.broadcast(used.select("column_id")), "column_id", "left_anti"), min(size, left), seed, "column_id")


def ledger(batches: DataFrame, budget: int) -> DataFrame:
    """iter, size -> spent, left, refused: a batch is paid only as far as the budget goes."""
    running = Window.orderBy("iter").rowsBetween(Window.unboundedPreceding, 0)  # one row per iteration
    wanted = F.sum("size").over(running)
    spent = F.least(wanted, F.lit(budget))
    before = F.least(wanted - F.col("size"), F.lit(budget))
    return batches.select("iter", "size", (spent - before).alias("paid"), spent.alias("spent"), (F.lit(budget) - spent).alias("left"))


def replay(trace: DataFrame) -> DataFrame:
    """iter -> how many columns its training set holds: all batches so far."""
    later = trace.select("iter").distinct().withColumnRenamed("iter", "at")
    return trace.join(F.broadcast(later), F.col("iter") <= F.col("at")).groupBy("at").agg(F.countDistinct("column_id").alias("n")).withColumnRenamed("at", "iter")


def stop_trace(losses: DataFrame, patience: int) -> DataFrame:
    """iter, loss -> improved, alpha, best, stopped. Only a strictly smaller loss counts."""
    w = Window.orderBy("iter")  # one row per iteration
    before = F.min("loss").over(w.rowsBetween(Window.unboundedPreceding, -1))
    marked = losses.withColumn("improved", before.isNull() | (F.col("loss") < before))
    last = F.last(F.when(F.col("improved"), F.col("iter")), ignorenulls=True).over(w.rowsBetween(Window.unboundedPreceding, 0))
    counted = marked.withColumn("best", last).withColumn("alpha", F.col("iter") - F.col("best"))
    first_stop = F.min(F.when(F.col("alpha") >= patience, F.col("iter"))).over(Window.partitionBy())
    return counted.withColumn("stopped", F.coalesce(F.col("iter") >= first_stop, F.lit(False)))


def random_tables(columns: DataFrame, n: int, seed: str) -> DataFrame:
    """All columns of n random tables."""
    tables = columns.select("table_id").distinct().orderBy(draw(seed, "table_id"), "table_id").limit(n)
    return columns.join(F.broadcast(tables), "table_id", "left_semi")
