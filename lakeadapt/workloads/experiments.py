"""The paper's experiment tables, re-expressed on the lakes of the given tables."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from lakeadapt.baselines import methods
from lakeadapt.operators.adapt import Config
from lakeadapt.operators.cost import UNIT
from lakeadapt.sources import catalog
from lakeadapt.workloads.grid import Run, run_grid

LOW = (5, 10, 20, 30)
SHARES = (0.25, 0.5, 1.0)
BASELINES = ("feature_fusion", "row_col", "plain_J", "plain_C", "plain_R")
FULL = ("full_J", "full_C", "full_R")
VARIANTS = ("no_judge_J", "strong_judge_J")
K_FACTORS = (0.0, 0.5, 1.0, 1.5, 2.0)


def low(workload: str, transfer: str, methods: tuple[str, ...], points: tuple[int, ...] = LOW, seeds: tuple[int, ...] = (1,)) -> list[Run]:
    return [Run(workload, transfer, m, f"low{LOW.index(p) + 1}", iterations=p, seed=s) for m in methods for p in points for s in seeds]


def high(workload: str, transfer: str, methods: tuple[str, ...], shares: tuple[float, ...] = SHARES, seeds: tuple[int, ...] = (1,)) -> list[Run]:
    return [Run(workload, transfer, m, f"{int(100 * x)}%", share=x, seed=s) for m in methods for x in shares for s in seeds]


def runs(name: str, seeds: tuple[int, ...] = (1,), points: tuple[int, ...] = LOW, shares: tuple[float, ...] = SHARES) -> list[Run]:
    """The configurations of a workload."""
    every = BASELINES + FULL + VARIANTS
    both = ("TX1", "TX2")
    if name in ("W1", "W2"):
        return low(name, both[name == "W2"], every, points, seeds)
    if name == "W3":
        return high(name, "TX3", BASELINES + FULL, (0.1, *shares), seeds)
    if name == "W4":
        return [r for tx in both for r in high(name, tx, every, shares, seeds)]
    if name == "W5":
        return [r for tx in both for r in low(name, tx, ("full_J", "no_judge_J", "random_J"), points, seeds)]
    if name == "W6":
        return [r for tx in both for r in low(name, tx, ("full_J", "strong_judge_J", "perfect_judge_J"), points, seeds)]
    if name == "W7":
        return [Run(name, tx, m, "none") for tx in both for m in methods.ANNOTATORS] + [r for tx in both for r in low(name, tx, ("full_J",), points[-1:], seeds)]
    if name == "W8":
        return [r for tx in both for r in low(name, tx, ("generator",), points, seeds) + high(name, tx, ("generator",), shares, seeds)]
    if name == "W9":
        return [Run(name, tx, m, "100%", share=1.0, seed=s) for tx in both for m in (*FULL, "generator") for s in seeds]
    if name == "W11":
        return [Run(name, tx, f"{m}_{b}", "warm-up", seed=s) for tx in both for b in "JCR" for m in ("warm_random_head", "warm_transplant") for s in seeds]
    if name == "W12":
        return [Run(name, tx, "strong_judge_J", f"low{LOW.index(n) + 1}, k x {f}", iterations=n, k_factor=f, seed=s) for tx in both for f in K_FACTORS for n in points for s in seeds]
    if name == "W14":
        return low(name, "TX1", ("weak_judge_W", "plain_W"), points, seeds) + high(name, "TX1", ("weak_judge_W",), shares, seeds)
    if name == "W16":
        return [Run(name, tx, m, f"n={n}", labels=n, iterations=50, seed=s) for tx in both for m in ("full_J", "plain_J") for n in (40, 60, 100, 150, 200, 300, 400) for s in seeds]
    if name == "W18":
        return [Run(name, tx, m, "none", seed=s) for tx in ("TX1", "TX2", "TX3") for m in ("source_test_J", "direct_J") for s in seeds]
    if name == "V10":
        return [Run(name, tx, "full_J", f"delta {x}", iterations=points[-1], delta=x, seed=s) for tx in both for x in (0.8, 0.9, 0.95) for s in seeds]
    if name == "V30":
        return [r for tx in both for r in low(name, tx, ("full_J", "knowledge_judge_J"), points, seeds)]
    if name == "V13":
        return low(name, "TX1", ("full_J", "no_replay_J"), points, seeds)
    if name == "V14":
        return [Run(name, tx, "full_J", space, iterations=points[-1], space=space, seed=s) for tx in both for space in ("hidden", "logits") for s in seeds]
    raise ValueError(f"no workload is named {name}")


def run(name: str, spark: SparkSession, sf_dir: str, **grid) -> DataFrame:
    return run_grid(spark, sf_dir, runs(name, **grid))


def families(spark: SparkSession, sf_dir: str) -> DataFrame:
    """W22: method families side by side: F1 on the source and after the move, what is lost, out-of-set share."""
    made = [("source_test_J", "none"), ("direct_J", "none"), ("plain_J", "low2"), ("prompted_newest", "none"), ("generator", "low2"), ("full_J", "low2")]
    rows = run_grid(spark, sf_dir, [Run("W22", "TX1", m, b, iterations=10) for m, b in made])
    start = rows.where("method = 'source_test_J'").select(F.col("sw_f1").alias("source_f1"))
    return rows.crossJoin(F.broadcast(start)).select(
        "method", "n_labels", *[F.round(c, 4).alias(c) for c in ("sw_f1", "ma_f1", "ood")], F.round(F.col("source_f1") - F.col("sw_f1"), 4).alias("lost")
    )


def drops(spark: SparkSession, sf_dir: str) -> DataFrame:
    """W18: accuracy on the source's held-out tables, after the move, and the drop."""
    rows = run("W18", spark, sf_dir)
    return rows.groupBy("transfer").agg(
        F.round(F.avg(F.when(F.col("method") == "source_test_J", F.col("sw_f1"))), 4).alias("source_f1"), F.round(F.avg(F.when(F.col("method") == "direct_J", F.col("sw_f1"))), 4).alias("target_f1")
    ).withColumn("drop", F.round(F.col("source_f1") - F.col("target_f1"), 4))


def gain_table(results: DataFrame, methods_: tuple[str, ...] = FULL) -> DataFrame:
    """Mean relative gain of each method over the plain backbone of its letter, on one's own results."""
    parts = [gains(results, f"plain_{m[-1]}", m).withColumn("method", F.lit(m)) for m in methods_]
    return reduce(DataFrame.unionByName, parts)


def labels_needed(spark: SparkSession, sf_dir: str, thresholds: tuple[float, ...] = (0.6, 0.9)) -> DataFrame:
    """W16: the least number of labels with which each method passes the published threshold, and one that these easier lakes need."""
    from lakeadapt.operators.metrics import labels_to_reach

    rows = spark.createDataFrame(run("W16", spark, sf_dir).withColumnRenamed("sw_f1", "value").toPandas())  # one row a configuration
    return reduce(DataFrame.unionByName, [labels_to_reach(rows, x).withColumn("threshold", F.lit(x)) for x in thresholds])


def overheads(spark: SparkSession, sf_dir: str) -> DataFrame:
    """W9: judge calls of own runs, with seconds and money by the published unit costs, iterations, columns trained on per second
    (batches replayed in all epochs, over the time of the run) and what the tuned generator manages."""
    from lakeadapt.operators.cost import prompt_dollars

    rows = run("W9", spark, sf_dir)
    n_types = F.when(F.col("transfer") == "TX1", len(catalog.TX1.target)).otherwise(len(catalog.TX2.target))
    usd = F.lit(prompt_dollars(0)) + n_types * (prompt_dollars(1) - prompt_dollars(0))
    epochs = F.lit(Config().epochs)
    trained = epochs * (F.col("iterations") + 1) * F.col("n_labels") / 2
    rows = rows.withColumn("rate", trained / F.col("seconds"))
    base = rows.where("method = 'generator'").groupBy("transfer").agg((F.avg("n_labels") / F.avg("seconds")).alias("_base"))
    return rows.where("method <> 'generator'").join(F.broadcast(base), "transfer").select(
        "transfer", "method", "n_labels", "judge_calls", "iterations", F.round(F.col("judge_calls") * UNIT["V"][2], 1).alias("judge_seconds"),
        F.round(F.col("judge_calls") * usd, 4).alias("judge_usd"), F.round("rate", 1).alias("columns_per_second"), F.round(F.col("rate") / F.col("_base"), 2).alias("times_generator"),
    )


def gains(results: DataFrame, base: str, method: str) -> DataFrame:
    """Mean relative gain over the budgets of a result table."""
    from lakeadapt.operators.metrics import avg_gain

    means = results.groupBy("transfer", "method", "budget").agg(F.avg("sw_f1").alias("value"))
    return avg_gain(means, method, base)


def seed_variance(spark: SparkSession, sf_dir: str, name: str = "W5", seeds: tuple[int, ...] = (1, 2, 3), **grid) -> DataFrame:
    """Mean and standard deviation over seeds of a workload's results."""
    rows = run(name, spark, sf_dir, seeds=seeds, **grid)
    return rows.groupBy("workload", "transfer", "method", "budget").agg(
        F.count("*").alias("seeds"), F.round(F.avg("n_labels"), 1).alias("n_labels"), F.round(F.avg("sw_f1"), 4).alias("sw_f1"), F.round(F.stddev_samp("sw_f1"), 4).alias("sw_sd"),
        F.round(F.avg("ma_f1"), 4).alias("ma_f1"), F.round(F.stddev_samp("ma_f1"), 4).alias("ma_sd"), F.round(F.avg("ood"), 4).alias("ood"), F.round(F.avg("judge_calls"), 1).alias("judge_calls"),
    )
