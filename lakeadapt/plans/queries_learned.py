"""Queries of the learned part: adaptation in Spark, variants, baselines and the experiment tables with their whole budget
grids, one seed each; `report.py` adds seeds. They are checked by invariants in tests, not by SQL."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from lakeadapt.functions.features import WIDTH, encode
from lakeadapt.operators.adapt import Config, Result, SparkLake, adapt
from lakeadapt.operators.typer import Typer, fit_blocks, realign, score
from lakeadapt.session import REGISTRY
from lakeadapt.sources import catalog, lake
from lakeadapt.sources.store import written
from lakeadapt.workloads import checks, experiments, mechanism

#: The published settings, with a judge that reads cells.
WHOLE = Config(judge="knowledge")


def prepared(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, DataFrame]:
    """TX1 as written tables: source and target columns with features. Nobody reads source columns of other tables than the
    star's, so these are not made."""
    cols = written(encode(lake.build(spark, sf_dir, sources=catalog.STAR), packed=True), "tx1", ("lake", "split"))
    return cols.where("lake = 'source'"), cols.where("lake = 'target'")


def source_typer(source: DataFrame) -> Typer:
    """Trained on all source columns, in blocks of one size at every size of the lake."""
    return fit_blocks(source, Typer.new(catalog.TX1.source, WIDTH, 1), most=12)


def adapted(spark: SparkSession, sf_dir: str, cfg: Config) -> tuple[Result, DataFrame]:
    source, target = prepared(spark, sf_dir)
    start = realign(source_typer(source), catalog.TX1.target, 1)
    return adapt(SparkLake(target), start, cfg), target


def adapt_full(spark: SparkSession, sf_dir: str, cfg: Config = WHOLE) -> DataFrame:
    """The whole method on TX1 in Spark: per type of the test split, support and F1 of the adapted typer."""
    from lakeadapt.operators.metrics import per_type

    result, target = adapted(spark, sf_dir, cfg)
    test = target.where("split = 'test'")
    pred = score(test, result.typer, with_hidden=False).join(test.select("column_id", "type_name"), "column_id")
    return per_type(pred).withColumn("spent", F.lit(result.spent)).withColumn("judge_calls", F.lit(result.judge_calls))


REGISTRY.add("adapt_full", adapt_full)
REGISTRY.add("adapt_trace", lambda s, d: s.createDataFrame(adapted(s, d, WHOLE)[0].trace, "iter int, stage string, column_id string"))
for _name in ("W1", "W2", "W3", "W4", "W5", "W6", "W7", "W8", "W11", "W12", "W14", "V10", "V13", "V14", "V30"):
    REGISTRY.add(f"{_name.lower()}_results", lambda s, d, n=_name: experiments.run(n, s, d))
REGISTRY.add("w9_results", experiments.overheads)
REGISTRY.add("w16_results", experiments.labels_needed)
REGISTRY.add("w18_results", experiments.drops)
REGISTRY.add("w1_gain", lambda s, d: experiments.gain_table(experiments.run("W1", s, d)))
REGISTRY.add("w2_gain", lambda s, d: experiments.gain_table(experiments.run("W2", s, d)))
REGISTRY.add("w10_results", mechanism.labelling_and_judging)
REGISTRY.add("w15_results", mechanism.threshold_choice)
REGISTRY.add("trace_measures", mechanism.trace_measures)
REGISTRY.add("seed_variance", lambda s, d: experiments.seed_variance(s, d))
REGISTRY.add("w22_families", experiments.families)
REGISTRY.add("w13_results", checks.silhouette_scores)
REGISTRY.add("w13_silhouette_k", checks.silhouette_k)
REGISTRY.add("w19_worked_example", checks.worked_example)
REGISTRY.add("w20_complexity", checks.complexity)
REGISTRY.add("w21_extrapolation", checks.extrapolation)
REGISTRY.add("w23_documents", checks.documents_as_units)
