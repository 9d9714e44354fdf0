"""Baselines as plans: a prompted annotator with words of its own, and the nearest labelled example."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from lakeadapt.functions.draws import draw
from lakeadapt.operators.joins import knn
from lakeadapt.sources.catalog import KNOWLEDGE


def own_words(columns: DataFrame, words: int = 25) -> DataFrame:
    """Reads the cells: the first pattern of the knowledge table that fits names the type, `words` % of the types in words of
    its own; nothing fits: an answer outside any set."""
    fits = []
    for name, pattern, least in KNOWLEDGE:
        said = F.when(draw("word", F.lit(name)) % 100 < words, name.upper()).otherwise(name)
        share = F.size(F.filter("cells", _matching(pattern))) / F.greatest(F.size("cells"), F.lit(1))
        fits.append(F.when((F.size("cells") > 0) & (share >= least), said))
    return columns.select("column_id", F.coalesce(*fits, F.lit("unlisted")).alias("pred"))


def _matching(pattern: str):
    return lambda c: F.rlike(c, F.lit(pattern))


def nearest_answer(queries: DataFrame, examples: DataFrame, floor: float) -> DataFrame:
    """The label of the most similar example; below the floor an answer outside the set."""
    near = knn(queries, examples, 1)
    return near.select("query", F.when(F.col("sim") >= floor, F.concat(F.lit("t"), "label")).otherwise("unlisted").alias("pred"))
