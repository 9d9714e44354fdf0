"""Where the typer's competence ends: probe, doubt gate, judge, flags."""

from __future__ import annotations

from collections.abc import Callable, Iterable, Iterator

import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from lakeadapt.functions.draws import smallest, uniform
from lakeadapt.sources.catalog import KNOWLEDGE
from lakeadapt.sources.lake import for_prompt

ANSWERS = ("yes", "no", "unknown")


def probe(columns: DataFrame, seen: DataFrame, size: int, seed: str) -> DataFrame:
    """Random columns that no earlier probe or batch has touched."""
    return smallest(columns.join(F.broadcast(seen.select("column_id").distinct()), "column_id", "left_anti"), size, seed, "column_id")


def gate(scored: DataFrame, delta: float = 0.9) -> DataFrame:
    return scored.where(F.col("phi") < delta)


def delta_sweep(scored: DataFrame, grid: Iterable[float], n: int, seed: str) -> DataFrame:
    """Per threshold: how often `phi < delta` is the same as `wrong`, on n held-out columns."""
    held = smallest(scored, n, seed, "column_id")
    grid_rows = F.explode(F.array(*[F.lit(float(d)) for d in grid]))
    right = ((F.col("phi") < F.col("delta")) == (F.col("pred") != F.col("type_name"))).cast("double")
    return held.withColumn("delta", grid_rows).groupBy("delta").agg(F.round(F.avg(right), 6).alias("accuracy"), F.count_if(F.col("phi") < F.col("delta")).alias("gated"))


def prompt(types: Iterable[str], cells: str, label: str) -> Column:
    """Instruction, type list, as many cells as a prompt holds, proposed type."""
    listed = ", ".join(sorted(types))
    return F.concat(
        F.lit(f"You check a proposed type for a table column. Reply with one word: yes, no or unknown.\nTypes: {listed}\nValues: "),
        F.array_join(for_prompt(cells), "; "), F.lit("\nProposed: "), F.col(label),
    )


def parse_answer(text: str) -> Column:
    """Anything outside the closed set counts as unknown."""
    word = F.lower(F.trim(F.coalesce(F.col(text), F.lit(""))))
    return F.when(word.rlike(r"^yes\b"), "yes").when(word.rlike(r"^no\b"), "no").otherwise("unknown")


def knowledge_judge(columns: DataFrame, label: str = "pred", knowledge: Iterable[tuple[str, str, float]] = KNOWLEDGE) -> DataFrame:
    """Generic knowledge: yes if the label's pattern covers the cells, no if it does not or another type's does, else unknown.

    The patterns are a fixed, short list, so each is an expression over the row's own cells: no shuffle.
    """
    names, fits = [], []
    for name, pattern, least in knowledge:
        hits = F.size(F.filter("cells", _matching(pattern)))
        names.append(F.lit(name))
        fits.append(F.when((F.size("cells") > 0) & (hits / F.greatest(F.size("cells"), F.lit(1)) >= least), F.lit(name)))
    fitting = F.array_compact(F.array(*fits))
    known = F.array_contains(F.array(*names), F.col(label))
    decided = F.when(F.array_contains("_fitting", F.col(label)), "yes").when(known | (F.size("_fitting") > 0), "no").otherwise("unknown")
    return columns.withColumn("_fitting", fitting).withColumn("decision", decided).drop("_fitting")


def _matching(pattern: str):
    return lambda c: F.rlike(c, F.lit(pattern))


def noisy_judge(columns: DataFrame, accuracy: float, abstain: float, seed: str, label: str = "pred", truth: str = "type_name") -> DataFrame:
    """The truth, flipped and withheld at given rates by a seeded draw."""
    right = F.col(label) == F.col(truth)
    kept = uniform(seed + ":right", "column_id") < accuracy
    answer = F.when(uniform(seed + ":silent", "column_id") < abstain, "unknown").when(right == kept, "yes").otherwise("no")
    return columns.withColumn("decision", answer)


def constant_judge(columns: DataFrame, answer: str) -> DataFrame:
    return columns.withColumn("decision", F.lit(answer))


def client_judge(columns: DataFrame, ask: Callable[[list[str]], list[str]], types: Iterable[str], concurrency: int = 8, label: str = "pred") -> DataFrame:
    """A remote or local model behind `ask(prompts) -> answers`. Cells are redacted first; persist the result before use, so
    that a retried task does not pay twice."""
    names = columns.columns
    asked = columns.withColumn("cells", F.transform("cells", redact)).withColumn("_prompt", prompt(types, "cells", label)).select("column_id", "_prompt")

    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for f in frames:
            yield pd.DataFrame({"column_id": f["column_id"], "_text": ask(f["_prompt"].tolist())})

    answers = asked.repartition(concurrency).mapInPandas(run, "column_id string, _text string")
    return columns.join(answers, "column_id").withColumn("decision", parse_answer("_text")).select(*names, "decision")


def redact(cell: Column) -> Column:
    """Mask e-mail addresses, IPv4 addresses, long digit runs and long hex keys before cells leave the cluster."""
    out = F.regexp_replace(cell, r"[A-Za-z0-9._%+-]+@[A-Za-z0-9.-]+\.[A-Za-z]{2,}", "<mail>")
    out = F.regexp_replace(out, r"\b[0-9]{1,3}(\.[0-9]{1,3}){3}\b", "<ip>")
    out = F.regexp_replace(out, r"\b[0-9a-f]{32,}\b", "<hex>")
    return F.regexp_replace(out, r"\b[0-9]{12,}\b", "<digits>")


def flagged(judged: DataFrame) -> DataFrame:
    return judged.where(F.col("decision").isin("no", "unknown"))


def flag_regions(judged: DataFrame, regions: DataFrame) -> DataFrame:
    """decision x region of the true type, with counts: what each answer points at."""
    return judged.join(F.broadcast(regions), "type_name").groupBy("decision", "region").agg(F.count("*").alias("n"))
