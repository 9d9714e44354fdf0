"""Annotation processes: who gives labels, and the account they are charged to."""

from __future__ import annotations

import re
from collections.abc import Callable
from dataclasses import dataclass
from typing import Protocol

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


class Process(Protocol):
    """Names the types of the columns asked for, or of those it can; the loop asks only for what it pays."""

    def label(self, ids: list[str]) -> dict[str, str]: ...


@dataclass(frozen=True)
class Truth:
    """People who are always right: the truth of a benchmark lake."""

    read: Callable[[list[str]], dict[str, str]]

    def label(self, ids: list[str]) -> dict[str, str]:
        return self.read(ids)


@dataclass(frozen=True)
class Heuristic:
    """The rules of `heuristic` on a column's own cells."""

    cells: Callable[[list[str]], dict[str, list[str]]]

    def label(self, ids: list[str]) -> dict[str, str]:
        return {i: shape_label(c) for i, c in self.cells(ids).items() if c}


@dataclass(frozen=True)
class Dictionary:
    """A knowledge base value -> type: the type of most cells, if it covers `share` of them."""

    cells: Callable[[list[str]], dict[str, list[str]]]
    entries: dict[str, str]
    share: float = 0.5

    def label(self, ids: list[str]) -> dict[str, str]:
        out = {}
        for i, own in self.cells(ids).items():
            hits: dict[str, int] = {}
            for c in own:
                if c in self.entries:
                    hits[self.entries[c]] = hits.get(self.entries[c], 0) + 1
            if hits:
                best = min(hits, key=lambda t: (-hits[t], t))
                if hits[best] >= self.share * len(own):
                    out[i] = best
        return out


class Account:
    """What labels cost: a label is paid when it is asked for, right or wrong, and none beyond the budget."""

    def __init__(self, process: Process, budget: int, spent: int = 0):
        self.process, self.budget, self.spent = process, budget, spent

    @property
    def left(self) -> int:
        return self.budget - self.spent

    def buy(self, ids: list[str]) -> dict[str, str]:
        if len(ids) > self.left:
            raise ValueError(f"{len(ids)} labels asked for, {self.left} left")
        self.spent += len(ids)
        return self.process.label(ids) if ids else {}


def shape_label(cells: list[str]) -> str:
    if all("@" in c or c.startswith("http") for c in cells):
        return "web_address"
    if all(c.startswith("{") and c.endswith("}") for c in cells):
        return "json_props"
    if all(re.fullmatch("[0-9]+", c) for c in cells):
        return "record_key"
    return "money_amount" if all(_is_number(c.replace(",", ".")) for c in cells) else "name"


def _is_number(text: str) -> bool:
    try:
        float(text)
        return True
    except ValueError:
        return False


class GroundTruth:
    """Reads the truth for the columns asked for, in id order, as far as the budget goes."""

    def __init__(self, truth: DataFrame, budget: int):
        self.truth, self.left = truth, budget

    def label(self, ids: DataFrame) -> DataFrame:
        asked = [r["column_id"] for r in ids.select("column_id").distinct().orderBy("column_id").limit(self.left).collect()]  # at most the budget
        self.left -= len(asked)
        granted = ids.sparkSession.createDataFrame([(i,) for i in asked], "column_id string")
        return self.truth.join(F.broadcast(granted), "column_id", "left_semi")


def heuristic(columns: DataFrame) -> DataFrame:
    """Rules on the cells: a cheap process that knows four shapes."""
    cell = columns.select("column_id", F.explode("cells").alias("cell"))
    every = lambda c: F.bool_and(c)
    label = (
        F.when(every(F.col("cell").contains("@") | F.col("cell").startswith("http")), "web_address")
        .when(every(F.col("cell").startswith("{") & F.col("cell").endswith("}")), "json_props")
        .when(every(F.col("cell").rlike("^[0-9]+$")), "record_key")
        .when(every(F.expr("try_cast(replace(cell, ',', '.') AS double) IS NOT NULL")), "money_amount")
        .otherwise("name")
    )
    return cell.groupBy("column_id").agg(label.alias("label"))


def knowledge_base(columns: DataFrame, dictionary: DataFrame, share: float = 0.5) -> DataFrame:
    """dictionary(value, type_name): the type that most cells are listed under, if it covers `share` of them."""
    cell = columns.select("column_id", F.explode("cells").alias("value"))
    n = cell.groupBy("column_id").agg(F.count("*").alias("n"))
    hits = cell.join(dictionary, "value").groupBy("column_id", "type_name").agg(F.count("*").alias("hits"))
    best = hits.groupBy("column_id").agg(F.min(F.struct((-F.col("hits")).alias("m"), "type_name")).alias("b"))
    return best.join(n, "column_id").where(-F.col("b.m") >= share * F.col("n")).select("column_id", F.col("b.type_name").alias("label"))
