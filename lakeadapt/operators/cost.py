"""Cost measures: judge calls, time, money, replay and clustering work."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: Published unit costs of a judge call (dollars, seconds) at two type counts.
UNIT = {"V": (78, 0.00047, 1.2643), "S": (275, 0.00150, 1.0037)}


@dataclass(frozen=True)
class Work:
    """Counts of one run; each method gives a closed form."""

    iterations: int
    first: int
    batch: int
    epochs: int
    n_valid: int
    n_source: int
    n_target: int
    n_columns: int
    width: int
    rounds: int

    def realign(self) -> int:
        return self.n_source + self.n_target

    def realign_paper(self) -> int:
        return self.n_source * self.n_target

    def clustering(self) -> int:
        return self.n_columns * self.n_target * self.width * self.rounds * self.iterations

    def replay_exact(self) -> int:
        """Columns trained on, iterations 1..P with all batches so far."""
        p = self.iterations
        return self.epochs * (p * self.first + self.batch * p * (p + 1) // 2)

    def replay_lower(self) -> int:
        """The sum that counts batches before the current one only."""
        p = self.iterations
        return self.epochs * (p * self.first + self.batch * p * (p - 1) // 2)

    def replay_bound(self, budget: int) -> int | None:
        """P x budget, where it holds: P x the largest batch within the budget."""
        return self.iterations * budget * self.epochs if self.iterations * max(self.first, self.batch) <= budget else None

    def validation(self) -> int:
        return self.iterations * self.epochs * self.n_valid


def query_counts(trace: DataFrame) -> DataFrame:
    """trace(run, iter, stage, column_id) -> judge calls and realised iterations per run."""
    return trace.groupBy("run").agg(F.count_if(F.col("stage") == "judge").alias("judge_calls"), F.countDistinct(F.when(F.col("iter") > 0, F.col("iter"))).alias("iterations"))


def overhead(calls: DataFrame) -> DataFrame:
    """lake, judge_calls -> seconds and dollars by the unit costs."""
    rows = F.create_map(*[F.lit(x) for k, (_, usd, _) in UNIT.items() for x in (k, usd)])
    secs = F.create_map(*[F.lit(x) for k, (_, _, s) in UNIT.items() for x in (k, s)])
    return calls.select("transfer", "backbone", "judge_calls", F.round(F.col("judge_calls") * F.element_at(secs, F.col("lake")), 1).alias("seconds"), F.round(F.col("judge_calls") * F.element_at(rows, F.col("lake")), 2).alias("usd"))


def prompt_dollars(n_types: int) -> float:
    """Dollars of a call as a line in the number of types, through the two published points."""
    (a, x, _), (b, y, _) = UNIT["V"], UNIT["S"]
    slope = (y - x) / (b - a)
    return x + slope * (n_types - a)
