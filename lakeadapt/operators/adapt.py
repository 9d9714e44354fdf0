"""The adaptation loop: warm up, find gaps, spread them to clusters, buy labels, replay, stop early, spend the rest.

The loop is the same over a lake in Spark (`SparkLake`) and over arrays inside one task (`ArrayLake`); draws are hashes
of ids, so both choose the same columns. Who judges and who labels are arguments: the loop itself never sees the type of a
column that it has not paid for. Only ids of a probe or a batch and k x m centroid sums reach the driver.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from dataclasses import dataclass, field
from typing import Protocol

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.storagelevel import StorageLevel

from lakeadapt.functions.draws import drawn, rank, smallest
from lakeadapt.functions.features import row_of, rows_of
from lakeadapt.operators.judge import ConstantJudge, Judge, KnowledgeJudge, NoisyJudge, Proposal
from lakeadapt.operators.process import Account, Process, Truth
from lakeadapt.operators.typer import Typer, blocked, fit, train_blocks
from lakeadapt.sources.store import RunStore

#: Columns that a draw brings to the driver together with their features; beyond that only ids come.
CARRIED = 4000
#: Vectors a row of those kept for the rounds of k-means: few rows pass faster, and an Arrow batch of them stays small.
BLOCK = 16


@dataclass(frozen=True)
class Config:
    iterations: int = 50
    budget: int = 600
    warm_tables: int = 25
    batch: int = 25
    probe: int = 64
    delta: float = 0.9
    patience: int = 5
    epochs: int = 5
    lr: float = 2e-3
    k_factor: float = 1.0
    kmeans_rounds: int = 8
    judge: str = "noisy"  # noisy, knowledge, none, yes, no; or any Judge as an argument of adapt
    judge_accuracy: float = 0.807
    judge_abstains: float = 0.009
    selector: str = "weak"  # weak, random
    space: str = "hidden"  # hidden, logits
    replay: bool = True
    residual: bool = True
    on_empty: str = "skip"  # skip, random, stop
    local_labels: int = 50_000  # labels of a block: more than this are fitted in Spark, a block a task
    seed: int = 1


def judge_of(cfg: Config, lake: Lake) -> Judge | None:
    """The configured judge; None asks nobody, and every doubtful column is flagged."""
    if cfg.judge == "none":
        return None
    if cfg.judge == "knowledge":
        return KnowledgeJudge()
    if cfg.judge in ("yes", "no"):
        return ConstantJudge(cfg.judge)
    return NoisyJudge(lake.truth, cfg.judge_accuracy, cfg.judge_abstains, cfg.seed)


class Lake(Protocol):
    def warm(self, tables: int, seed: str) -> list[str]: ...
    def fresh(self, seen: set[str], n: int, seed: str) -> list[str]: ...
    def gate(self, t: Typer, ids: list[str], delta: float) -> list[tuple[str, str]]: ...
    def cells(self, ids: list[str]) -> dict[str, list[str]]: ...
    def truth(self, ids: list[str]) -> dict[str, str]: ...
    def from_weak(self, t: Typer, flagged: list[str], used: set[str], n: int, k: int, cfg: Config, seed: str) -> list[str]: ...
    def fit(self, t: Typer, labels: dict[str, str], cfg: Config, seed: int) -> Typer: ...
    def loss(self, t: Typer, labels: dict[str, str] | None) -> float: ...
    def has_validation(self) -> bool: ...


@dataclass
class Result:
    typer: Typer
    history: list[dict] = field(default_factory=list)
    trace: list[tuple[int, str, str]] = field(default_factory=list)
    spent: int = 0
    judge_calls: int = 0
    iterations: int = 0


def adapt(
    lake: Lake, start: Typer, cfg: Config, store: RunStore | None = None, sufficient: Callable[[float], bool] | None = None,
    judge: Judge | None = None, process: Process | None = None,
) -> Result:
    """Run the method. With a store, every iteration is written before the next, and a stored run goes on where it stopped.

    `judge` and `process` replace the configured judge and the truth of the lake. A lake without validation types of its own
    has a fifth of the bought labels kept out of training for the loss.
    """
    found = store.last() if store else None
    out = Result(start)
    asks = judge is not None or cfg.judge != "none"
    judge = judge or judge_of(cfg, lake)
    account = Account(process or Truth(lake.truth), cfg.budget)
    batches: list[list[str]] = []
    labels: dict[str, str] = {}
    seen: set[str] = set()
    best, alpha, first = float("inf"), 0, 1
    t, own_loss = start, lake.has_validation()

    def note(l: int, stage: str, ids: list[str]) -> None:
        out.trace += [(l, stage, i) for i in ids]

    def buy(l: int, stage: str, ids: list[str]) -> None:
        note(l, stage, ids)
        labels.update((i, n) for i, n in account.buy(ids).items() if n in t.index)
        out.spent = account.spent

    def checkpoint(l: int) -> None:
        if store:
            weights = {f"last_{k}": v for k, v in t.weights().items()} | {f"best_{k}": v for k, v in out.typer.weights().items()}
            state = {"batches": batches, "labels": labels, "seen": sorted(seen), "best": best, "alpha": alpha, "spent": out.spent, "calls": out.judge_calls, "history": out.history}
            store.save(l, [(s, c) for k, s, c in out.trace if k == l], weights, state)

    def held(i: str) -> bool:
        return not own_loss and rank("held", i) % 5 == 0

    def train(t: Typer, sets: list[list[str]], seed: int) -> Typer:
        chosen = {i: labels[i] for b in sets for i in b if i in labels and not held(i)}
        return lake.fit(t, chosen, cfg, seed) if chosen else t

    if found:
        l, weights, state = found
        t = Typer(start.types, *(weights[f"last_{k}"] for k in ("w1", "b1", "w2", "b2")))
        out.typer = Typer(start.types, *(weights[f"best_{k}"] for k in ("w1", "b1", "w2", "b2")))
        batches, labels, seen, best, alpha = state["batches"], state["labels"], set(state["seen"]), state["best"], state["alpha"]
        account.spent = out.spent = state["spent"]
        out.judge_calls, out.history, out.iterations, first = state["calls"], state["history"], l, l + 1
        out.trace = store.traced(l)
    else:
        warm = lake.warm(cfg.warm_tables, f"warm:{cfg.seed}")[: cfg.budget]
        batches.append(warm)
        buy(0, "batch", warm)
        t = train(t, batches, cfg.seed)
        out.typer = t
        checkpoint(0)

    for l in range(first, cfg.iterations + 1):
        used = {i for b in batches for i in b}
        if account.left <= 0 or alpha >= cfg.patience:
            break
        flagged: list[str] = []
        gated: list[tuple[str, str]] = []
        if cfg.selector == "weak":
            probed = lake.fresh(seen | used, cfg.probe, f"probe:{cfg.seed}:{l}")
            if not probed:
                break
            seen |= set(probed)
            note(l, "probe", probed)
            gated = lake.gate(t, probed, cfg.delta)
            if asks and gated:
                out.judge_calls += len(gated)
                note(l, "judge", [i for i, _ in gated])
                cells = lake.cells([i for i, _ in gated]) if judge.reads_cells else {}
                answers = judge.answer([Proposal(i, tuple(cells.get(i, ())), label) for i, label in gated])
                flagged = [i for (i, _), a in zip(gated, answers, strict=True) if a != "yes"]
            else:
                flagged = [i for i, _ in gated]
            note(l, "flagged", flagged)
        size = min(cfg.batch, account.left)
        if flagged:
            k = max(1, round(cfg.k_factor * len(t.types)))
            new = lake.from_weak(t, flagged, used, size, k, cfg, f"batch:{cfg.seed}:{l}")
        elif cfg.selector == "random" or cfg.on_empty == "random":
            new = lake.fresh(used, size, f"batch:{cfg.seed}:{l}")
        elif cfg.on_empty == "stop":
            break
        else:
            new = []
        batches.append(new)
        buy(l, "batch", new)
        t = train(t, batches if cfg.replay else batches[-1:], cfg.seed * 1000 + l)
        loss = lake.loss(t, None if own_loss else {i: n for i, n in labels.items() if held(i)})
        out.iterations = l
        if loss < best:
            best, alpha, out.typer = loss, 0, t
        else:
            alpha += 1
        out.history.append({"iter": l, "loss": loss, "batch": len(new), "gated": len(gated), "flagged": len(flagged), "alpha": alpha})
        checkpoint(l)
        if alpha >= cfg.patience or (sufficient and sufficient(loss)):
            break

    used = {i for b in batches for i in b}
    if cfg.residual and account.left > 0:
        rest = lake.fresh(used, account.left, f"rest:{cfg.seed}")
        if rest:
            buy(out.iterations + 1, "residual", rest)
            out.typer = train(out.typer, [*batches, rest], cfg.seed * 1000 + 999)
    return out


def kmeans_arrays(h: np.ndarray, seeds: np.ndarray, rounds: int) -> np.ndarray:
    centres = seeds.copy()
    for _ in range(rounds):
        near = np.argmin(((h**2).sum(1)[:, None] - 2 * h @ centres.T + (centres**2).sum(1)), axis=1)
        for c in range(len(centres)):
            if (near == c).any():
                centres[c] = h[near == c].mean(0)
    return np.argmin(((h**2).sum(1)[:, None] - 2 * h @ centres.T + (centres**2).sum(1)), axis=1)


class ArrayLake:
    """A lake of features inside one task: the grid of experiments runs one of these per configuration."""

    def __init__(self, ids: list[str], tables: list[str], split: list[str], x: np.ndarray, y: list[str], cells: list[list[str]] | None = None):
        self.at = {i: k for k, i in enumerate(ids)}
        self.x, self.y, self.tables, self._cells = x, y, tables, cells
        self.train = [i for i, s in zip(ids, split) if s == "train"]
        self.held = [i for i, s in zip(ids, split) if s == "valid"]
        self.test = [i for i, s in zip(ids, split) if s == "test"]

    def rows(self, ids: list[str]) -> np.ndarray:
        return self.x[[self.at[i] for i in ids]] if ids else self.x[:0]

    def warm(self, tables: int, seed: str) -> list[str]:
        chosen = set(drawn(sorted({self.tables[self.at[i]] for i in self.train}), tables, seed))
        return sorted(i for i in self.train if self.tables[self.at[i]] in chosen)

    def fresh(self, seen: set[str], n: int, seed: str) -> list[str]:
        return drawn([i for i in self.train if i not in seen], n, seed)

    def gate(self, t: Typer, ids: list[str], delta: float) -> list[tuple[str, str]]:
        best, phi = t.predict(self.rows(ids))
        return [(i, t.types[b]) for i, b, p in zip(ids, best, phi) if p < delta]

    def truth(self, ids: list[str]) -> dict[str, str]:
        return {i: self.y[self.at[i]] for i in ids}

    def from_weak(self, t: Typer, flagged: list[str], used: set[str], n: int, k: int, cfg: Config, seed: str) -> list[str]:
        h = t.hidden(self.rows(self.train)) if cfg.space == "hidden" else t.logits(self.rows(self.train))
        seeds = sorted(drawn(self.train, k, "centre:" + seed))
        where = {i: j for j, i in enumerate(self.train)}
        near = kmeans_arrays(h, h[[where[i] for i in seeds]], cfg.kmeans_rounds)
        weak = {near[where[i]] for i in flagged}
        return drawn([i for i, c in zip(self.train, near) if c in weak and i not in used], n, seed)

    def cells(self, ids: list[str]) -> dict[str, list[str]]:
        if self._cells is None:
            raise ValueError("this lake was made without cells")
        return {i: self._cells[self.at[i]] for i in ids}

    def labelled(self, ids: list[str], t: Typer) -> tuple[np.ndarray, np.ndarray]:
        ids = sorted(i for i in ids if self.y[self.at[i]] in t.index)
        return self.rows(ids), t.encode_types([self.y[self.at[i]] for i in ids])

    def fit(self, t: Typer, labels: dict[str, str], cfg: Config, seed: int) -> Typer:
        ids = sorted(labels)
        return fit(t, self.rows(ids), t.encode_types([labels[i] for i in ids]), cfg.epochs, 8, cfg.lr, seed)

    def has_validation(self) -> bool:
        return bool(self.held)

    def valid(self, t: Typer) -> tuple[np.ndarray, np.ndarray]:
        return self.labelled(self.held, t)

    def loss(self, t: Typer, labels: dict[str, str] | None = None) -> float:
        if labels is None:
            return t.loss(*self.valid(t))
        ids = sorted(labels)
        return t.loss(self.rows(ids), t.encode_types([labels[i] for i in ids]))


class SparkLake:
    """A lake as a DataFrame: column_id, table_id, split, features, and cells if a judge or a process reads them.

    Types are read by `truth`, for a benchmark's process and judge, and on the validation split, if `type_name` is there; a
    lake without that column needs a judge and a process of its own. `columns` should be a written table: every iteration
    passes over it a few times.
    """

    def __init__(self, columns: DataFrame):
        self.columns = columns
        self.train = columns.where("split = 'train'")
        self.known: dict[str, np.ndarray] = {}  # features that reached the driver: probes, first centres, labelled columns

    def _pick(self, df: DataFrame, n: int, seed: str) -> list[str]:
        """The n smallest draws; a few come with their features, which saves another pass for them."""
        with_features = n <= CARRIED and "features" in df.columns
        rows = smallest(df.select("column_id", "features") if with_features else df.select("column_id"), n, seed, "column_id").collect()
        if with_features:
            self.known.update((r["column_id"], row_of(r["features"])) for r in rows)
        return [r["column_id"] for r in rows]

    def _ids(self, ids: list[str]) -> DataFrame:
        return self.columns.sparkSession.createDataFrame(pa.table({"column_id": pa.array(ids, pa.string())}))

    def _without(self, df: DataFrame, ids: set[str]) -> DataFrame:
        return df.join(F.broadcast(self._ids(sorted(ids))), "column_id", "left_anti") if ids else df

    def _features(self, ids: list[str]) -> np.ndarray:
        """Features of ids, in their order; those that are not known yet are read in one pass."""
        new = [i for i in ids if i not in self.known]
        if new:
            got = self.columns.join(F.broadcast(self._ids(new)), "column_id", "left_semi").select("column_id", "features").collect()
            self.known.update((r["column_id"], row_of(r["features"])) for r in got)
        return np.array([self.known[i] for i in ids], np.float64)

    def warm(self, tables: int, seed: str) -> list[str]:
        from lakeadapt.operators.weak import random_tables

        return sorted(r["column_id"] for r in random_tables(self.train.select("column_id", "table_id"), tables, seed).select("column_id").collect())

    def fresh(self, seen: set[str], n: int, seed: str) -> list[str]:
        return self._pick(self._without(self.train, seen), n, seed)

    def gate(self, t: Typer, ids: list[str], delta: float) -> list[tuple[str, str]]:
        if not ids:
            return []
        best, phi = t.predict(self._features(ids))
        return [(i, t.types[b]) for i, b, p in zip(ids, best, phi) if p < delta]

    def truth(self, ids: list[str]) -> dict[str, str]:
        return {r[0]: r[1] for r in self.columns.join(F.broadcast(self._ids(ids)), "column_id", "left_semi").select("column_id", "type_name").collect()}

    def from_weak(self, t: Typer, flagged: list[str], used: set[str], n: int, k: int, cfg: Config, seed: str) -> list[str]:
        """The weights stand still meanwhile, so the vectors are computed once and kept for all rounds; a lost one is
        computed again. The clusters of the few flagged columns are found on the driver."""
        layer = t.logits if cfg.space == "logits" else t.hidden
        centres = layer(self._features(sorted(self._pick(self.train, k, "centre:" + seed))))
        space = self._space(t, cfg.space == "logits").persist(StorageLevel.MEMORY_AND_DISK)
        try:
            for _ in range(cfg.kmeans_rounds):
                centres = self._round(space, centres)
            pool = self._pool(space, centres, np.unique(nearest(layer(self._features(flagged)), centres)))
            return self._pick(self._without(pool, used), n, seed)
        finally:
            space.unpersist()

    def _space(self, t: Typer, logits: bool) -> DataFrame:
        """Ids and packed vectors (doubles) of all training columns, BLOCK of them a row."""
        sent = self.columns.sparkSession.sparkContext.broadcast(t)

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                if len(batch):
                    x = rows_of(batch.column("features"))
                    h = sent.value.logits(x) if logits else sent.value.hidden(x)
                    at = [*range(0, len(batch), BLOCK), len(batch)]
                    ids = pa.ListArray.from_arrays(pa.array(at, pa.int32()), batch.column("column_id"))
                    yield pa.RecordBatch.from_arrays([ids, pa.array([h[a:b].tobytes() for a, b in zip(at, at[1:])], pa.binary())], ["ids", "h"])

        return self.train.select("column_id", "features").mapInArrow(run, "ids array<string>, h binary")

    def _pool(self, space: DataFrame, centres: np.ndarray, weak: np.ndarray) -> DataFrame:
        """The columns of the weak clusters."""
        sent = self.columns.sparkSession.sparkContext.broadcast((centres, weak))

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                if len(batch):
                    c = sent.value[0]
                    near = np.concatenate([nearest(h, c) for h in pieces(batch, c.shape[1])])
                    yield pa.RecordBatch.from_arrays([batch.column("ids").flatten().filter(pa.array(np.isin(near, sent.value[1])))], ["column_id"])

        return space.mapInArrow(run, "column_id string")

    def _round(self, space: DataFrame, centres: np.ndarray) -> np.ndarray:
        """One k-means round: each task sends its counts and sums, k x (m + 1) numbers in one piece; there are a few tasks a core."""
        sent = self.columns.sparkSession.sparkContext.broadcast(centres)

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            sums, counts = np.zeros_like(sent.value), np.zeros(len(sent.value), np.int64)
            for batch in batches:
                for h in pieces(batch, sums.shape[1]):
                    near = nearest(h, sent.value)
                    sums += np.eye(len(sums))[near].T @ h
                    counts += np.bincount(near, minlength=len(counts))
            yield pa.RecordBatch.from_arrays([pa.array([counts.tobytes()], pa.binary()), pa.array([sums.tobytes()], pa.binary())], ["n", "sums"])

        tasks = 4 * self.columns.sparkSession.sparkContext.defaultParallelism
        parts = space.select("h").coalesce(tasks).mapInArrow(run, "n binary, sums binary").toArrow()
        sent.unpersist()
        out, counts = centres.copy(), sum((np.frombuffer(v, np.int64) for v in parts.column("n").to_pylist()), np.zeros(len(centres), np.int64))
        sums = sum((np.frombuffer(v).reshape(centres.shape) for v in parts.column("sums").to_pylist()), np.zeros(centres.shape))
        out[counts > 0] = sums[counts > 0] / counts[counts > 0, None]
        return out

    def cells(self, ids: list[str]) -> dict[str, list[str]]:
        """At most a probe or a batch of columns."""
        return {r[0]: list(r[1] or []) for r in self.columns.join(F.broadcast(self._ids(ids)), "column_id", "left_semi").select("column_id", "cells").collect()}

    def _rows(self, labels: dict[str, str]) -> DataFrame:
        named = self.columns.sparkSession.createDataFrame(sorted(labels.items()), "column_id string, type_name string")
        return self.columns.select("column_id", "features").join(F.broadcast(named) if len(labels) <= 1_000_000 else named, "column_id")

    def fit(self, t: Typer, labels: dict[str, str], cfg: Config, seed: int) -> Typer:
        """In blocks of about `local_labels` labels, from the same weights to the mean of theirs; a single one on the driver."""
        if len(labels) > cfg.local_labels:
            return train_blocks(blocked(self._rows(labels), t.types, cfg.local_labels), t, lambda m, b: fit(m, b["features"], b["y"], cfg.epochs, 8, cfg.lr, seed))[0]
        ids = sorted(i for i, n in labels.items() if n in t.index)
        return fit(t, self._features(ids), t.encode_types([labels[i] for i in ids]), cfg.epochs, 8, cfg.lr, seed)

    def has_validation(self) -> bool:
        return "type_name" in self.columns.columns and not self.columns.where("split = 'valid'").isEmpty()

    def loss(self, t: Typer, labels: dict[str, str] | None = None) -> float:
        """Mean cross-entropy over the validation split (or over labels), summed where the columns lie."""
        rows = self._rows(labels) if labels is not None else self.columns.where("split = 'valid'")
        rows = rows.where(F.col("type_name").isin(list(t.types))).select("features", "type_name")
        sent = self.columns.sparkSession.sparkContext.broadcast(t)

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                x, y = rows_of(batch.column("features")), sent.value.encode_types(batch.column("type_name").to_pylist())
                if len(y):
                    yield pa.RecordBatch.from_arrays([pa.array([sent.value.loss(x, y) * len(y)]), pa.array([len(y)], pa.int64())], ["s", "n"])

        got = rows.mapInArrow(run, "s double, n long").agg(F.sum("s").alias("s"), F.sum("n").alias("n")).head()
        return got["s"] / got["n"] if got["n"] else float("inf")


def pieces(batch: pa.RecordBatch, width: int, most: int = 4096) -> list[np.ndarray]:
    """The vectors of a batch of blocks, so many at a time that distances to all centres stay small."""
    h = rows_of(batch.column("h"), "<f8", width)
    return [h[k : k + most] for k in range(0, len(h), most)]


def nearest(h: np.ndarray, centres: np.ndarray) -> np.ndarray:
    """The nearest centre of each row; its own length does not matter for that."""
    far = h @ (-2 * centres.T)
    far += (centres**2).sum(1)
    return far.argmin(1)
