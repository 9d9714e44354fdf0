"""Experiments on whole lakes: each configuration runs in Spark over every table, where `grid` sends drawn ones to a task.

Draws, labels and training are those of `grid.execute`: on a lake that `grid` does not cut both give the same results.
Configurations that differ only in how long they run are one run that is measured on its way.
"""

from __future__ import annotations

import time
from collections import Counter
from collections.abc import Iterator
from concurrent.futures import ThreadPoolExecutor
from copy import deepcopy
from dataclasses import replace
from functools import lru_cache, reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.storagelevel import StorageLevel

from lakeadapt.functions.features import WIDTH, encode, packed_array, rows_of
from lakeadapt.operators import backbones
from lakeadapt.operators.adapt import Config, SparkLake, adapt
from lakeadapt.operators.typer import Typer, blocked, contrastive, fit, fit_blocks, realign, train_blocks
from lakeadapt.sources import catalog, lake
from lakeadapt.sources.store import written
from lakeadapt.workloads.grid import _TO_COARSE, BACKBONE, BATCH, JUDGES, METHODS, RESULT, WARM_TABLES, Run, f1_counts

ABOUT = ("column_id", "table_id", "source_table", "position", "lake", "split", "type_name", "coarse")
#: Runs at a time: most of a run's jobs are too small for all cores.
AT_ONCE = 4


def aligned(batches: Iterator[pa.RecordBatch], key: str) -> Iterator[pa.RecordBatch]:
    """Batches of rows in the order of `key`, cut anew so that none ends within a value of it."""
    held: list[pa.RecordBatch] = []
    for batch in batches:
        at = np.flatnonzero(np.array(batch.column(key).to_pylist(), dtype=object) != batch.column(key)[len(batch) - 1].as_py()) if len(batch) else []
        if not len(batch):
            continue
        same = bool(held) and held[-1].column(key)[0].as_py() == batch.column(key)[0].as_py()
        if not len(at):
            if held and not same:
                yield pa.concat_batches(held)
                held = []
            held.append(batch)
            continue
        cut = int(at[-1]) + 1
        yield pa.concat_batches([*held, batch.slice(0, cut)])
        held = [batch.slice(cut)]
    if held:
        yield pa.concat_batches(held)


def with_siblings(columns: DataFrame) -> DataFrame:
    """`backbones.joint` on packed features: + siblings, packed. Tables are taken many at a time."""
    names = columns.columns

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in aligned(batches, "table_id"):
            x, tables = rows_of(batch.column("features")), np.array(batch.column("table_id").to_pylist(), dtype=object)
            starts = np.flatnonzero(np.concatenate([[True], tables[1:] != tables[:-1]]))
            n = np.diff([*starts, len(x)])
            rest = (np.repeat(np.add.reduceat(x, starts), n, axis=0) - x) / np.repeat(np.maximum(1, n - 1), n)[:, None]
            yield pa.RecordBatch.from_arrays([*batch.columns, packed_array(rest.astype(np.float32))], [*names, "siblings"])

    schema = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in columns.schema) + ", siblings binary"
    return columns.repartition("table_id").sortWithinPartitions("table_id", "column_id").mapInArrow(run, schema)


def with_relatives(columns: DataFrame) -> DataFrame:
    """`backbones.related` on packed features: + relatives, packed. A task sends one sum for each signature and place."""
    signed = columns.join(backbones.signatures(columns), "table_id")

    def sums(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        found: dict[tuple[str, int], list] = {}
        for batch in batches:
            for key, v in zip(zip(batch.column("signature").to_pylist(), batch.column("position").to_pylist()), rows_of(batch.column("features"))):
                if key in found:
                    found[key][0] += 1
                    found[key][1] += v
                else:
                    found[key] = [1, v.copy()]
        if found:
            keys = list(found)
            yield pa.RecordBatch.from_arrays([pa.array([s for s, _ in keys]), pa.array([p for _, p in keys], pa.int32()), pa.array([found[k][0] for k in keys], pa.int64()), pa.array([found[k][1] for k in keys], pa.list_(pa.float64()))], ["signature", "position", "n", "sums"])

    parts = signed.select("signature", "position", "features").mapInArrow(sums, "signature string, position int, n long, sums array<double>")
    long = parts.select("signature", "position", "n", F.posexplode("sums").alias("dim", "x")).groupBy("signature", "position", "dim").agg((F.sum("x") / F.sum("n")).alias("x"))
    means = long.groupBy("signature", "position").agg(F.transform(F.array_sort(F.collect_list(F.struct("dim", "x"))), lambda e: e["x"].cast("float")).alias("v"))

    def pack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            if len(batch):
                yield pa.RecordBatch.from_arrays([batch.column("signature"), batch.column("position"), packed_array(rows_of(batch.column("v")).astype(np.float32))], ["signature", "position", "relatives"])

    return signed.join(means.mapInArrow(pack, "signature string, position int, relatives binary"), ["signature", "position"]).drop("signature")


@lru_cache(maxsize=4)
def _base(app: str, sf_dir: str) -> DataFrame:
    spark = SparkSession.getActiveSession()
    return written(encode(lake.build(spark, sf_dir).select(*ABOUT, "cells"), packed=True), "whole")


@lru_cache(maxsize=8)
def _columns(app: str, sf_dir: str, letter: str) -> tuple[DataFrame, DataFrame]:
    base = _base(app, sf_dir)
    if letter == "C":
        star = base.where((F.col("lake") == "source") & F.col("source_table").isin(list(catalog.STAR)))
        return written(backbones.two_views(star).drop("cells"), "whole-views"), base.drop("cells")
    if letter == "R":
        cols = with_relatives(base).withColumn("features", F.concat("features", "relatives"))
    elif letter == "W":
        words = encode(base.select("column_id", "cells"), word_level=True, packed=True).select("column_id", F.col("features").alias("words"))
        cols = with_siblings(base.drop("cells")).join(words, "column_id").withColumn("features", F.concat("words", "siblings"))
    else:
        cols = with_siblings(base.drop("cells")).withColumn("features", F.concat("features", "siblings"))
    cols = written(cols.select(*ABOUT, "features"), f"whole-{letter}", ("lake", "split"))
    return cols, cols


def columns(spark: SparkSession, sf_dir: str, letter: str) -> tuple[DataFrame, DataFrame]:
    """All columns with the vectors of a backbone, to take source and target columns from."""
    return _columns(spark.sparkContext.applicationId, sf_dir, letter)


def sides(spark: SparkSession, sf_dir: str, transfer: str, letter: str) -> tuple[DataFrame, DataFrame]:
    """`grid.sides` of the first two transfers: source and target columns under the types of the transfer."""
    tx = next(t for t in catalog.TRANSFERS if t.name == transfer)
    s, t = columns(spark, sf_dir, letter)
    star = F.col("source_table").isin(list(catalog.STAR))
    s, t = s.where((F.col("lake") == "source") & star), t.where("lake = 'target'")
    if transfer == "TX2":
        coarse = reduce(lambda c, kv: c.when(F.col("type_name") == kv[0], kv[1]), _TO_COARSE.items(), F.when(star, F.col("type_name"))).otherwise(F.col("type_name"))
        return s.withColumn("type_name", F.col("coarse")), t.withColumn("type_name", coarse).where(F.col("type_name").isin(list(tx.target)))
    if transfer != "TX1":
        raise ValueError(f"{transfer} has no whole lake")
    return s, t


class Kept:
    """A run folder in memory, from which a longer run goes on."""

    def __init__(self) -> None:
        self.rows: list[tuple[int, str, str]] = []
        self.found: tuple[int, dict, dict] | None = None

    def save(self, iteration: int, rows: list[tuple[str, str]], model: dict[str, np.ndarray], state: dict) -> None:
        self.rows += [(iteration, stage, c) for stage, c in rows]
        self.found = iteration, dict(model), deepcopy(state)

    def last(self) -> tuple[int, dict, dict] | None:
        return deepcopy(self.found)

    def traced(self, upto: int) -> list[tuple[int, str, str]]:
        return [r for r in self.rows if r[0] <= upto]


def source_typer(source: DataFrame, types: tuple[str, ...], letter: str, seed: int) -> Typer:
    t = Typer.new(types, WIDTH * len(BACKBONE[letter]), seed)
    if letter == "C":
        views = blocked(source.select("column_id", "type_name", "view_a", "view_b"), types).persist(StorageLevel.MEMORY_AND_DISK)
        t, _ = train_blocks(views, t, lambda m, b: contrastive(m, b["view_a"], b["view_b"], seed=seed), ("view_a", "view_b"))
        views.unpersist()
    return fit_blocks(source, t, seed=seed)


def counted(test: DataFrame, t: Typer) -> Counter[tuple[str, str]]:
    """How often each type is named for columns of each type: at most types x types numbers."""
    sent = test.sparkSession.sparkContext.broadcast(t)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        found: Counter[tuple[str, str]] = Counter()
        for batch in batches:
            if len(batch):
                best = sent.value.predict(rows_of(batch.column("features")))[0]
                found.update(zip(batch.column("type_name").to_pylist(), [sent.value.types[k] for k in best]))
        yield pa.RecordBatch.from_arrays([pa.array([a for a, _ in found], pa.string()), pa.array([b for _, b in found], pa.string()), pa.array(list(found.values()), pa.int64())], ["truth", "pred", "n"])

    got = test.select("features", "type_name").mapInArrow(run, "truth string, pred string, n long").groupBy("truth", "pred").agg(F.sum("n").alias("n")).collect()
    return Counter({(r["truth"], r["pred"]): r["n"] for r in got})


def _chain(target: DataFrame, begin: Typer, types: tuple[str, ...], runs: list[Run]) -> list[dict]:
    """Runs that differ only in iterations or budget, the shorter first: each goes on where the one before stopped."""
    held, store, limit, rows, began = SparkLake(target), Kept(), None, [], time.time()
    n_train = held.train.count() if any(r.share for r in runs) else 0
    for r in sorted(runs, key=lambda r: (r.iterations, r.share, r.labels)):
        kind = r.method.rpartition("_")[0]
        cfg = Config(iterations=r.iterations, warm_tables=WARM_TABLES[r.transfer], batch=BATCH[r.transfer], budget=10**9, residual=False, seed=r.seed, k_factor=r.k_factor, space=r.space, delta=r.delta, patience=10**9)
        n_labels, calls, steps = r.labels, 0, 0
        if kind in METHODS:
            if r.share:
                cfg = replace(cfg, iterations=50, budget=int(r.share * n_train), residual=True, patience=5)
            if r.labels:
                cfg = replace(cfg, budget=r.labels)
            if limit is not None and store.found and store.found[2]["spent"] >= limit:
                store, began = Kept(), time.time()  # the smaller budget cut the loop short
            limit = cfg.budget
            out = adapt(held, realign(begin, types, r.seed), replace(cfg, **JUDGES.get(kind, {})), store)
            typer, n_labels, calls, steps = out.typer, out.spent, out.judge_calls, out.iterations
        else:
            warm = kind in ("warm_transplant", "warm_random_head")
            typer = realign(begin, types, r.seed, transplant=kind in ("warm_transplant", "random"))
            ids = held.warm(cfg.warm_tables, f"warm:{r.seed}") if warm else held.fresh(set(), r.labels, f"random:{r.seed}")
            truth, n_labels = held.truth(ids), len(ids)
            typer = fit(typer, held._features(ids), typer.encode_types([truth[i] for i in ids]), epochs=5 if warm else 25, seed=r.seed)
        sw, ma, ood = f1_counts(counted(target.where("split = 'test'"), typer), types)
        rows.append({"workload": r.workload, "transfer": r.transfer, "method": r.method, "budget": r.budget, "n_labels": n_labels, "seed": r.seed, "sw_f1": sw, "ma_f1": ma, "ood": ood, "judge_calls": calls, "iterations": steps, "seconds": time.time() - began})
    return rows


KINDS = (*(m for m in METHODS if m != "knowledge_judge"), "plain", "random", "warm_transplant", "warm_random_head")


def batch(spark: SparkSession, sf_dir: str, runs: list[Run]) -> DataFrame:
    """One row of results a configuration."""
    chains: dict[Run, list[Run]] = {}
    for r in runs:
        if r.method.rpartition("_")[0] not in KINDS:
            raise ValueError(f"{r.method} does not run on whole lakes")
        looped = r.method.rpartition("_")[0] in METHODS and not r.labels
        chains.setdefault(replace(r, budget="", iterations=0, share=float(r.share > 0)) if looped else r, []).append(r)
    made = {}
    for key in dict.fromkeys((r.transfer, r.method.rpartition("_")[2], r.seed) for r in runs):
        tx = next(t for t in catalog.TRANSFERS if t.name == key[0])
        source, target = sides(spark, sf_dir, *key[:2])
        made[key] = target, source_typer(source, tx.source, *key[1:]), tx.target
    with ThreadPoolExecutor(AT_ONCE) as pool:
        found = list(pool.map(lambda c: _chain(*made[(c[0].transfer, c[0].method.rpartition("_")[2], c[0].seed)], c), chains.values()))
    return spark.createDataFrame([tuple(row.values()) for rows in found for row in rows], RESULT)
