"""Experiment grids: one configuration per group of an applyInPandas, so that a whole table of results runs in parallel.

The experiments run on lakes of a fixed size, as the published ones do: LAKE_TABLES tables of each kind and side at most,
drawn by a hash, so that the feature arrays are bounded and can be sent to every task. (`adapt_full`, the lake queries
and the workloads of WHOLE work on whole lakes.) Each configuration trains a source typer, adapts or retrains it, and is measured on held-out tables.
Baselines get as many labels as the method bought: the method's runs come first.
"""

from __future__ import annotations

import time
from collections import Counter
from dataclasses import asdict, dataclass, replace
from functools import lru_cache

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from lakeadapt.baselines import methods
from lakeadapt.functions.draws import draw, drawn
from lakeadapt.functions.features import encode
from lakeadapt.operators import backbones
from lakeadapt.operators.adapt import ArrayLake, Config, adapt
from lakeadapt.operators.typer import Typer, contrastive, fit, fit_to_plateau, realign
from lakeadapt.sources import catalog, lake
from lakeadapt.sources.store import written

RESULT = "workload string, transfer string, method string, budget string, n_labels long, seed long, sw_f1 double, ma_f1 double, ood double, judge_calls long, iterations long, seconds double"


@dataclass(frozen=True)
class Arrays:
    ids: list[str]
    tables: list[str]
    lakes: list[str]
    split: list[str]
    fine: list[str]
    coarse: list[str | None]
    groups: list[str]
    cells: list[list[str]]
    parts: dict[str, np.ndarray]

    def subset(self, keep: np.ndarray) -> Arrays:
        at = np.flatnonzero(keep)
        pick = lambda xs: [xs[k] for k in at]
        return Arrays(pick(self.ids), pick(self.tables), pick(self.lakes), pick(self.split), pick(self.fine), pick(self.coarse), pick(self.groups), pick(self.cells), {k: v[at] for k, v in self.parts.items()})


#: Tables of a kind and side in an experiment.
LAKE_TABLES = 300
#: Workloads that run on whole lakes instead, in Spark.
WHOLE = ("V13", "W11", "W14")


def featured(spark: SparkSession, sf_dir: str) -> DataFrame:
    """An experiment's lake with every encoder's vectors, as a written table."""
    whole = lake.build(spark, sf_dir)
    drawn_ = Window.partitionBy("source_table", "lake").orderBy(draw("experiment", "table_id"), "table_id")
    tables = whole.select("table_id", "source_table", "lake").distinct().withColumn("r", F.row_number().over(drawn_)).where(F.col("r") <= LAKE_TABLES).select("table_id")
    cols = written(encode(whole.join(F.broadcast(tables), "table_id", "left_semi")), "features")
    cols = backbones.two_views(backbones.related(backbones.joint(cols)))
    cols = backbones.row_context(cols)
    return written(cols, "contexts")


def vectors(rows: DataFrame, column: str) -> np.ndarray:
    """One vector column as a matrix in the order of column_id. Vectors come one column at a time and never as Python
    numbers, which take eight times the room."""
    got = rows.select("column_id", F.col(column).cast("array<float>").alias("v")).toArrow()
    order = got.select(["column_id"]).append_column("at", pa.array(np.arange(len(got)))).sort_by("column_id").column("at").to_numpy()
    flat = got.column("v").combine_chunks().flatten().to_numpy(zero_copy_only=False)
    return flat.reshape(len(got), -1)[order]


@lru_cache(maxsize=4)
def _arrays(app: str, sf_dir: str) -> Arrays:
    spark = SparkSession.getActiveSession()
    f = featured(spark, sf_dir)
    words = encode(f.select("column_id", "cells"), word_level=True).selectExpr("column_id", "features AS words")
    about = f.select("column_id", "table_id", "lake", "split", "type_name", "coarse", "source_table", lake.for_prompt("cells").alias("cells")).toArrow().sort_by("column_id")
    named = (("x", "features"), ("siblings", "siblings"), ("relatives", "relatives"), ("a", "view_a"), ("b", "view_b"), ("rows", "row_vector"))
    parts = {k: vectors(f, c) for k, c in named} | {"words": vectors(words, "words")}
    return Arrays(*[about.column(c).to_pylist() for c in about.column_names], parts)


def arrays(spark: SparkSession, sf_dir: str) -> Arrays:
    return _arrays(spark.sparkContext.applicationId, sf_dir)


_TO_COARSE = {"user_key": "record_key", "event_value": "money_amount", "turn_number": "small_integer"}


def sides(a: Arrays, name: str) -> tuple[Arrays, list[str], tuple[str, ...], Arrays, list[str], tuple[str, ...]]:
    """Source and target of a transfer, with their types by column."""
    tx = next(t for t in catalog.TRANSFERS if t.name == name)
    star = np.array([g in catalog.STAR for g in a.groups])
    src = np.array([x == "source" for x in a.lakes])
    if name == "TX3":
        star_or_events = star | np.array([g == "events" for g in a.groups])
        s, t = a.subset(src & star_or_events), a.subset(~src & np.array([f in tx.target for f in a.fine]))
        return s, s.fine, tx.source, t, t.fine, tx.target
    if name == "TX2":
        s = a.subset(src & star)
        named = [f if st and f in tx.target else (_TO_COARSE.get(f, f) if not st else "") for f, st in zip(a.fine, star)]
        keep = ~src & np.array([n in tx.target for n in named])
        return s, s.coarse, tx.source, a.subset(keep), [n for n, k in zip(named, keep) if k], tx.target
    s, t = a.subset(src & star), a.subset(~src)
    return s, s.fine, tx.source, t, t.fine, tx.target


#: Tables of the warm-up, and labels of an iteration: the second and third transfers have smaller lakes.
WARM_TABLES = {"TX1": 16, "TX2": 10, "TX3": 10}
BATCH = {"TX1": 25, "TX2": 15, "TX3": 15}
BACKBONE = {"J": ("x", "siblings"), "C": ("x",), "R": ("x", "relatives"), "W": ("words", "siblings")}


def inputs(a: Arrays, backbone: str) -> np.ndarray:
    return np.concatenate([a.parts[p] for p in BACKBONE[backbone]], axis=1).astype(np.float64)


@dataclass(frozen=True)
class Run:
    workload: str
    transfer: str
    method: str
    budget: str
    iterations: int = 5
    labels: int = 0
    share: float = 0.0
    seed: int = 1
    k_factor: float = 1.0
    space: str = "hidden"
    delta: float = 0.9


def f1(truth: list[str], pred: list[str], types: tuple[str, ...]) -> tuple[float, float, float]:
    return f1_counts(Counter(zip(truth, pred)), types)


def f1_counts(counts: Counter[tuple[str, str]], types: tuple[str, ...]) -> tuple[float, float, float]:
    """Support-weighted F1, macro F1 and out-of-set share from how often each type was named for columns of each type."""
    known, sw, per = set(types), 0.0, []
    tp, fp, fn = Counter(), Counter(), Counter()
    for (t, p), n in counts.items():
        if t == p:
            tp[t] += n
        else:
            fp[p] += n
            fn[t] += n
    for t in sorted({t for pair in counts for t in pair} & known):
        a, b, c = tp[t], fp[t], fn[t]
        score = 2 * a / (2 * a + b + c) if a else 0.0
        per.append(score)
        sw += score * (a + c)
    n = max(1, sum(counts.values()))
    return sw / n, float(np.mean(per)) if per else 0.0, sum(k for (_, p), k in counts.items() if p not in known) / n


def execute(a: Arrays, r: Run) -> dict:
    """One row of results."""
    began = time.time()
    s, sy, s_types, t, ty, t_types = sides(a, r.transfer)
    kind, _, letter = r.method.rpartition("_")
    backbone = letter if letter in BACKBONE else "J"
    kind = kind if letter in BACKBONE else r.method
    x = inputs(t, backbone)
    target = ArrayLake(t.ids, t.tables, t.split, x, ty, t.cells)
    test = [target.at[i] for i in target.test]
    truth = [ty[k] for k in test]
    cfg = Config(iterations=r.iterations, warm_tables=WARM_TABLES[r.transfer], batch=BATCH[r.transfer], budget=10**9, residual=False, seed=r.seed, k_factor=r.k_factor, space=r.space, delta=r.delta, patience=10**9)
    n_full = len(target.warm(cfg.warm_tables, f"warm:{r.seed}")) + r.iterations * cfg.batch
    n_labels = r.labels or (int(r.share * len(target.train)) if r.share else n_full)
    if r.share:
        cfg = replace(cfg, iterations=50, budget=n_labels, residual=True, patience=5)
    calls = steps = 0

    def source() -> Typer:
        fresh = Typer.new(s_types, x.shape[1], r.seed)
        if backbone == "C":
            fresh = contrastive(fresh, s.parts["a"].astype(np.float64), s.parts["b"].astype(np.float64), seed=r.seed)
        return fit_to_plateau(fresh, inputs(s, backbone), fresh.encode_types(sy), seed=r.seed)

    def sample() -> list[int]:
        return [target.at[i] for i in drawn(target.train, n_labels, f"random:{r.seed}")]

    if kind in METHODS:
        if r.labels:
            cfg = replace(cfg, budget=r.labels)
        out = adapt(target, realign(source(), t_types, r.seed), replace(cfg, **JUDGES.get(kind, {})))
        typer, n_labels, calls, steps = out.typer, out.spent, out.judge_calls, out.iterations
        pred = [typer.types[k] for k in typer.predict(x[test])[0]]
    elif kind in ("plain", "random"):
        begin = source()
        ids = sample()
        typer = realign(begin, t_types, r.seed, transplant=kind == "random")
        typer = fit(typer, x[ids], typer.encode_types([ty[k] for k in ids]), epochs=25, seed=r.seed)
        pred = [typer.types[k] for k in typer.predict(x[test])[0]]
    elif kind in ("warm_transplant", "warm_random_head"):
        typer = realign(source(), t_types, r.seed, transplant=kind == "warm_transplant")
        ids = [target.at[i] for i in target.warm(cfg.warm_tables, f"warm:{r.seed}")]
        typer, n_labels = fit(typer, x[ids], typer.encode_types([ty[k] for k in ids]), seed=r.seed), len(ids)
        pred = [typer.types[k] for k in typer.predict(x[test])[0]]
    elif kind == "direct":
        typer, n_labels = source(), 0
        pred = [typer.types[k] for k in typer.predict(x[test])[0]]
    elif kind in ("feature_fusion", "row_col"):
        ids = sample()
        parts = [t.parts["x"], t.parts["words"]] if kind == "feature_fusion" else [t.parts["x"], t.parts["rows"]]
        try:
            typer = methods.feature_fusion(parts, ty, t_types, ids, r.seed, strict=kind == "feature_fusion")
            pred = [typer.types[k] for k in typer.predict(np.concatenate(parts, axis=1)[test])[0]]
        except methods.MissingTypeError:
            pred = None
    elif kind in methods.ANNOTATORS:
        n_labels, pred = 0, methods.direct_label([t.cells[k] for k in test], t_types, kind)
    elif kind == "source_test":
        # the source typer on held-out tables of its own lake: what a transfer starts from
        own = [k for k, sp in enumerate(s.split) if sp == "test"]
        kept = [k for k, sp in enumerate(s.split) if sp != "test"]
        typer = Typer.new(s_types, x.shape[1], r.seed)
        typer = fit_to_plateau(typer, inputs(s, backbone)[kept], typer.encode_types([sy[k] for k in kept]), seed=r.seed)
        truth, n_labels, t_types = [sy[k] for k in own], 0, s_types
        pred = [typer.types[k] for k in typer.predict(inputs(s, backbone)[own])[0]]
    elif kind == "generator":
        pred = methods.nearest_label(t.parts["x"], sample(), ty, test)
    else:
        raise ValueError(f"no method is named {r.method}")
    sw, ma, ood = f1(truth, pred, t_types) if pred is not None else (float("nan"),) * 3
    return {"workload": r.workload, "transfer": r.transfer, "method": r.method, "budget": r.budget, "n_labels": n_labels, "seed": r.seed, "sw_f1": sw, "ma_f1": ma, "ood": ood, "judge_calls": calls, "iterations": steps, "seconds": time.time() - began}


#: What a method changes in the loop.
JUDGES = {"knowledge_judge": {"judge": "knowledge"}, "no_judge": {"judge": "none"}, "strong_judge": {"judge_accuracy": 0.95}, "weak_judge": {"judge_accuracy": 0.75}, "perfect_judge": {"judge_accuracy": 1.0, "judge_abstains": 0.0}, "no_replay": {"replay": False}}
METHODS = ("full", "no_judge", "strong_judge", "weak_judge", "perfect_judge", "knowledge_judge", "no_replay")
#: Methods that take labels without buying them one batch at a time.
FED = ("plain", "random", "feature_fusion", "row_col", "generator")


def _letter(method: str) -> str:
    return method.rpartition("_")[2] if method.rpartition("_")[2] in BACKBONE else "J"


def _batch(spark: SparkSession, sf_dir: str, runs: list[Run]) -> DataFrame:
    if runs[0].workload in WHOLE:
        from lakeadapt.workloads import whole

        return whole.batch(spark, sf_dir, runs)
    sent = spark.sparkContext.broadcast(arrays(spark, sf_dir))
    rows = spark.createDataFrame([{"id": k, **asdict(r)} for k, r in enumerate(runs)])

    def one(group: pd.DataFrame) -> pd.DataFrame:
        return pd.DataFrame([execute(sent.value, Run(**{k: group.iloc[0][k].item() if hasattr(group.iloc[0][k], "item") else group.iloc[0][k] for k in Run.__dataclass_fields__}))])

    return rows.repartition(len(runs), "id").groupBy("id").applyInPandas(one, RESULT)


def run_grid(spark: SparkSession, sf_dir: str, runs: list[Run]) -> DataFrame:
    """All configurations, one group each. A baseline at a number of iterations gets the labels that the full method, on the
    same backbone and seed, bought in them; where that run is not among the configurations it is made for this count."""
    fed = [r for r in runs if r.method.rsplit("_", 1)[0] in FED or r.method in FED]
    fed = [r for r in fed if not r.labels and not r.share]
    twin = {r: replace(r, method=f"full_{_letter(r.method)}", workload=r.workload) for r in fed}
    ready = [r for r in runs if r not in twin]
    extra = [r for r in dict.fromkeys(twin.values()) if r not in ready]
    if not fed:
        return _batch(spark, sf_dir, runs)
    done = _batch(spark, sf_dir, [*ready, *extra]).toPandas()  # one row a configuration
    bought = {(d["transfer"], d["method"], d["budget"], d["seed"]): int(d["n_labels"]) for d in done.to_dict("records")}
    rest = [replace(r, labels=bought[(r.transfer, twin[r].method, r.budget, r.seed)]) for r in fed]
    fed_rows = _batch(spark, sf_dir, rest)
    keys = {(r.transfer, r.method, r.budget, r.seed) for r in ready}
    own = done[[(d["transfer"], d["method"], d["budget"], d["seed"]) in keys for d in done.to_dict("records")]]
    return spark.createDataFrame(own, RESULT).unionByName(fed_rows) if len(own) else fed_rows
