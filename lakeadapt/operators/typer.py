"""The typer: a trainable hidden layer under a linear head over a type set, in numpy.

Training sets are bounded by the label budget, so fitting is one task's work; scoring a lake is an Arrow pass with the
weights broadcast.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from dataclasses import dataclass, field, replace

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.storagelevel import StorageLevel

from lakeadapt.functions.draws import draw
from lakeadapt.functions.features import rows_of

HIDDEN = 64
#: Columns of a block, on which one task trains from one to the next.
BLOCK_COLUMNS = 4000


@dataclass
class Typer:
    types: tuple[str, ...]
    w1: np.ndarray
    b1: np.ndarray
    w2: np.ndarray
    b2: np.ndarray
    index: dict[str, int] = field(init=False, repr=False)

    def __post_init__(self) -> None:
        self.index = {t: k for k, t in enumerate(self.types)}

    @classmethod
    def new(cls, types: tuple[str, ...], width: int, seed: int, hidden: int = HIDDEN) -> Typer:
        rng = np.random.default_rng(seed)
        return cls(tuple(types), rng.normal(0, 1 / np.sqrt(width), (width, hidden)) * 2, np.zeros(hidden), *random_head(len(types), hidden, rng))

    def hidden(self, x: np.ndarray) -> np.ndarray:
        return np.tanh(x @ self.w1 + self.b1)

    def logits(self, x: np.ndarray) -> np.ndarray:
        return self.hidden(x) @ self.w2 + self.b2

    def proba(self, x: np.ndarray) -> np.ndarray:
        return softmax(self.logits(x))

    def loss(self, x: np.ndarray, y: np.ndarray) -> float:
        return float(-np.log(np.maximum(self.proba(x)[np.arange(len(y)), y], 1e-12)).mean()) if len(y) else float("inf")

    def predict(self, x: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Type numbers and confidences."""
        p = self.proba(x)
        return p.argmax(1), p.max(1)

    def encode_types(self, names: list[str]) -> np.ndarray:
        return np.array([self.index[n] for n in names], np.int64)

    def weights(self) -> dict[str, np.ndarray]:
        return {"w1": self.w1, "b1": self.b1, "w2": self.w2, "b2": self.b2}

    def copy(self) -> Typer:
        return replace(self, **{k: v.copy() for k, v in self.weights().items()})


def softmax(v: np.ndarray) -> np.ndarray:
    e = np.exp(v - v.max(1, keepdims=True))
    return e / e.sum(1, keepdims=True)


def random_head(n: int, hidden: int, rng: np.random.Generator) -> tuple[np.ndarray, np.ndarray]:
    return rng.normal(0, 1 / np.sqrt(hidden), (hidden, n)), np.zeros(n)


def realign(source: Typer, target: tuple[str, ...], seed: int, transplant: bool = True) -> Typer:
    """Encoder as it is; each shared type keeps its column and bias of the head, all others start at random."""
    w2, b2 = random_head(len(target), source.w2.shape[0], np.random.default_rng(seed))
    for j, name in enumerate(target):
        if transplant and name in source.index:
            w2[:, j], b2[j] = source.w2[:, source.index[name]], source.b2[source.index[name]]
    return Typer(tuple(target), source.w1.copy(), source.b1.copy(), w2, b2)


def gradients(t: Typer, x: np.ndarray, y: np.ndarray) -> dict[str, np.ndarray]:
    h = t.hidden(x)
    d = softmax(h @ t.w2 + t.b2)
    d[np.arange(len(y)), y] -= 1
    d /= len(y)
    back = (d @ t.w2.T) * (1 - h * h)
    return {"w1": x.T @ back, "b1": back.sum(0), "w2": h.T @ d, "b2": d.sum(0)}


class Adam:
    def __init__(self, lr: float):
        self.lr, self.step, self.m, self.v = lr, 0, {}, {}

    def update(self, weights: dict[str, np.ndarray], grads: dict[str, np.ndarray]) -> None:
        self.step += 1
        for k, g in grads.items():
            self.m[k] = 0.9 * self.m.get(k, 0.0) + 0.1 * g
            self.v[k] = 0.999 * self.v.get(k, 0.0) + 0.001 * g * g
            weights[k] -= self.lr * (self.m[k] / (1 - 0.9**self.step)) / (np.sqrt(self.v[k] / (1 - 0.999**self.step)) + 1e-8)


def fit(t: Typer, x: np.ndarray, y: np.ndarray, epochs: int = 5, batch: int = 8, lr: float = 2e-3, seed: int = 0) -> Typer:
    """Cross-entropy by Adam, in place on a copy."""
    out, adam, rng = t.copy(), Adam(lr), np.random.default_rng(seed)
    w = out.weights()
    for _ in range(epochs):
        order = rng.permutation(len(y))
        for k in range(0, len(order), batch):
            pick = order[k : k + batch]
            adam.update(w, gradients(out, x[pick], y[pick]))
    return out


def fit_to_plateau(t: Typer, x: np.ndarray, y: np.ndarray, tolerance: float = 0.02, most: int = 30, seed: int = 0) -> Typer:
    """Train until an epoch lowers the loss by less than `tolerance` of it."""
    last = t.loss(x, y)
    for k in range(most):
        t = fit(t, x, y, epochs=1, batch=16, seed=seed + k)
        now = t.loss(x, y)
        if k > 2 and last - now < tolerance * last:
            break
        last = now
    return t


def contrastive(t: Typer, a: np.ndarray, b: np.ndarray, epochs: int = 2, batch: int = 64, heat: float = 0.2, lr: float = 1e-3, seed: int = 0) -> Typer:
    """Pull two views of a column together in the hidden layer, push other columns of the batch away."""
    out, adam, rng = t.copy(), Adam(lr), np.random.default_rng(seed)
    w = out.weights()
    for _ in range(epochs):
        order = rng.permutation(len(a))
        for k in range(0, len(order) - 1, batch):
            pick = order[k : k + batch]
            ha, hb = out.hidden(a[pick]), out.hidden(b[pick])
            na, nb = (np.linalg.norm(h, axis=1, keepdims=True) + 1e-9 for h in (ha, hb))
            za, zb = ha / na, hb / nb
            p = softmax(za @ zb.T / heat)
            d = (p - np.eye(len(pick))) / (heat * len(pick))
            ga, gb = d @ zb, d.T @ za
            ga, gb = ((g - (g * z).sum(1, keepdims=True) * z) / n * (1 - h * h) for g, z, n, h in ((ga, za, na, ha), (gb, zb, nb, hb)))
            adam.update({k: w[k] for k in ("w1", "b1")}, {"w1": a[pick].T @ ga + b[pick].T @ gb, "b1": ga.sum(0) + gb.sum(0)})
    return out


def score(columns: DataFrame, typer: Typer, with_hidden: bool = True) -> DataFrame:
    """columns(column_id, features) -> column_id, pred, phi, hidden: one Arrow pass, weights broadcast."""
    sent = columns.sparkSession.sparkContext.broadcast(typer)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        t = sent.value
        for batch in batches:
            if not len(batch):
                continue
            h = t.hidden(rows_of(batch.column("features")))
            p = softmax(h @ t.w2 + t.b2)
            best = p.argmax(1)
            out = [batch.column("column_id"), pa.array([t.types[k] for k in best], pa.string()), pa.array(p.max(1))]
            names = ["column_id", "pred", "phi"]
            if with_hidden:
                out.append(pa.array(list(h), pa.list_(pa.float64())))
                names.append("hidden")
            yield pa.RecordBatch.from_arrays(out, names)

    schema = "column_id string, pred string, phi double" + (", hidden array<double>" if with_hidden else "")
    return columns.select("column_id", "features").mapInArrow(run, schema)


def fit_distributed(labelled: DataFrame, t: Typer, steps: int = 20, lr: float = 2e-2) -> Typer:
    """Full-batch Adam over labelled(features, type_name) of any size: weights out, summed gradients back, each step.

    For source lakes beyond one task; a task sends one gradient (the size of the model), however many rows it reads.
    """
    out, adam = t.copy(), Adam(lr)
    w = out.weights()
    rows = labelled.where(labelled["type_name"].isin(list(t.types))).select("features", "type_name")
    spark = labelled.sparkSession

    for _ in range(steps):
        sent = spark.sparkContext.broadcast(out)

        def run(batches: Iterator[pa.RecordBatch], sent=sent) -> Iterator[pa.RecordBatch]:
            model, total, n = sent.value, None, 0
            for batch in batches:
                x = rows_of(batch.column("features"))
                if not len(x):
                    continue
                own = gradients(model, x, model.encode_types(batch.column("type_name").to_pylist()))
                total = {k: v * len(x) + (total[k] if total else 0.0) for k, v in own.items()}
                n += len(x)
            if total:
                yield pa.RecordBatch.from_arrays([pa.array(list(total)), pa.array([v.ravel() for v in total.values()], pa.list_(pa.float64())), pa.array([n] * len(total))], ["name", "sums", "n"])

        parts = rows.mapInArrow(run, "name string, sums array<double>, n long").toArrow().to_pylist()  # one model per task
        if not parts:
            break
        whole = {k: sum(np.array(p["sums"]) for p in parts if p["name"] == k) / sum(p["n"] for p in parts if p["name"] == k) for k in w}
        adam.update(w, {k: g.reshape(w[k].shape) for k, g in whole.items()})
        sent.unpersist()
    return out


def blocked(labelled: DataFrame, types: tuple[str, ...], size: int = BLOCK_COLUMNS) -> DataFrame:
    """labelled(column_id, type_name, ...) of these types as blocks of about `size` columns, dealt by a hash: as many as the
    columns need, each whole in one partition and in id order."""
    rows = labelled.where(F.col("type_name").isin(list(types)))
    n = max(1, -(-rows.count() // size))
    parts = min(n, 4 * labelled.sparkSession.sparkContext.defaultParallelism)
    dealt = rows.withColumn("block", (draw("block", "column_id") % n).cast("int"))
    return dealt.repartitionById(parts, F.col("block") % parts).sortWithinPartitions("block", "column_id")


def train_blocks(blocks: DataFrame, t: Typer, step: Callable[[Typer, dict[str, np.ndarray]], Typer], columns: tuple[str, ...] = ("features",)) -> tuple[Typer, float]:
    """Each block trains a copy of t by `step`, which gets its vectors by name and its types as `y`. Returned are the mean of
    the copies, weighted by columns, and the loss of t itself. A task sends one sum of models, however many blocks it reads."""
    sent = blocks.sparkSession.sparkContext.broadcast(t)

    def whole(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.Table]:
        last, held = None, []
        for batch in batches:
            at = batch.column("block").to_numpy()
            cuts = [0, *(np.flatnonzero(at[1:] != at[:-1]) + 1).tolist(), len(at)]
            for a, b in zip(cuts, cuts[1:]):
                if b > a:
                    if held and at[a] != last:
                        yield pa.Table.from_batches(held)
                        held = []
                    held.append(batch.slice(a, b - a))
                    last = at[a]
        if held:
            yield pa.Table.from_batches(held)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        model, total, n, loss = sent.value, None, 0, 0.0
        for block in whole(batches):
            got = {c: np.concatenate([rows_of(x) for x in block.column(c).chunks]) for c in columns}
            got["y"] = model.encode_types(block.column("type_name").to_pylist())
            loss += model.loss(got[columns[0]], got["y"]) * len(block)
            own = step(model, got).weights()
            total = {k: v * len(block) + (total[k] if total else 0.0) for k, v in own.items()}
            n += len(block)
        if total:
            yield pa.RecordBatch.from_arrays([pa.array(list(total)), pa.array([v.ravel() for v in total.values()], pa.list_(pa.float64())), pa.array([n] * len(total)), pa.array([loss] * len(total))], ["name", "sums", "n", "loss"])

    parts = blocks.select("block", "type_name", *columns).mapInArrow(run, "name string, sums array<double>, n long, loss double").toArrow()  # one model per task
    sent.unpersist()
    if not len(parts):
        return t, float("inf")
    names, sums = np.array(parts.column("name").to_pylist()), parts.column("sums").combine_chunks()
    first = names == names[0]
    n, loss = parts.column("n").to_numpy()[first].sum(), parts.column("loss").to_numpy()[first].sum()
    mean = {k: sum(sums[int(j)].values.to_numpy() for j in np.flatnonzero(names == k)) / n for k in t.weights()}
    return Typer(t.types, *(mean[k].reshape(v.shape) for k, v in t.weights().items())), float(loss / n)


def fit_blocks(labelled: DataFrame, t: Typer, tolerance: float = 0.02, most: int = 30, seed: int = 0, size: int = BLOCK_COLUMNS) -> Typer:
    """`fit_to_plateau` on labelled(column_id, features, type_name) of any size. An epoch trains every block from the same
    weights and goes on with their mean, so that all columns count alike and an epoch's time does not grow with the blocks if
    the cores do. A lake of one block is trained just as `fit_to_plateau` does."""
    blocks = blocked(labelled.select("column_id", "features", "type_name"), t.types, size).persist(StorageLevel.MEMORY_AND_DISK)
    last = float("inf")
    try:
        for k in range(most):
            new, now = train_blocks(blocks, t, lambda m, b, k=k: fit(m, b["features"], b["y"], epochs=1, batch=16, seed=seed + k))
            if k > 3 and last - now < tolerance * last:
                break
            t, last = new, now
        return t
    finally:
        blocks.unpersist()
