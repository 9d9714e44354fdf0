"""Column encoders: what stands in for a pre-trained one. Values only; names never enter."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

GRAMS, SHAPES = 256, 10
WIDTH = GRAMS + SHAPES


def serialize(cells: str, max_tokens: int = 128) -> Column:
    """The cells as one token sequence, cut at max_tokens."""
    return F.array_join(F.slice(F.split(F.array_join(cells, " "), " "), 1, max_tokens), " ")


def shape_stats(cols: DataFrame) -> DataFrame:
    """Lengths, character classes, distinctness and numeric share of each column, in SQL functions."""
    cells = cols.select("column_id", F.explode("cells").alias("cell"))
    count = lambda pattern: F.sum(F.length(F.regexp_replace("cell", pattern, "")))
    chars = F.sum(F.length("cell"))
    return cells.groupBy("column_id").agg(
        F.count("*").alias("n_cells"),
        F.round(F.avg(F.length("cell")), 6).alias("mean_length"),
        F.max(F.length("cell")).alias("max_length"),
        F.round(count("[^0-9]") / chars, 6).alias("digit_share"),
        F.round(count("[^A-Za-z]") / chars, 6).alias("letter_share"),
        F.round(F.countDistinct("cell") / F.count("*"), 6).alias("distinct_share"),
        F.round(F.avg(F.when(F.expr("try_cast(cell AS double)").isNotNull(), 1.0).otherwise(0.0)), 6).alias("number_share"),
    )


def gram_buckets(cols: DataFrame, n: int, buckets: int) -> DataFrame:
    """Character n-grams of each column hashed to buckets, with counts. One pass of a pattern cuts a cell: asking for the k-th
    character would walk the cell from its start each time, which long texts cannot afford."""
    cells = cols.select("column_id", F.explode("cells").alias("cell")).where(F.length("cell") >= n)
    grams = cells.select("column_id", F.explode(F.regexp_extract_all("cell", F.lit(rf"(?s)(?=(.{{{n}}}))."), F.lit(1))).alias("gram"))
    bucket = (F.conv(F.substring(F.md5("gram"), 1, 8), 16, 10).cast("long") % buckets).cast("int")
    return grams.groupBy("column_id", bucket.alias("bucket")).agg(F.count("*").alias("n"))


def _codes(text: str) -> np.ndarray:
    return np.frombuffer(text.encode("utf-32-le", "surrogatepass"), np.uint32).astype(np.uint64)


def vector_of(cells: list[str], word_level: bool = False) -> np.ndarray:
    """Hashed 1..3-grams (or words) of the cells, normalised, and ten numbers on their shape."""
    cells = [c for c in cells if c is not None]
    joined = "\n".join(cells)
    out = np.zeros(WIDTH, np.float32)
    codes = _codes(joined)
    if word_level:
        hashes = [np.array([_word_hash(w) for w in joined.lower().split()], np.uint64)]
    else:
        hashes, acc = [], np.zeros(len(codes), np.uint64)
        for n in range(3):
            acc = acc[: len(codes) - n] * np.uint64(1000003) + codes[n:] + np.uint64(7919 * (n + 1))
            hashes.append((acc ^ (acc >> np.uint64(17))) * np.uint64(0x9E3779B97F4A7C15) >> np.uint64(40))
    for h in hashes:
        np.add.at(out, (h % np.uint64(GRAMS)).astype(np.int64), 1.0)
    norm = np.linalg.norm(out)
    out /= norm or 1.0
    lengths = np.array([len(c) for c in cells] or [0], np.float32)
    chars = max(1, len(codes))
    numbers = [x for x in map(_number, cells) if x is not None]
    magnitude = np.log1p(np.abs(numbers)) if numbers else np.zeros(1)
    out[GRAMS:] = [
        lengths.mean() / 20, lengths.std() / 20, ((codes >= 48) & (codes <= 57)).sum() / chars, ((codes | 32) >= 97).sum() / chars, (codes == 32).sum() / chars,
        len(set(cells)) / max(1, len(cells)), len(numbers) / max(1, len(cells)), magnitude.mean() / 10, magnitude.std() / 5, (codes > 127).sum() / chars,
    ]
    return out


#: Characters of columns that are encoded at once.
PIECE = 1 << 20


def lists_of(column: pa.Array) -> list[list[str]]:
    """The cells of an Arrow batch; its texts become Python's in one go, not list by list."""
    flat, at = column.flatten().to_numpy(zero_copy_only=False).tolist(), np.concatenate([[0], np.cumsum(column.value_lengths().fill_null(0).to_numpy())]).tolist()
    return [flat[a:b] for a, b in zip(at, at[1:])]


def vectors_of(columns: list[list[str]]) -> np.ndarray:
    """`vector_of` (n-grams) of many columns at once, to the last bit: n-grams are counted over all texts end to end, and
    numbers are averaged together over columns that have equally many."""
    out, start, size = [np.zeros((0, WIDTH), np.float32)], 0, 0
    kept = [[c for c in cells if c is not None] for cells in columns]
    joined = ["\n".join(cells) for cells in kept]
    for k, text in enumerate(joined):
        size += len(text)
        if size >= PIECE or k + 1 == len(joined):
            out.append(_piece(kept[start : k + 1], joined[start : k + 1]))
            start, size = k + 1, 0
    return np.concatenate(out)


def _piece(kept: list[list[str]], joined: list[str]) -> np.ndarray:
    n = len(joined)
    sizes = np.array([len(t) for t in joined], np.int64)
    codes = _codes("".join(joined))
    row = np.repeat(np.arange(n), sizes)
    left = np.repeat(np.cumsum(sizes), sizes) - np.arange(len(codes))  # characters from here to the end of the column
    counts, acc = np.zeros(n * GRAMS, np.int64), np.zeros(len(codes), np.uint64)
    for k in range(3):
        acc = acc[: len(codes) - k] * np.uint64(1000003) + codes[k:] + np.uint64(7919 * (k + 1))
        within = left[: len(acc)] > k
        h = (acc ^ (acc >> np.uint64(17))) * np.uint64(0x9E3779B97F4A7C15) >> np.uint64(40)
        counts += np.bincount((row[: len(acc)] * GRAMS + (h % np.uint64(GRAMS)).astype(np.int64))[within], minlength=n * GRAMS)
    out = np.zeros((n, WIDTH), np.float32)
    out[:, :GRAMS] = counts.reshape(n, GRAMS)
    norm = np.sqrt(np.array([v.dot(v) for v in out], np.float32))
    out /= np.where(norm, norm, np.float32(1))[:, None]
    chars, low = np.maximum(1, sizes), codes | np.uint64(32)
    share = lambda mask: np.bincount(row[mask], minlength=n) / chars
    out[:, GRAMS + 2], out[:, GRAMS + 3] = share((codes >= 48) & (codes <= 57)), share(low >= 97)
    out[:, GRAMS + 4], out[:, GRAMS + 9] = share(codes == 32), share(codes > 127)
    many = np.array([max(1, len(cells)) for cells in kept])
    numbers = [[x for x in map(_number, cells) if x is not None] for cells in kept]
    out[:, GRAMS + 5], out[:, GRAMS + 6] = np.array([len(set(cells)) for cells in kept]) / many, np.array([len(x) for x in numbers]) / many
    mean, std = _moments([[len(c) for c in cells] or [0] for cells in kept], np.float32)
    out[:, GRAMS], out[:, GRAMS + 1] = mean / 20, std / 20
    mean, std = _moments([x or [0.0] for x in numbers], np.float64, lambda x: np.log1p(np.abs(x)))
    out[:, GRAMS + 7], out[:, GRAMS + 8] = mean / 10, std / 5
    return out


def _moments(rows: list[list[float]], kind: type, change: Callable[[np.ndarray], np.ndarray] = lambda x: x) -> tuple[np.ndarray, np.ndarray]:
    """Mean and standard deviation of each row, taken together over rows of one length."""
    length = np.array([len(r) for r in rows], np.int64)
    mean, std = np.zeros(len(rows), kind), np.zeros(len(rows), kind)
    for w in np.unique(length):
        at = np.flatnonzero(length == w)
        x = change(np.array([rows[k] for k in at], kind))
        mean[at], std[at] = x.mean(1), x.std(1)
    return mean, std


def _word_hash(word: str) -> int:
    h = 1469598103934665603
    for b in word.encode("utf-8", "surrogatepass"):
        h = (h ^ b) * 1099511628211 % (1 << 64)
    return h


def _number(cell: str) -> float | None:
    if cell[:1].isalpha():  # a word, nan or inf
        return None
    try:
        x = float(cell.replace(",", "."))
        return x if np.isfinite(x) else None
    except ValueError:
        return None


def encode(cols: DataFrame, word_level: bool = False, packed: bool = False) -> DataFrame:
    """cols -> the same columns plus features array<float>, an Arrow batch at a time. Packed features are the bytes of the
    same numbers: a pass over a lake then copies a column whole, not number by number."""
    names = [c for c in cols.columns]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            cells = lists_of(batch.column("cells"))
            vectors = np.array([vector_of(c, True) for c in cells], np.float32).reshape(-1, WIDTH) if word_level else vectors_of(cells)
            yield pa.RecordBatch.from_arrays([*batch.columns, packed_array(vectors) if packed else pa.array(list(vectors), pa.list_(pa.float32()))], [*names, "features"])

    schema = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in cols.schema) + f", features {'binary' if packed else 'array<float>'}"
    return cols.mapInArrow(run, schema)


def packed_array(x: np.ndarray) -> pa.Array:
    """The rows of a matrix as binary values, one copy for all."""
    x = np.ascontiguousarray(x)
    offsets = np.arange(len(x) + 1, dtype=np.int64) * x.shape[1] * x.itemsize
    if offsets[-1] >= 1 << 31:
        return pa.array([v.tobytes() for v in x], pa.binary())
    return pa.Array.from_buffers(pa.binary(), len(x), [None, pa.py_buffer(offsets.astype(np.int32)), pa.py_buffer(x)])


def rows_of(column: pa.Array, kind: str = "<f4", width: int | None = None) -> np.ndarray:
    """Features of an Arrow batch, as lists of numbers or packed, as a matrix in double precision. With a `width`, a packed
    value may hold several rows."""
    if not len(column):
        return np.zeros((0, width or 0))
    if pa.types.is_binary(column.type) or pa.types.is_large_binary(column.type):
        size = np.dtype(kind).itemsize
        at = np.frombuffer(column.buffers()[1], np.int64 if pa.types.is_large_binary(column.type) else np.int32)[column.offset : column.offset + len(column) + 1]
        flat = np.frombuffer(column.buffers()[2], kind, int(at[-1] - at[0]) // size, int(at[0]))
    else:
        flat = column.flatten().to_numpy(zero_copy_only=False)
    return flat.reshape(-1, width or len(flat) // len(column)).astype(np.float64, copy=False)


def row_of(value: bytes | list[float]) -> np.ndarray:
    """The same of one value that reached the driver."""
    return np.frombuffer(value, "<f4") if isinstance(value, bytes | bytearray) else np.array(value)
