"""Streams around the method: columns typed on arrival, drift watched, labels bought under a quota."""

from __future__ import annotations

from collections.abc import Iterator
from typing import Any

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from lakeadapt.operators.typer import Typer, score


def arrivals(spark: SparkSession, folder: str, schema: T.StructType | str, files_per_batch: int = 1) -> DataFrame:
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", files_per_batch).parquet(folder)


def typed(stream: DataFrame, typer: Typer) -> DataFrame:
    """Stateless scoring: the same Arrow pass as in batch."""
    return score(stream, typer, with_hidden=False)


def drift(stream: DataFrame, at: str = "ts", late: str = "1 hour", width: str = "1 day", slide: str | None = None, value: str = "phi", delta: float = 0.9) -> DataFrame:
    """Per window: rows, mean confidence, share under the threshold. Rows later than the watermark are dropped."""
    window = F.window(at, width, slide) if slide else F.window(at, width)
    return stream.withWatermark(at, late).groupBy(window.alias("w")).agg(
        F.count("*").alias("n"), F.avg(value).alias("mean"), F.avg((F.col(value) < delta).cast("double")).alias("gated")
    ).select(F.col("w.start").alias("start"), "n", "mean", "gated")


def sessions(stream: DataFrame, key: str, at: str = "ts", gap: str = "6 hours", late: str = "1 hour") -> DataFrame:
    return stream.withWatermark(at, late).groupBy(key, F.session_window(at, gap).alias("w")).agg(F.count("*").alias("n")).select(key, F.col("w.start").alias("start"), "n")


def without_replays(stream: DataFrame, keys: list[str], at: str = "ts", late: str = "1 hour") -> DataFrame:
    return stream.withWatermark(at, late).dropDuplicatesWithinWatermark(keys)


def decided_in_time(columns: DataFrame, decisions: DataFrame, late: str = "2 hours") -> DataFrame:
    """Column arrivals with the decision made within an hour: an interval join of two streams."""
    a = columns.withWatermark("arrived", late).alias("a")
    b = decisions.withWatermark("decided", late).alias("b")
    within = F.expr("a.column_id = b.column_id AND b.decided >= a.arrived AND b.decided <= a.arrived + INTERVAL 1 HOUR")
    return a.join(b, within).select(F.col("a.column_id").alias("column_id"), "arrived", "decided", "decision")


def with_catalogue(stream: DataFrame, catalogue: DataFrame, on: str) -> DataFrame:
    """Stream-static join: the catalogue is read again for every batch."""
    return stream.join(catalogue, on, "left")


QUOTA_SCHEMA = "type_name string, column_id string, granted boolean, left long"


def type_quota(stream: DataFrame, quota: int) -> DataFrame:
    """type_name, column_id -> granted: each type buys at most `quota` labels, in order of arrival (state: one number a type)."""
    def step(key: tuple, frames: Iterator[pd.DataFrame], state: Any) -> Iterator[pd.DataFrame]:
        left = state.get[0] if state.exists else quota
        for f in frames:
            ids = sorted(f["column_id"])
            granted = [k < left for k in range(len(ids))]
            left = max(0, left - len(ids))
            yield pd.DataFrame({"type_name": key[0], "column_id": ids, "granted": granted, "left": left})
        state.update((left,))

    return stream.select("type_name", "column_id").groupBy("type_name").applyInPandasWithState(step, QUOTA_SCHEMA, "left long", "append", "NoTimeout")


def into_table(stream: DataFrame, path: str, checkpoint: str):
    """Every batch goes to its own partition, so writing one again after a failure changes nothing."""
    def put(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(f"{path}/batch={number}")

    return stream.writeStream.foreachBatch(put).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()
