"""Run folders: the trace, models and written stages of an adaptation, in storage that all machines share."""

from __future__ import annotations

import json
import tempfile
import uuid
from dataclasses import dataclass

import numpy as np
from pyspark.sql import DataFrame, SparkSession

TRACE = "iter int, stage string, column_id string"
_OWN: dict[str, str] = {}
#: Bytes of a row group of a written table.
ROW_GROUP = 8 << 20


def shared_folder(spark: SparkSession) -> str:
    """spark.checkpoint.dir; where it is unset, a folder in the warehouse, or a temporary one if everything runs in this process."""
    given = spark.conf.get("spark.checkpoint.dir", None)
    if given:
        return given.rstrip("/")
    if not spark.sparkContext.master.startswith("local"):
        return f"{spark.conf.get('spark.sql.warehouse.dir').rstrip('/')}/_intermediate"
    app = spark.sparkContext.applicationId
    if app not in _OWN:
        _OWN[app] = "file://" + tempfile.mkdtemp(prefix="lakeadapt-run-")
    return _OWN[app]


def written(df: DataFrame, tag: str, by: tuple[str, ...] = ()) -> DataFrame:
    """df as a table in the shared folder: cuts its lineage, survives lost executors, and goes when the session ends. Rows of
    one value of `by` lie together, so that a pass over some of these reads no others. A file can only be shared between tasks
    by its row groups: small ones keep all cores busy."""
    spark = df.sparkSession
    folder = f"{shared_folder(spark)}/lakeadapt/{spark.sparkContext.applicationId}-lakes"
    if folder not in _OWN:
        path = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(folder)
        files = path.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration())
        files.mkdirs(path)
        files.deleteOnExit(path)
        _OWN[folder] = folder
    path = f"{folder}/{tag}-{uuid.uuid4().hex}"
    df.write.partitionBy(*by).option("parquet.block.size", ROW_GROUP).parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


@dataclass(frozen=True)
class RunStore:
    """Trace and models partitioned by iteration; writing an iteration again replaces it and nothing else."""

    spark: SparkSession
    path: str

    @classmethod
    def new(cls, spark: SparkSession) -> RunStore:
        return cls(spark, f"{shared_folder(spark)}/lakeadapt/run-{uuid.uuid4().hex}")

    def save(self, iteration: int, rows: list[tuple[str, str]], model: dict[str, np.ndarray], state: dict) -> None:
        trace = self.spark.createDataFrame([(k, stage, c) for k, (stage, c) in enumerate(rows)], "pos int, stage string, column_id string")
        trace.coalesce(1).write.mode("overwrite").parquet(f"{self.path}/trace/iter={iteration}")
        blob = [(k, v.astype(np.float64).ravel().tolist(), list(v.shape)) for k, v in model.items()]
        self.spark.createDataFrame(blob, "name string, weights array<double>, shape array<long>").coalesce(1).write.mode("overwrite").parquet(f"{self.path}/model/iter={iteration}")
        self.spark.createDataFrame([(json.dumps(state),)], "state string").coalesce(1).write.mode("overwrite").parquet(f"{self.path}/state/iter={iteration}")

    def trace(self) -> DataFrame:
        return self.spark.read.parquet(f"{self.path}/trace")

    def traced(self, upto: int) -> list[tuple[int, str, str]]:
        """The trace of iterations 0..upto in its order: a probe and a batch each, so a bounded list."""
        kept = self.trace().where(f"iter <= {upto}").collect()
        return [(r["iter"], r["stage"], r["column_id"]) for r in sorted(kept, key=lambda r: (r["iter"], r["pos"]))]

    def last(self) -> tuple[int, dict[str, np.ndarray], dict] | None:
        """The last iteration that was written whole: its number, model and state."""
        try:
            states = self.spark.read.parquet(f"{self.path}/state")
        except Exception as missing:  # noqa: BLE001
            if "PATH_NOT_FOUND" in str(missing):
                return None
            raise
        row = states.orderBy(states["iter"].desc()).limit(1).collect()[0]
        weights = self.spark.read.parquet(f"{self.path}/model/iter={row['iter']}").collect()
        return row["iter"], {r["name"]: np.array(r["weights"]).reshape(r["shape"]) for r in weights}, json.loads(row["state"])
