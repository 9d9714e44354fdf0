"""What the corpus operators share: written tables, dense row numbers, components, word splitting."""

from __future__ import annotations

import gc
import tempfile
import uuid
from collections.abc import Iterator
from contextlib import contextmanager

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

#: ASCII white space, the only separators of the words used here.
WORD = r"[^\x20\x09-\x0D]+"
SPACE = r"[\x20\x09-\x0D]+"

_OWN: dict[str, str] = {}
_RUN: list[str] = []


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share: spark.checkpoint.dir; where it is unset, a folder in the warehouse, or a
    temporary one if everything runs in this process."""
    set_ = spark.conf.get("spark.checkpoint.dir", None)
    if set_:
        return set_.rstrip("/")
    if not spark.sparkContext.master.startswith("local"):
        return f"{spark.conf.get('spark.sql.warehouse.dir').rstrip('/')}/_intermediate"
    app = spark.sparkContext.applicationId
    if app not in _OWN:
        _OWN[app] = f"file://{tempfile.mkdtemp(prefix='lakeadapt-')}"
    return _OWN[app]


def _path(spark: SparkSession, folder: str):
    jvm = spark.sparkContext._jvm
    path = jvm.org.apache.hadoop.fs.Path(folder)
    return path, path.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration())


def new_path(spark: SparkSession, tag: str) -> str:
    """A new place for an intermediate table. It goes when the session ends, or before that with its `scratch`."""
    app = f"{shared_dir(spark)}/lakeadapt/{spark.sparkContext.applicationId}"
    if app not in _OWN:
        path, files = _path(spark, app)
        files.mkdirs(path)
        files.deleteOnExit(path)
        _OWN[app] = app
    return "/".join([app, *_RUN, f"{tag}-{uuid.uuid4().hex}"])


@contextmanager
def scratch(spark: SparkSession, tag: str) -> Iterator[None]:
    """Intermediates that are written inside are deleted at the end: what is kept must be a table written outside by then."""
    _RUN.append(f"{tag}-{uuid.uuid4().hex}")
    try:
        yield
    finally:
        path, files = _path(spark, "/".join([f"{shared_dir(spark)}/lakeadapt/{spark.sparkContext.applicationId}", *_RUN]))
        _RUN.pop()
        files.delete(path, True)


def store(df: DataFrame, path: str) -> DataFrame:
    """Write df to path and read it back."""
    df.write.option("compression", "zstd").parquet(path)
    out = df.sparkSession.read.schema(df.schema).parquet(path)
    out._stored_at = path
    return out


def discard(*tables: DataFrame) -> None:
    """Delete intermediate tables that nothing will read again, and let go of finished shuffles: executors delete their
    files once the driver has collected what refers to them."""
    for t in tables:
        path, files = _path(t.sparkSession, t._stored_at)
        files.delete(path, True)
    gc.collect()
    tables[0].sparkSession.sparkContext._jvm.System.gc()


def materialize(df: DataFrame, tag: str) -> DataFrame:
    """Write df to the shared folder and read it back: cuts the lineage and survives lost executors."""
    return store(df, new_path(df.sparkSession, tag))


def task_count(df: DataFrame, mb: int = 256) -> int:
    """Shuffle partitions, and more where a task would get over `mb` of the input: by the size that the optimizer knows, which
    is that of the files. A plan without a known size (Spark then assumes the largest number) keeps the setting."""
    size = int(df._jdf.queryExecution().optimizedPlan().stats().sizeInBytes())
    return max(int(df.sparkSession.conf.get("spark.sql.shuffle.partitions")), -(-size // (mb << 20)) if size < 1 << 60 else 0)


def utf8_bytes(text: str | Column) -> Column:
    """Bytes of a text in UTF-8, 0 for null."""
    return F.coalesce(F.octet_length(F.col(text) if isinstance(text, str) else text), F.lit(0)).cast("long")


def cut_points(df: DataFrame, column: str, parts: int, accuracy: int = 10_000) -> list[int]:
    """At most parts - 1 ascending values that cut `column` into about even ranges (a sketch: few numbers come back)."""
    if parts < 2:
        return []
    at = [i / parts for i in range(1, parts)]
    row = df.agg(F.percentile_approx(column, at, accuracy).alias("q")).head()
    return sorted({int(x) for x in (row["q"] or [])})


def range_bucket(column: Column, cuts: list[int]) -> Column:
    """Number of cut points below the value; nulls go to bucket 0, before everything else."""
    def node(lo: int, hi: int) -> Column:
        # a binary search over literals, as nested CASEs: stays in generated code
        if lo == hi:
            return F.lit(lo)
        mid = (lo + hi) // 2
        return F.when(column <= F.lit(cuts[mid]), node(lo, mid)).otherwise(node(mid + 1, hi))

    return F.when(column.isNull(), F.lit(0)).otherwise(node(0, len(cuts)))


def number_rows(df: DataFrame, order: list[str], out: str, rows_a_range: int = 1_000_000) -> tuple[DataFrame, int]:
    """Dense numbers from 0 in the order of some columns, nulls first; also the row count. `df` should be slim: it is written.

    Ranges of about `rows_a_range` rows are numbered side by side, and one count per range reaches the driver. The row's
    place in the input comes last in the order, so that a range may begin inside a run of equal rows, however long.
    """
    spark = df.sparkSession
    ranges = max(int(spark.conf.get("spark.sql.shuffle.partitions")), -(-df.count() // rows_a_range))
    by = [*[F.col(c).asc_nulls_first() for c in order], F.col("_place").asc()]
    dealt = df.withColumn("_place", F.monotonically_increasing_id()).repartitionByRange(ranges, *by)
    dealt = materialize(dealt.withColumn("_range", F.spark_partition_id()), "ranges")
    sizes = {r["_range"]: r["n"] for r in dealt.groupBy("_range").agg(F.count("*").alias("n")).collect()}
    starts, total = [], 0
    for k in sorted(sizes):
        starts.append((k, total))
        total += sizes[k]
    offsets = spark.createDataFrame(starts or [(0, 0)], "_range int, _start long")
    own = F.row_number().over(Window.partitionBy("_range").orderBy(*by))
    numbered = dealt.withColumn("_own", own).join(F.broadcast(offsets), "_range")
    return numbered.withColumn(out, F.col("_start") + F.col("_own") - 1).drop("_range", "_own", "_start", "_place"), total


def components(edges: DataFrame) -> DataFrame:
    """edges(a long, b long), undirected -> (node, component): the smallest node reachable.

    Each round every node moves to its smallest neighbour's smallest neighbour and the edges follow; the image of a
    connected graph stays connected and its smallest node never moves, so what is left at the end is that node. The
    node count at least halves in each round. Rounds are written to the shared folder.
    """
    def undirected(e: DataFrame) -> DataFrame:
        e = e.where("a <> b")
        return e.select("a", "b").union(e.select(F.col("b").alias("a"), F.col("a").alias("b"))).distinct()

    links = materialize(undirected(edges), "links")
    labels = links.select(F.col("a").alias("node"), F.col("a").alias("component")).distinct()
    step = 0
    while not links.isEmpty():
        to = materialize(links.groupBy("a").agg(F.least(F.col("a"), F.min("b")).alias("p")), f"parents{step}")
        far = to.select(F.col("a").alias("p"), F.col("p").alias("g"))
        jump = materialize(to.join(far, "p", "left").select("a", F.coalesce("g", "p").alias("g")), f"jump{step}")
        as_b = jump.select(F.col("a").alias("b"), F.col("g").alias("h"))
        moved = links.where("a < b").join(jump, "a").join(as_b, "b").select(F.col("g").alias("a"), F.col("h").alias("b"))
        links = materialize(undirected(moved), f"links{step}")
        move = jump.select(F.col("a").alias("component"), "g")
        labels = materialize(
            labels.join(move, "component", "left").select("node", F.coalesce("g", "component").alias("component")),
            f"labels{step}",
        )
        step += 1
    return labels


def of_type(df: DataFrame, wanted: dict[str, str]) -> DataFrame:
    """Only the named columns, each cast to its type: extra columns of any name are out of the way."""
    return df.select(*[F.col(f"`{c}`").cast(t).alias(c) for c, t in wanted.items()])


def sliced(batches: Iterator[pa.RecordBatch], rows: int = 1000) -> Iterator[pa.RecordBatch]:
    """The same rows in smaller batches: what a worker holds at a time."""
    for batch in batches:
        for k in range(0, batch.num_rows, rows):
            yield batch.slice(k, rows)
