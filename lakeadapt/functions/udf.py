"""What a user calls: SQL functions over cells, a table function over any table, vector aggregates."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import Column, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.udtf import AnalyzeArgument, AnalyzeResult

from lakeadapt.functions.features import vector_of
from lakeadapt.operators.typer import Typer


def column_type(spark: SparkSession, typer: Typer):
    """col_type(cells) -> type name: an Arrow-batched function with the model broadcast once."""
    sent = spark.sparkContext.broadcast(typer)

    @F.pandas_udf("string")
    def col_type(batches: Iterator[pd.Series]) -> Iterator[pd.Series]:
        t = sent.value
        for cells in batches:
            x = np.stack([vector_of(list(c) if c is not None else []) for c in cells]).astype(np.float64) if len(cells) else np.zeros((0, t.w1.shape[0]))
            yield pd.Series([t.types[k] for k in t.predict(x)[0]])

    return col_type


@F.pandas_udf(T.ArrayType(T.DoubleType()))
def vec_mean(vectors: pd.Series) -> list[float]:
    """Mean of vectors; groups are gathered, so use functions.vectors.mean_by for large ones."""
    return np.stack(vectors).mean(axis=0).tolist()


def table_function(typer: Typer, max_cells: int = 16):
    """SELECT * FROM typed_columns(TABLE(t)): column, type and confidence from the first cells of any table."""
    class TypedColumns:
        @staticmethod
        def analyze(rows: AnalyzeArgument) -> AnalyzeResult:
            return AnalyzeResult(schema=T.StructType().add("column", "string").add("type", "string").add("phi", "double"), withSinglePartition=True)

        def __init__(self):
            self.cells: dict[str, list[str]] = {}

        def eval(self, row):
            for name, value in row.asDict().items():
                own = self.cells.setdefault(name, [])
                if value is not None and len(own) < max_cells:
                    own.append(str(value))

        def terminate(self):
            for name, own in self.cells.items():
                best, phi = typer.predict(vector_of(own)[None, :].astype(np.float64))
                yield name, typer.types[best[0]], float(phi[0])

    return F.udtf(TypedColumns)


def register(spark: SparkSession, typer: Typer) -> None:
    """SQL surface: col_type(cells) and typed_columns(TABLE(...))."""
    spark.udf.register("col_type", column_type(spark, typer))
    spark.udtf.register("typed_columns", table_function(typer))


def sampled(cells: Column, n: int = 16) -> Column:
    return F.slice(cells, 1, n)
