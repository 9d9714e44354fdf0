"""Context that the three backbones add to a column: its siblings (J), a second view (C), related tables (R)."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from lakeadapt.functions.draws import draw
from lakeadapt.functions.features import vector_of
from lakeadapt.functions.vectors import mean_by


def sibling_mean(value: str) -> Column:
    """Mean of a number over the other columns of the table; 0 without siblings."""
    w = Window.partitionBy("table_id")
    n = F.count("*").over(w)
    return F.when(n > 1, (F.sum(value).over(w) - F.col(value)) / (n - 1)).otherwise(0.0)


def joint(columns: DataFrame) -> DataFrame:
    """features -> + siblings: the mean vector of the other columns. A table is one group: as many rows as it has columns."""
    def one(t: pd.DataFrame) -> pd.DataFrame:
        x = np.stack(t["features"]).astype(np.float64)
        rest = (x.sum(0) - x) / max(1, len(x) - 1)
        return pd.DataFrame({"column_id": t["column_id"], "siblings": list(rest.astype(np.float32))})

    added = columns.select("column_id", "table_id", "features").groupBy("table_id").applyInPandas(one, "column_id string, siblings array<float>")
    return columns.join(added, "column_id")


def view(cells: str, which: str) -> Column:
    """One of two views of a column: a seeded half of its cells (all of them if the half is empty), in hash order."""
    half = F.filter(F.transform(cells, lambda c, i: F.struct(draw(which, c, i).alias("h"), c.alias("c"))), lambda e: e["h"] % 2 == 0)
    ordered = F.transform(F.array_sort(half), lambda e: e["c"])
    return F.when(F.size(ordered) > 0, ordered).otherwise(F.col(cells))


def two_views(columns: DataFrame) -> DataFrame:
    """+ view_a, view_b: vectors of the two halves."""
    @F.pandas_udf("array<float>")
    def encoded(cells: pd.Series) -> pd.Series:
        return cells.map(lambda c: vector_of(list(c)))

    return columns.withColumn("view_a", encoded(view("cells", "a"))).withColumn("view_b", encoded(view("cells", "b")))



def signatures(columns: DataFrame) -> DataFrame:
    """table_id -> signature: the sorted coarse shapes of its columns (numeric or not, short, middle or long)."""
    cell = columns.select("table_id", "position", F.explode_outer("cells").alias("cell"))
    shape = cell.groupBy("table_id", "position").agg(F.avg(F.when(F.expr("try_cast(cell AS double)").isNotNull(), 1.0).otherwise(0.0)).alias("num"), F.avg(F.length("cell")).alias("len"))
    code = F.concat(F.when(F.col("num") >= 0.5, "n").otherwise("s"), F.when(F.col("len") < 8, "1").when(F.col("len") < 32, "2").otherwise("3"))
    return shape.groupBy("table_id").agg(F.array_join(F.array_sort(F.collect_list(code)), ",").alias("signature"))


def related(columns: DataFrame) -> DataFrame:
    """features -> + relatives: the mean vector of the same place in all tables of the same signature (a hash join on the
    signature; per signature and place only sums are shuffled, so a common signature is no hot group)."""
    signed = columns.join(signatures(columns), "table_id")
    means = mean_by(signed, ["signature", "position"], "features", "relatives")
    return signed.join(means, ["signature", "position"]).withColumn("relatives", F.col("relatives").cast("array<float>")).drop("signature")


def row_context(columns: DataFrame) -> DataFrame:
    """+ row_vector: the mean vector of the table's rows (the cells of one ordinal across its columns)."""
    cells = columns.select("table_id", "position", F.posexplode("cells").alias("row", "cell"))
    rows = cells.groupBy("table_id", "row").agg(F.array_join(F.transform(F.array_sort(F.collect_list(F.struct("position", "cell"))), lambda e: e["cell"]), " ").alias("line"))
    gathered = rows.groupBy("table_id").agg(F.transform(F.array_sort(F.collect_list(F.struct("row", "line"))), lambda e: e["line"]).alias("lines"))

    @F.pandas_udf("array<float>")
    def encoded(lines: pd.Series) -> pd.Series:
        return lines.map(lambda x: np.mean([vector_of([line]) for line in x], axis=0).astype(np.float32))

    return columns.join(gathered.select("table_id", encoded("lines").alias("row_vector")), "table_id")
