"""Type sets: regions, overlap, granularity."""

from __future__ import annotations

from collections.abc import Iterable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def typeset(spark: SparkSession, types: Iterable[str]) -> DataFrame:
    return spark.createDataFrame([(t,) for t in sorted(set(types))], "type_name string")


def regions(source: DataFrame, target: DataFrame) -> DataFrame:
    """type_name, region: source_only, shared or target_only. One hash join over both sets."""
    s, t = source.select("type_name", F.lit(True).alias("_s")), target.select("type_name", F.lit(True).alias("_t"))
    region = F.when(F.col("_t").isNull(), "source_only").when(F.col("_s").isNull(), "target_only").otherwise("shared")
    return s.join(t, "type_name", "full_outer").select("type_name", region.alias("region"))


def overlap(region_rows: DataFrame) -> DataFrame:
    """transfer, region rows -> shared types, their share of each set, and whether nothing must be forgotten."""
    n = lambda cond: F.count_if(cond)
    r = F.col("region")
    return region_rows.groupBy("transfer").agg(
        n(r == "shared").alias("shared"),
        F.round(n(r == "shared") / n(r != "target_only"), 6).alias("share_of_source"),
        F.round(n(r == "shared") / n(r != "source_only"), 6).alias("share_of_target"),
        (n(r == "source_only") == 0).alias("pure_extension"),
    )


def granularity(pairs: DataFrame, source: DataFrame, target: DataFrame) -> DataFrame:
    """Coarse source types with the finer target types they cover: a boundary to learn again, not to copy."""
    known = pairs.join(F.broadcast(source.withColumnRenamed("type_name", "coarse")), "coarse").join(F.broadcast(target.withColumnRenamed("type_name", "fine")), "fine")
    return known.groupBy("coarse").agg(F.count("*").alias("children"), F.array_join(F.array_sort(F.collect_set("fine")), ",").alias("fine"))
