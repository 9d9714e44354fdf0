"""Lake queries: building, statistics, type sets, splits, serialising and features."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from lakeadapt.functions import features
from lakeadapt.session import REGISTRY, table
from lakeadapt.sources import catalog, lake

_LAKE = lake.oracle_columns()


@REGISTRY.entry(_LAKE)
def lake_columns(spark: SparkSession, sf_dir: str) -> DataFrame:
    return lake.flat(lake.build(spark, sf_dir))


REGISTRY.add(
    "lake_stats",
    lambda spark, d: lake.stats(lake.build(spark, d)),
    f"""WITH c AS ({_LAKE}), t AS (SELECT lake, table_id, count(*) AS w FROM c GROUP BY ALL)
    SELECT lake, count(DISTINCT type_name) AS n_types, count(DISTINCT table_id) AS n_tables, count(*) AS n_columns,
           round(count(*) / count(DISTINCT table_id), 6) AS mean_width FROM c GROUP BY lake""",
)
REGISTRY.add(
    "lake_splits",
    lambda spark, d: lake.build(spark, d).groupBy("lake", "split").agg(F.countDistinct("table_id").alias("n_tables"), F.count("*").alias("n_columns")),
    f"SELECT lake, split, count(DISTINCT table_id) AS n_tables, count(*) AS n_columns FROM ({_LAKE}) GROUP BY ALL",
)


def _values(types: tuple[str, ...]) -> str:
    return ", ".join(f"('{t}')" for t in types)


def _regions_sql() -> str:
    parts = [
        f"""SELECT '{x.name}' AS transfer, coalesce(s.t, g.t) AS type_name,
        CASE WHEN g.t IS NULL THEN 'source_only' WHEN s.t IS NULL THEN 'target_only' ELSE 'shared' END AS region
        FROM (VALUES {_values(x.source)}) s(t) FULL JOIN (VALUES {_values(x.target)}) g(t) ON s.t = g.t"""
        for x in catalog.TRANSFERS
    ]
    return " UNION ALL ".join(parts)


def _regions(spark: SparkSession, sf_dir: str) -> DataFrame:
    from lakeadapt.operators import typesets

    out = None
    for x in catalog.TRANSFERS:
        one = typesets.regions(typesets.typeset(spark, x.source), typesets.typeset(spark, x.target)).select(F.lit(x.name).alias("transfer"), "type_name", "region")
        out = one if out is None else out.unionByName(one)
    return out


REGISTRY.add("type_regions", _regions, _regions_sql())


def _overlap(spark: SparkSession, sf_dir: str) -> DataFrame:
    from lakeadapt.operators import typesets

    return typesets.overlap(_regions(spark, sf_dir))


REGISTRY.add(
    "type_overlap",
    _overlap,
    f"""SELECT transfer, count(*) FILTER (region = 'shared') AS shared,
    round(count(*) FILTER (region = 'shared') / count(*) FILTER (region <> 'target_only'), 6) AS share_of_source,
    round(count(*) FILTER (region = 'shared') / count(*) FILTER (region <> 'source_only'), 6) AS share_of_target,
    count(*) FILTER (region = 'source_only') = 0 AS pure_extension FROM ({_regions_sql()}) GROUP BY transfer""",
)
def _granularity(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Coarse: the status of an order; finer: status and priority. Orders in progress are no source type, the lowest priority no target type."""
    from lakeadapt.operators import typesets

    pairs = table(spark, sf_dir, "orders").select(F.col("o_orderstatus").alias("coarse"), F.concat_ws("/", "o_orderstatus", "o_orderpriority").alias("fine")).distinct()
    source = pairs.where("coarse <> 'P'").select(F.col("coarse").alias("type_name")).distinct()
    return typesets.granularity(pairs, source, pairs.where("fine NOT LIKE '%5-LOW'").select(F.col("fine").alias("type_name")))


REGISTRY.add(
    "type_granularity",
    _granularity,
    """SELECT coarse, count(*) AS children, string_agg(fine, ',' ORDER BY fine) AS fine FROM (SELECT DISTINCT o_orderstatus AS coarse, concat_ws('/', o_orderstatus, o_orderpriority) AS fine FROM orders)
    WHERE coarse <> 'P' AND fine NOT LIKE '%5-LOW' GROUP BY coarse""",
)
REGISTRY.add(
    "serialize_cells",
    lambda spark, d: lake.build(spark, d).select("column_id", features.serialize("cells", 24).alias("tokens")),
    f"SELECT column_id, array_to_string(list_slice(string_split(replace(cells, chr(31), ' '), ' '), 1, 24), ' ') AS tokens FROM ({_LAKE})",
)
_CELLS = f"SELECT column_id, unnest(string_split(cells, chr(31))) AS cell FROM ({_LAKE})"


@REGISTRY.entry(
    f"""SELECT column_id, count(*) AS n_cells, round(avg(length(cell)), 6) AS mean_length, max(length(cell)) AS max_length,
    round(sum(length(regexp_replace(cell, '[^0-9]', '', 'g'))) / sum(length(cell)), 6) AS digit_share,
    round(sum(length(regexp_replace(cell, '[^A-Za-z]', '', 'g'))) / sum(length(cell)), 6) AS letter_share,
    round(count(DISTINCT cell) / count(*), 6) AS distinct_share,
    round(avg(CASE WHEN try_cast(cell AS DOUBLE) IS NOT NULL THEN 1.0 ELSE 0.0 END), 6) AS number_share FROM ({_CELLS}) GROUP BY column_id"""
)
def shape_features(spark: SparkSession, sf_dir: str) -> DataFrame:
    return features.shape_stats(lake.build(spark, sf_dir))


@REGISTRY.entry(
    f"""SELECT column_id, CAST(CAST('0x' || substr(md5(substr(cell, CAST(i AS INTEGER), 2)), 1, 8) AS BIGINT) % 256 AS INTEGER) AS bucket, count(*) AS n
    FROM (SELECT column_id, cell, unnest(range(1, length(cell))) AS i FROM ({_CELLS})) GROUP BY ALL"""
)
def gram_buckets(spark: SparkSession, sf_dir: str) -> DataFrame:
    return features.gram_buckets(lake.build(spark, sf_dir), 2, 256)
