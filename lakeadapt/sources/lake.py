"""Lakes of small tables, cut from the given ones: one row per column.

Every table is read once. A row goes to the shard that its hash names, and a shard is a small table: there are as many as
the rows need (ROWS_A_SHARD each), so a lake holds every row and its tables stay short at any scale. A table shows about
half of its columns, drawn by a hash, as the columns of real lakes are only partly annotated: its siblings then do not
give a column away. Columns without any cell are left
out. Cells are whole; encoders and prompts take as many of them as they need.
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from lakeadapt.session import table
from lakeadapt.sources.catalog import GROUPS, Group

ROWS_A_SHARD, LEAST_SHARDS, SHOWN_PERCENT = 10, 12, 50
#: Cells that a prompt holds, and characters of each.
PROMPT_CELLS, PROMPT_CHARS = 16, 200


def hash8(expr: str, spark: bool) -> str:
    """The first 32 bits of an md5, as SQL of either engine."""
    return f"CAST(conv(substr(md5({expr}), 1, 8), 16, 10) AS BIGINT)" if spark else f"CAST('0x' || substr(md5({expr}), 1, 8) AS BIGINT)"


def rendered(g: Group, spark: bool) -> list[str]:
    """The cells of a row, by the parity of its shard. Arrays count from 0 in Spark and from 1 in DuckDB."""
    fix = (lambda s: s.replace("embedding[1]", "embedding[0]")) if spark else (lambda s: s)
    return [f"CASE WHEN shard % 2 = 0 THEN {fix(c.plain)} ELSE {fix(c.shifted)} END AS c{k}" for k, c in enumerate(g.cells)]


def variant(g: Group) -> str:
    """SQL of either engine: the value of `by` that a row belongs to."""
    if g.by == "''":
        return "''"
    return f"CASE WHEN {g.by} IN ({', '.join(repr(v) for v in g.values)}) THEN {g.by} ELSE 'other' END"


def shards(n: str) -> str:
    return f"greatest({LEAST_SHARDS}, CAST(floor({n} / {ROWS_A_SHARD}) AS BIGINT))"


def shard_cells(spark: SparkSession, sf_dir: str, g: Group, odd: bool = False) -> DataFrame:
    """v, shard, k1, tie and the rendered cells c0, c1, ... of every row (of those in odd shards): one scan, no shuffle."""
    rows = table(spark, sf_dir, g.table)
    placed = rows.selectExpr("*", f"{variant(g)} AS v", hash8(f"concat('{g.name}:', {g.key})", True) + " AS h", f"CAST({g.key} AS STRING) AS tie")
    if g.repeats:
        placed = placed.withColumn("shard", F.explode(F.sequence(F.lit(0), F.lit(LEAST_SHARDS - 1)))).withColumn("k1", F.expr("md5(concat(shard, ':', tie))"))
    else:
        if len(g.values) == 1:
            counts = {"": rows.count()}  # from the footers
        else:
            counts = {r["v"]: r["count"] for r in rows.groupBy(F.expr(variant(g)).alias("v")).count().collect()}  # one row a value
        sizes = F.expr("CASE v " + " ".join(f"WHEN '{v}' THEN {n}" for v, n in sorted(counts.items())) + " END") if counts else F.lit(0)
        placed = placed.withColumn("n", sizes).withColumn("shard", F.expr(f"CAST(h % {shards('n')} AS INT)")).withColumn("k1", F.lpad(F.col("h").cast("string"), 12, "0"))
    placed = placed.where("shard % 2 = 1") if odd else placed
    return placed.selectExpr("v", "shard", "k1", "tie", *rendered(g, True))


def table_name(g: Group, v: str) -> str:
    """SQL of either engine."""
    return f"'{g.name}/'" if g.by == "''" else f"concat('{g.name}-', {v}, '/')"


def shown(column_id: str, spark: bool) -> str:
    return f"{hash8(f'concat({chr(39)}shown:{chr(39)}, {column_id})', spark)} % 100 < {SHOWN_PERCENT}"


def build_group(spark: SparkSession, sf_dir: str, g: Group, odd: bool = False) -> DataFrame:
    """The columns of one group. The plan is given as SQL text: built call by call, 14 groups keep the driver busy for seconds."""
    names = [f"c{k}" for k in range(len(g.cells))]
    gathered = shard_cells(spark, sf_dir, g, odd).groupBy("v", "shard").agg(F.count("*").alias("n_rows"), F.expr(f"array_sort(collect_list(struct(k1, tie, {', '.join(names)}))) AS x"))
    every = [
        f"named_struct('position', {k}, 'cells', filter(transform(x, r -> r.{n}), c -> c IS NOT NULL), 'type_name', '{c.type_name}', 'coarse', {f"'{c.coarse}'" if c.coarse is not None else 'CAST(NULL AS STRING)'})"
        for k, (n, c) in enumerate(zip(names, g.cells))
    ]
    long = gathered.selectExpr("v", f"concat({table_name(g, 'v')}, CAST(shard AS STRING)) AS table_id", "n_rows", f"explode(array({', '.join(every)})) AS e")
    return long.selectExpr(
        "concat(table_id, '#', CAST(e.position AS STRING)) AS column_id", "table_id", f"'{g.name}' AS source_table", "e.position", "n_rows", "e.cells",
        "replace(e.type_name, '{}', v) AS type_name", "e.coarse",
    ).where(f"size(cells) > 0 AND {shown('column_id', True)}")


def build(spark: SparkSession, sf_dir: str, groups: tuple[Group, ...] = GROUPS, sources: tuple[str, ...] | None = None) -> DataFrame:
    """All columns of both lakes: even shards (`lake` = source) rendered plainly, odd ones (target) shifted. With `sources`,
    only these groups have source columns; the even shards of the others are then never gathered."""
    parts = [build_group(spark, sf_dir, g, sources is not None and g.name not in sources) for g in groups]
    whole = reduce(DataFrame.unionByName, parts)
    return whole.withColumn("lake", F.when(F.split("table_id", "/")[1].cast("int") % 2 == 0, "source").otherwise("target")).withColumn("split", split_of("table_id"))


def split_of(table_id: str):
    """Test 10 %, then validation to training 1 : 4; whole tables, so that siblings stay together."""
    bucket = F.expr(hash8(f"concat('split:', {table_id})", True)) % 100
    return F.when(bucket < 10, "test").when(bucket < 28, "valid").otherwise("train")


def oracle_columns(groups: tuple[Group, ...] = GROUPS) -> str:
    """DuckDB: column_id, table_id, position, n_rows, cells joined by chr(31), type_name, lake, split."""
    parts = []
    for g in groups:
        h = hash8(f"'{g.name}:' || CAST({g.key} AS VARCHAR)", False)
        base = f"SELECT *, {variant(g)} AS v, {h} AS h, CAST({g.key} AS STRING) AS tie FROM {g.table}"
        if g.repeats:
            placed = f"SELECT *, md5(CAST(shard AS VARCHAR) || ':' || tie) AS k1 FROM (SELECT *, unnest(range(0, {LEAST_SHARDS})) AS shard FROM ({base}))"
        else:
            placed = f"SELECT *, h % {shards('n')} AS shard, lpad(CAST(h AS VARCHAR), 12, '0') AS k1 FROM (SELECT *, count(*) OVER (PARTITION BY v) AS n FROM ({base}))"
        cells = f"SELECT v, shard, k1, tie, {', '.join(rendered(g, False))} FROM ({placed})"
        for k, c in enumerate(g.cells):
            kind = "replace('" + c.type_name + "', '{}', v)"
            parts.append(
                f"SELECT {table_name(g, 'v')} || shard AS table_id, {k} AS position, count(*) AS n_rows, coalesce(string_agg(c{k}, chr(31) ORDER BY k1, tie), '') AS cells, "
                f"{kind} AS type_name FROM ({cells}) GROUP BY v, shard"
            )
    h = hash8("'split:' || table_id", False)
    return f"""
SELECT column_id, table_id, CAST(position AS INTEGER) AS position, CAST(n_rows AS BIGINT) AS n_rows, cells, type_name,
       CASE WHEN CAST(split_part(table_id, '/', 2) AS INTEGER) % 2 = 0 THEN 'source' ELSE 'target' END AS lake,
       CASE WHEN {h} % 100 < 10 THEN 'test' WHEN {h} % 100 < 28 THEN 'valid' ELSE 'train' END AS split
FROM (SELECT table_id || '#' || position AS column_id, * FROM ({" UNION ALL ".join(parts)})) WHERE cells <> '' AND {shown("column_id", False)}"""


def flat(cols: DataFrame) -> DataFrame:
    return cols.select("column_id", "table_id", "position", "n_rows", F.array_join("cells", "\x1f").alias("cells"), "type_name", "lake", "split")


def for_prompt(cells: str = "cells") -> Column:
    """As many cells as a prompt holds, each cut to a length: the token limit of a judge."""
    return F.transform(F.slice(cells, 1, PROMPT_CELLS), lambda c: F.substring(c, 1, PROMPT_CHARS))


def stats(cols: DataFrame) -> DataFrame:
    """Per lake: types, tables, annotated columns, mean width."""
    return cols.groupBy("lake").agg(
        F.countDistinct("type_name").alias("n_types"), F.countDistinct("table_id").alias("n_tables"), F.count("*").alias("n_columns"),
        F.round(F.count("*") / F.countDistinct("table_id"), 6).alias("mean_width"),
    )
