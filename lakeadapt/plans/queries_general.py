"""Queries of the operators around the method: scans, joins, windows, sets, functions, and what backbones, baselines and
judges take from a lake. Each has its SQL beside it."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window as W

from lakeadapt.baselines.relational import nearest_answer, own_words
from lakeadapt.functions.draws import draw, smallest, sql_draw
from lakeadapt.functions.vectors import cosine, dot, norm
from lakeadapt.operators import backbones, gap, joins, process
from lakeadapt.plans.queries_core import TARGET, scored
from lakeadapt.plans.queries_core import sql as core
from lakeadapt.session import REGISTRY, table
from lakeadapt.sources import catalog, lake

add = REGISTRY.add
_LAKE = lake.oracle_columns()
_cells = lake.build
_PRED = "e src tgt hs fresh ht sc pr"

# -- process, judge ---------------------------------------------------------------------------------------------------
_PROPOSED = f"SELECT *, CASE WHEN {sql_draw('propose', 'column_id')} % 3 = 0 THEN 'event_kind' ELSE type_name END AS pred FROM ({_LAKE})"


def _proposed(s: SparkSession, d: str) -> DataFrame:
    return _cells(s, d).withColumn("pred", F.when(draw("propose", "column_id") % 3 == 0, "event_kind").otherwise(F.col("type_name")))


_KB = ", ".join("('" + t + "', '" + p.replace("'", "''") + f"', {m})" for t, p, m in catalog.KNOWLEDGE)
add("rule_judge", lambda s, d: gap.knowledge_judge(_proposed(s, d)).select("column_id", "pred", "decision"), f"""
    WITH c AS ({_PROPOSED}), x AS (SELECT column_id, pred, unnest(string_split(cells, chr(31))) AS cell FROM c), kb(t, p, m) AS (VALUES {_KB}),
    f AS (SELECT column_id, pred, t, avg(CASE WHEN regexp_matches(cell, p) THEN 1.0 ELSE 0.0 END) >= any_value(m) AS ok FROM x, kb GROUP BY column_id, pred, t)
    SELECT column_id, pred, CASE WHEN bool_or(t = pred AND ok) THEN 'yes' WHEN bool_or(t = pred) OR bool_or(t <> pred AND ok) THEN 'no' ELSE 'unknown' END AS decision FROM f GROUP BY column_id, pred""")
_TYPES = sorted(catalog.fine_types())
_IN_PROMPT = f"array_to_string(list_transform(list_slice(string_split(cells, chr(31)), 1, {lake.PROMPT_CELLS}), lambda x: substr(x, 1, {lake.PROMPT_CHARS})), '; ')"
add("judge_prompt", lambda s, d: _proposed(s, d).select("column_id", F.md5(gap.prompt(_TYPES, "cells", "pred")).alias("digest")), f"""SELECT column_id, md5('You check a proposed type for a table column. Reply with one word: yes, no or unknown.' || chr(10) || 'Types: {", ".join(_TYPES)}' || chr(10) || 'Values: ' || {_IN_PROMPT} || chr(10) || 'Proposed: ' || pred) AS digest FROM ({_PROPOSED})""")
add("prompt_words", lambda s, d: _proposed(s, d).select("column_id", F.size(F.split(gap.prompt(_TYPES, "cells", "pred"), " ")).cast("long").alias("n_words")), f"""SELECT column_id, len(string_split('You check a proposed type for a table column. Reply with one word: yes, no or unknown.' || chr(10) || 'Types: {", ".join(_TYPES)}' || chr(10) || 'Values: ' || {_IN_PROMPT} || chr(10) || 'Proposed: ' || pred, ' ')) AS n_words FROM ({_PROPOSED})""")
_ASK = f"SELECT column_id FROM ({_LAKE}) ORDER BY {sql_draw('ask', 'column_id')}, column_id LIMIT 40"


def _label_batch(s: SparkSession, d: str) -> DataFrame:
    cols = _cells(s, d)
    return process.GroundTruth(cols.select("column_id", "type_name"), budget=30).label(smallest(cols.select("column_id"), 40, "ask", "column_id"))


add("label_batch", _label_batch, f"SELECT column_id, type_name FROM ({_LAKE}) WHERE column_id IN (SELECT column_id FROM ({_ASK}) ORDER BY column_id LIMIT 30)")
add("heuristic_process", lambda s, d: process.heuristic(_cells(s, d)), f"""SELECT column_id, CASE WHEN bool_and(cell LIKE '%@%' OR cell LIKE 'http%') THEN 'web_address' WHEN bool_and(cell LIKE '{{%}}') THEN 'json_props' WHEN bool_and(regexp_matches(cell, '^[0-9]+$')) THEN 'record_key' WHEN bool_and(try_cast(replace(cell, ',', '.') AS DOUBLE) IS NOT NULL) THEN 'money_amount' ELSE 'name' END AS label
    FROM (SELECT column_id, unnest(string_split(cells, chr(31))) AS cell FROM ({_LAKE})) GROUP BY column_id""")
add("redact_cells", lambda s, d: table(s, d, "documents").select("doc_id", F.md5(gap.redact(F.col("text"))).alias("digest")), r"""SELECT doc_id, md5(regexp_replace(regexp_replace(regexp_replace(regexp_replace(text, '[A-Za-z0-9._%+-]+@[A-Za-z0-9.-]+\.[A-Za-z]{2,}', '<mail>', 'g'), '\b[0-9]{1,3}(\.[0-9]{1,3}){3}\b', '<ip>', 'g'), '\b[0-9a-f]{32,}\b', '<hex>', 'g'), '\b[0-9]{12,}\b', '<digits>', 'g')) AS digest FROM documents""")

# -- backbones, baselines ---------------------------------------------------------------------------------------------
_WIDE = f"SELECT column_id, table_id, CAST(n_cells AS DOUBLE) AS v FROM (SELECT column_id, table_id, length(cells) AS n_cells FROM ({_LAKE}))"
add("joint_context", lambda s, d: _cells(s, d).withColumn("v", F.length(F.array_join("cells", "\x1f")).cast("double")).select("column_id", F.round(backbones.sibling_mean("v"), 6).alias("siblings")), f"SELECT column_id, round(coalesce((sum(v) OVER (PARTITION BY table_id) - v) / nullif(count(*) OVER (PARTITION BY table_id) - 1, 0), 0), 6) AS siblings FROM ({_WIDE})")
_VIEW = f"SELECT column_id, cells, unnest(string_split(cells, chr(31))) AS c, unnest(range(0, len(string_split(cells, chr(31))))) AS i FROM ({_LAKE})"
add("augment_views", lambda s, d: _cells(s, d).select("column_id", F.array_join(backbones.view("cells", "a"), "|").alias("view")), f"""SELECT column_id, coalesce(string_agg(c, '|' ORDER BY h, c) FILTER (h % 2 = 0), replace(any_value(cells), chr(31), '|')) AS view FROM (SELECT *, {sql_draw('a', 'c', 'i')} AS h FROM ({_VIEW})) GROUP BY column_id""")
_SIGN = f"""SELECT table_id, string_agg(code, ',' ORDER BY code) AS signature FROM (SELECT table_id, position, CASE WHEN avg(CASE WHEN try_cast(cell AS DOUBLE) IS NOT NULL THEN 1.0 ELSE 0.0 END) >= 0.5 THEN 'n' ELSE 's' END || CASE WHEN avg(length(cell)) < 8 THEN '1' WHEN avg(length(cell)) < 32 THEN '2' ELSE '3' END AS code
    FROM (SELECT table_id, position, unnest(string_split(cells, chr(31))) AS cell FROM ({_LAKE})) GROUP BY ALL) GROUP BY table_id"""
add("related_tables", lambda s, d: backbones.signatures(_cells(s, d)).groupBy("signature").agg(F.count("*").alias("n_tables"), F.min("table_id").alias("first_table")), f"SELECT signature, count(*) AS n_tables, min(table_id) AS first_table FROM ({_SIGN}) GROUP BY signature")
_KBK = ", ".join("(" + str(k) + ", '" + t + "', '" + p.replace("'", "''") + f"', {m})" for k, (t, p, m) in enumerate(catalog.KNOWLEDGE))
add("direct_annotator", lambda s, d: own_words(_cells(s, d)), f"""
    WITH x AS (SELECT column_id, unnest(string_split(cells, chr(31))) AS cell, cells = '' AS none FROM ({_LAKE})), kb(k, t, p, m) AS (VALUES {_KBK}),
    f AS (SELECT column_id, k, t, avg(CASE WHEN regexp_matches(cell, p) THEN 1.0 ELSE 0.0 END) >= any_value(m) AND NOT any_value(none) AS ok FROM x, kb GROUP BY column_id, k, t)
    SELECT column_id, coalesce(arg_min(CASE WHEN {sql_draw('word', 't')} % 100 < 25 THEN upper(t) ELSE t END, k) FILTER (ok), 'unlisted') AS pred FROM f GROUP BY column_id""")
_V = "SELECT vec_id, label, unnest(range(0, 64)) AS dim, unnest(CAST(embedding AS DOUBLE[])) AS x FROM embeddings"
_NEAR = f"""WITH v AS ({_V}), d AS (SELECT a.vec_id AS query, b.vec_id AS found, any_value(b.label) AS label, round(sum(a.x * b.x) / sqrt(sum(a.x * a.x)) / sqrt(sum(b.x * b.x)), 9) AS sim FROM v a JOIN v b ON a.dim = b.dim AND a.vec_id % 20 = 0 AND a.vec_id <> b.vec_id GROUP BY a.vec_id, b.vec_id),
    r AS (SELECT *, row_number() OVER (PARTITION BY query ORDER BY sim DESC, found) AS k FROM d) """


def _vecs(s: SparkSession, d: str) -> DataFrame:
    return table(s, d, "embeddings").select("vec_id", "label", F.col("embedding").cast("array<double>").alias("hidden"))


add("knn_exact", lambda s, d: joins.knn(_vecs(s, d).where("vec_id % 20 = 0"), _vecs(s, d), 3).select("query", "found", F.col("k").cast("long").alias("k")), _NEAR + "SELECT query, found, k FROM r WHERE k <= 3")
add("knn_annotator", lambda s, d: nearest_answer(_vecs(s, d).where("vec_id % 20 = 0"), _vecs(s, d), 0.4), _NEAR + "SELECT query, CASE WHEN sim >= 0.4 THEN 't' || label ELSE 'unlisted' END AS pred FROM r WHERE k = 1")
add("knn_lsh", lambda s, d: joins.knn_lsh(_vecs(s, d).where("vec_id % 20 = 0"), _vecs(s, d), 3))

# -- scans, projections, joins ----------------------------------------------------------------------------------------
add("scan_pruned", lambda s, d: table(s, d, "lineitem").where("l_shipdate >= '1998-06-01' AND l_quantity > 45").select("l_orderkey", "l_linenumber"), "SELECT l_orderkey, l_linenumber FROM lineitem WHERE l_shipdate >= '1998-06-01' AND l_quantity > 45")


def _surface(s: SparkSession, d: str) -> DataFrame:
    return s.sql("SELECT c_mktsegment, count(*) AS n, round(sum(o_totalprice), 2) AS total FROM {orders} JOIN {customer} ON o_custkey = c_custkey GROUP BY c_mktsegment", orders=table(s, d, "orders"), customer=table(s, d, "customer"))


add("sql_surface", _surface, "SELECT c_mktsegment, count(*) AS n, round(sum(o_totalprice), 2) AS total FROM orders JOIN customer ON o_custkey = c_custkey GROUP BY c_mktsegment")
add("render_cells", lambda s, d: table(s, d, "orders").select("o_orderkey", F.concat_ws("|", *[F.col(c).cast("string") for c in ("o_custkey", "o_orderstatus", "o_totalprice", "o_orderdate")]).alias("cells")), "SELECT o_orderkey, concat_ws('|', CAST(o_custkey AS VARCHAR), o_orderstatus, CAST(o_totalprice AS VARCHAR), CAST(o_orderdate AS VARCHAR)) AS cells FROM orders")
add("filter_predicates", lambda s, d: table(s, d, "lineitem").where("l_quantity BETWEEN 10 AND 20 AND l_returnflag IN ('A', 'R') AND l_linestatus <=> 'F' AND l_discount NOT IN (0.05)").select("l_orderkey", F.expr("CASE WHEN l_tax > 0.04 THEN 'high' ELSE 'low' END").alias("tax")), "SELECT l_orderkey, CASE WHEN l_tax > 0.04 THEN 'high' ELSE 'low' END AS tax FROM lineitem WHERE l_quantity BETWEEN 10 AND 20 AND l_returnflag IN ('A', 'R') AND l_linestatus IS NOT DISTINCT FROM 'F' AND l_discount NOT IN (0.05)")
add("unpivot_cells", lambda s, d: table(s, d, "supplier").select("s_suppkey", F.col("s_name").alias("name"), F.col("s_nationkey").cast("string").alias("nation")).unpivot("s_suppkey", ["name", "nation"], "position", "cell"), "SELECT s_suppkey, 'name' AS position, s_name AS cell FROM supplier UNION ALL SELECT s_suppkey, 'nation', CAST(s_nationkey AS VARCHAR) FROM supplier")
add("truth_join", lambda s, d: scored(s, d).join(F.broadcast(s.createDataFrame([(t, k) for k, t in enumerate(TARGET)], "pred string, type_id long")), "pred").groupBy("type_id").agg(F.count("*").alias("n")), core(_PRED, "SELECT CAST(substr(pred, 2) AS BIGINT) - 3 AS type_id, count(*) AS n FROM pr GROUP BY 1"))
add("smj_orders_lineitem", lambda s, d: table(s, d, "orders").hint("merge").join(table(s, d, "lineitem"), F.col("o_orderkey") == F.col("l_orderkey")).groupBy("o_orderpriority").agg(F.count("*").alias("n"), F.round(F.sum("l_quantity"), 2).alias("quantity")), "SELECT o_orderpriority, count(*) AS n, round(sum(l_quantity), 2) AS quantity FROM orders JOIN lineitem ON o_orderkey = l_orderkey GROUP BY o_orderpriority")
add("unseen_anti", lambda s, d: table(s, d, "customer").join(table(s, d, "orders").where("o_orderpriority = '1-URGENT'"), F.col("c_custkey") == F.col("o_custkey"), "left_anti").select("c_custkey"), "SELECT c_custkey FROM customer WHERE c_custkey NOT IN (SELECT o_custkey FROM orders WHERE o_orderpriority = '1-URGENT')")
add("seen_semi", lambda s, d: table(s, d, "customer").join(table(s, d, "orders").where("o_totalprice > 300000"), F.col("c_custkey") == F.col("o_custkey"), "left_semi").select("c_custkey"), "SELECT c_custkey FROM customer WHERE c_custkey IN (SELECT o_custkey FROM orders WHERE o_totalprice > 300000)")
add("theta_pairs", lambda s, d: table(s, d, "nation").alias("a").join(F.broadcast(table(s, d, "nation").alias("b")), F.expr("a.n_regionkey < b.n_regionkey AND a.n_nationkey > b.n_nationkey")).select(F.col("a.n_name").alias("x"), F.col("b.n_name").alias("y")), "SELECT a.n_name AS x, b.n_name AS y FROM nation a JOIN nation b ON a.n_regionkey < b.n_regionkey AND a.n_nationkey > b.n_nationkey")
_BANDS = [("low", 1000.0, 20000.0), ("mid", 15000.0, 50000.0), ("top", 50000.0, 1e9)]
add("range_join", lambda s, d: joins.in_ranges(table(s, d, "lineitem").select("l_orderkey", "l_extendedprice"), s.createDataFrame(_BANDS, "band string, lo double, hi double"), "l_extendedprice").groupBy("band").agg(F.count("*").alias("n")), "SELECT band, count(*) AS n FROM lineitem JOIN (VALUES ('low', 1000.0, 20000.0), ('mid', 15000.0, 50000.0), ('top', 50000.0, 1e9)) b(band, lo, hi) ON l_extendedprice >= lo AND l_extendedprice < hi GROUP BY band")
add("asof_model_version", lambda s, d: joins.as_of(table(s, d, "events").where("event_type = 'click'").select("event_id", "user_id", "ts"), table(s, d, "events").where("event_type = 'view'").select("user_id", "ts", F.col("event_id").alias("version")), "user_id", "ts", "version", "event_id"), "SELECT event_id, version FROM (SELECT event_id, user_id, ts FROM events WHERE event_type = 'click') c ASOF LEFT JOIN (SELECT user_id, ts, max(event_id) AS version FROM events WHERE event_type = 'view' GROUP BY ALL) v ON c.user_id = v.user_id AND c.ts >= v.ts")


def _lateral(s: SparkSession, d: str) -> DataFrame:
    return s.sql("SELECT n_name, c_custkey, c_acctbal FROM {nation}, LATERAL (SELECT c_custkey, c_acctbal FROM {customer} WHERE c_nationkey = n_nationkey ORDER BY c_acctbal DESC, c_custkey LIMIT 2)", nation=table(s, d, "nation"), customer=table(s, d, "customer"))


add("lateral_cells", _lateral, "SELECT n_name, c_custkey, c_acctbal FROM (SELECT *, row_number() OVER (PARTITION BY c_nationkey ORDER BY c_acctbal DESC, c_custkey) AS r FROM customer) JOIN nation ON c_nationkey = n_nationkey WHERE r <= 2")
add("dedup_columns", lambda s, d: _cells(s, d).groupBy(F.md5(F.array_join("cells", "\x1f")).alias("digest")).agg(F.min("column_id").alias("column_id"), F.count("*").alias("copies")), f"SELECT md5(cells) AS digest, min(column_id) AS column_id, count(*) AS copies FROM ({_LAKE}) GROUP BY 1")

# -- aggregates, windows, sets ----------------------------------------------------------------------------------------
_E = lambda s, d: table(s, d, "events")
add("agg_by_type", lambda s, d: _E(s, d).groupBy("event_type").agg(F.count("*").alias("n"), F.round(F.avg("value"), 6).alias("mean"), F.min("value").alias("lo"), F.max("value").alias("hi")), "SELECT event_type, count(*) AS n, round(avg(value), 6) AS mean, min(value) AS lo, max(value) AS hi FROM events GROUP BY event_type")
add("distinct_exact", lambda s, d: _E(s, d).groupBy("event_type").agg(F.countDistinct("user_id").alias("users")), "SELECT event_type, count(DISTINCT user_id) AS users FROM events GROUP BY event_type")
add("distinct_sketch", lambda s, d: _E(s, d).groupBy("event_type").agg(F.hll_sketch_agg("user_id").alias("h")).select("event_type", F.hll_sketch_estimate("h").alias("users")))
_O = lambda s, d: table(s, d, "orders")
add("metrics_rollup", lambda s, d: _O(s, d).rollup("o_orderstatus", "o_orderpriority").agg(F.count("*").alias("n"), F.grouping_id().alias("level")), "SELECT o_orderstatus, o_orderpriority, count(*) AS n, grouping_id(o_orderstatus, o_orderpriority) AS level FROM orders GROUP BY ROLLUP (o_orderstatus, o_orderpriority)")
add("metrics_cube", lambda s, d: _O(s, d).cube("o_orderstatus", "o_orderpriority").agg(F.round(F.avg("o_totalprice"), 4).alias("mean")), "SELECT o_orderstatus, o_orderpriority, round(avg(o_totalprice), 4) AS mean FROM orders GROUP BY CUBE (o_orderstatus, o_orderpriority)")
add("phi_quantiles", lambda s, d: scored(s, d).agg(*[F.round(F.percentile("phi", q / 100), 6).alias(f"q{q}") for q in (10, 50, 90)]), core(_PRED, "SELECT round(quantile_cont(phi, 0.1), 6) AS q10, round(quantile_cont(phi, 0.5), 6) AS q50, round(quantile_cont(phi, 0.9), 6) AS q90 FROM pr"))
add("mode_cell", lambda s, d: table(s, d, "customer").groupBy("c_nationkey", "c_mktsegment").count().groupBy("c_nationkey").agg(F.min(F.struct(-F.col("count"), "c_mktsegment")).alias("m")).select("c_nationkey", F.col("m.c_mktsegment").alias("segment")), "SELECT c_nationkey, arg_min(c_mktsegment, (-n, c_mktsegment)) AS segment FROM (SELECT c_nationkey, c_mktsegment, count(*) AS n FROM customer GROUP BY ALL) GROUP BY c_nationkey")
add("vector_mean", lambda s, d: table(s, d, "embeddings").select("label", F.posexplode(F.col("embedding").cast("array<double>")).alias("dim", "x")).groupBy("label", "dim").agg(F.round(F.avg("x"), 6).alias("mean")), "SELECT label, CAST(dim AS INTEGER) AS dim, round(avg(x), 6) AS mean FROM (SELECT label, unnest(range(0, 64)) AS dim, unnest(CAST(embedding AS DOUBLE[])) AS x FROM embeddings) GROUP BY ALL")
_by = lambda: W.partitionBy("c_nationkey").orderBy(F.col("c_acctbal").desc(), "c_custkey")
add("rank_types", lambda s, d: table(s, d, "customer").select("c_custkey", F.row_number().over(_by()).alias("r"), F.ntile(4).over(_by()).alias("q"), F.round(F.percent_rank().over(_by()), 6).alias("p")), "SELECT c_custkey, CAST(row_number() OVER w AS INTEGER) AS r, CAST(ntile(4) OVER w AS INTEGER) AS q, round(percent_rank() OVER w, 6) AS p FROM customer WINDOW w AS (PARTITION BY c_nationkey ORDER BY c_acctbal DESC, c_custkey)")
_ut = lambda: W.partitionBy("user_id").orderBy("ts", "event_id")
add("loss_lag", lambda s, d: _E(s, d).select("event_id", F.round(F.col("value") - F.lag("value").over(_ut()), 6).alias("change"), F.min("value").over(_ut().rowsBetween(W.unboundedPreceding, -1)).alias("best")), "SELECT event_id, round(value - lag(value) OVER w, 6) AS change, min(value) OVER (w ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS best FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)")
add("moving_phi", lambda s, d: _E(s, d).select("event_id", F.round(F.avg("value").over(_ut().rowsBetween(-4, 0)), 6).alias("mean5"), F.round(F.sum("value").over(_ut().rowsBetween(W.unboundedPreceding, 0)), 4).alias("running")), "SELECT event_id, round(avg(value) OVER (w ROWS BETWEEN 4 PRECEDING AND CURRENT ROW), 6) AS mean5, round(sum(value) OVER (w ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW), 4) AS running FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)")
add("topk_hash", lambda s, d: smallest(table(s, d, "part").select("p_partkey"), 50, "top", "p_partkey"), f"SELECT p_partkey FROM part ORDER BY {sql_draw('top', 'p_partkey')}, p_partkey LIMIT 50")


def _setops(s: SparkSession, d: str) -> DataFrame:
    a, b = (s.createDataFrame([(t,) for t in x], "type_name string") for x in (catalog.TX2.source, catalog.TX2.target))
    tag = lambda df, n: df.select(F.lit(n).alias("op"), "type_name")
    return tag(a.intersect(b), "both").union(tag(a.exceptAll(b), "first")).union(tag(b.subtract(a), "second"))


_list = lambda x: "(VALUES " + ", ".join(f"('{t}')" for t in x) + ") v(type_name)"
_A, _B = (f"SELECT type_name FROM {_list(x)}" for x in (catalog.TX2.source, catalog.TX2.target))
add("typeset_setops", _setops, f"SELECT 'both' AS op, type_name FROM ({_A} INTERSECT {_B}) UNION ALL SELECT 'first', type_name FROM ({_A} EXCEPT {_B}) UNION ALL SELECT 'second', type_name FROM ({_B} EXCEPT {_A})")

# -- functions --------------------------------------------------------------------------------------------------------
add("string_features", lambda s, d: table(s, d, "part").select("p_partkey", F.lower("p_name").alias("low"), F.size(F.split("p_name", " ")).cast("long").alias("words"), F.levenshtein("p_brand", "p_type").cast("long").alias("distance"), F.md5("p_name").alias("digest"), F.sha2("p_type", 256).alias("sha")), "SELECT p_partkey, lower(p_name) AS low, len(string_split(p_name, ' ')) AS words, levenshtein(p_brand, p_type) AS distance, md5(p_name) AS digest, sha256(p_type) AS sha FROM part")
_SPANS = {"mail": r"[A-Za-z0-9._]+@[A-Za-z0-9.]+", "ip": r"[0-9]{1,3}[.][0-9]{1,3}[.][0-9]{1,3}[.][0-9]{1,3}", "hex": r"[0-9a-f]{40}", "digits": r"[0-9]{16}"}
add("span_extract", lambda s, d: table(s, d, "documents").select("doc_id", *[F.size(F.regexp_extract_all("text", F.lit(p), 0)).cast("long").alias(k) for k, p in _SPANS.items()]), "SELECT doc_id, " + ", ".join(f"len(regexp_extract_all(text, '{p}')) AS {k}" for k, p in _SPANS.items()) + " FROM documents")
add("date_render", lambda s, d: _O(s, d).select("o_orderkey", F.date_format("o_orderdate", "dd/MM/yyyy").alias("day"), F.year("o_orderdate").cast("long").alias("year"), F.datediff(F.lit("1999-01-01"), "o_orderdate").cast("long").alias("age")), "SELECT o_orderkey, strftime(o_orderdate, '%d/%m/%Y') AS day, year(o_orderdate) AS year, date_diff('day', CAST(o_orderdate AS DATE), DATE '1999-01-01') AS age FROM orders")
add("dot_and_norm", lambda s, d: _vecs(s, d).select("vec_id", F.round(norm("hidden"), 6).alias("norm"), F.round(dot("hidden", F.transform("hidden", lambda x: x * 2)), 6).alias("dot"), F.round(cosine("hidden", F.reverse("hidden")), 6).alias("cosine")), f"WITH v AS ({_V}) SELECT a.vec_id AS vec_id, round(sqrt(sum(a.x * a.x)), 6) AS norm, round(sum(a.x * 2 * a.x), 6) AS dot, round(sum(a.x * b.x) / sum(a.x * a.x), 6) AS cosine FROM v a JOIN v b ON a.vec_id = b.vec_id AND a.dim = 63 - b.dim GROUP BY a.vec_id")
add("array_argmax", lambda s, d: _vecs(s, d).select("vec_id", (F.array_position("hidden", F.array_max("hidden")) - 1).alias("at"), F.round(F.array_max("hidden"), 6).alias("top")), f"WITH v AS ({_V}) SELECT vec_id, arg_min(dim, (-x, dim)) AS at, round(max(x), 6) AS top FROM v GROUP BY vec_id")
add("json_props", lambda s, d: _E(s, d).select("event_id", F.get_json_object("props", "$.k").cast("long").alias("k"), F.from_json("props", "map<string,int>")["k"].cast("long").alias("mapped")), "SELECT event_id, CAST(json_extract_string(props, '$.k') AS BIGINT) AS k, CAST(json_extract_string(props, '$.k') AS BIGINT) AS mapped FROM events")
add("html_titles", lambda s, d: table(s, d, "pages").select("page_id", F.regexp_extract("html", "<title>([^<]*)</title>", 1).alias("title"), F.size(F.regexp_extract_all("html", F.lit("<a href=\"[^\"]*\">[^<]*</a>"), 0)).cast("long").alias("links")), """SELECT page_id, regexp_extract(html, '<title>([^<]*)</title>', 1) AS title, len(regexp_extract_all(html, '<a href="[^"]*">[^<]*</a>')) AS links FROM pages""")


def _correlated(s: SparkSession, d: str) -> DataFrame:
    return s.sql(_CORRELATED, orders=table(s, d, "orders"), customer=table(s, d, "customer"))


_CORRELATED = "WITH big AS (SELECT o_custkey, sum(o_totalprice) AS t FROM {orders} GROUP BY o_custkey) SELECT c_custkey, (SELECT count(*) FROM {orders} WHERE o_custkey = c_custkey) AS n FROM {customer} WHERE EXISTS (SELECT 1 FROM big WHERE o_custkey = c_custkey AND t > (SELECT avg(t) FROM big))"
add("sql_correlated", _correlated, _CORRELATED.format(orders="orders", customer="customer"))
_RECURSIVE = "WITH RECURSIVE r(i, a) AS (SELECT 1, CAST(max(o_orderkey) AS BIGINT) FROM {orders} UNION ALL SELECT i + 1, CAST(floor(a / 2) AS BIGINT) FROM r WHERE a > 1) SELECT i, a FROM r"
add("sql_recursive", lambda s, d: s.sql(_RECURSIVE, orders=table(s, d, "orders")).select(F.col("i").cast("long").alias("i"), F.col("a").cast("long").alias("a")), f"SELECT CAST(i AS BIGINT) AS i, CAST(a AS BIGINT) AS a FROM ({_RECURSIVE.format(orders='orders')})")

# -- batch twins of the streams ---------------------------------------------------------------------------------------
add("tumbling_phi", lambda s, d: _E(s, d).groupBy(F.window(F.col("ts").cast("timestamp"), "1 day").alias("w")).agg(F.count("*").alias("n"), F.round(F.avg("value"), 6).alias("mean")).select(F.date_format("w.start", "yyyy-MM-dd").alias("day"), "n", "mean"), "SELECT strftime(ts, '%Y-%m-%d') AS day, count(*) AS n, round(avg(value), 6) AS mean FROM events GROUP BY 1")
add("sliding_phi", lambda s, d: _E(s, d).groupBy(F.window(F.col("ts").cast("timestamp"), "2 days", "1 day").alias("w")).agg(F.count("*").alias("n")).select(F.date_format("w.start", "yyyy-MM-dd").alias("day"), "n"), "SELECT strftime(CAST(ts AS DATE) - CAST(k AS INTEGER), '%Y-%m-%d') AS day, count(*) AS n FROM events, (SELECT unnest([0, 1]) AS k) GROUP BY 1")
add("session_users", lambda s, d: _E(s, d).groupBy("user_id", F.session_window(F.col("ts").cast("timestamp"), "6 hours")).agg(F.count("*").alias("n")).groupBy("user_id").agg(F.count("*").alias("sessions"), F.max("n").alias("longest")), """SELECT user_id, count(*) AS sessions, max(n) AS longest FROM (SELECT user_id, s, count(*) AS n FROM (SELECT user_id, sum(b) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS s
    FROM (SELECT *, CASE WHEN ts < lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) + INTERVAL 6 HOURS THEN 0 ELSE 1 END AS b FROM events)) GROUP BY ALL) GROUP BY user_id""")
