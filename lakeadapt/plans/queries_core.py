"""Queries of the method itself on a representation that SQL can hold: `embeddings` as hidden vectors, labels as types.

Even ids are the source lake with types t0..t6, odd ids the target lake with t3..t9: four shared types, three released,
three fresh. The labels carry no signal, so these check arithmetic, not accuracy.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window as W

from lakeadapt.functions.draws import draw, smallest, sql_draw
from lakeadapt.functions.vectors import phi
from lakeadapt.operators import cost, gap, head, metrics, typesets, weak
from lakeadapt.session import REGISTRY, table

SCALE, SEED, WIDTH, DELTA, K = 40.0, 7, 64, 0.6, 7
SOURCE, TARGET = [f"t{k}" for k in range(7)], [f"t{k}" for k in range(3, 10)]
_T = "(VALUES " + ", ".join(f"('{t}')" for t in TARGET) + ") AS g(type_name)"
_S = "(VALUES " + ", ".join(f"('{t}')" for t in SOURCE) + ") AS s(type_name)"


def vectors(spark: SparkSession, d: str, part: str) -> DataFrame:
    e = table(spark, d, "embeddings").select(F.col("vec_id").cast("string").alias("column_id"), F.concat(F.lit("t"), "label").alias("type_name"), F.col("embedding").cast("array<double>").alias("hidden"), "vec_id", "label")
    return e.where("vec_id % 2 = 0 AND label <= 6") if part == "source" else e.where("vec_id % 2 = 1 AND label >= 3")


def source_head(spark: SparkSession, d: str) -> DataFrame:
    return head.prototypes(vectors(spark, d, "source"))


def target_head(spark: SparkSession, d: str) -> DataFrame:
    return head.realign(source_head(spark, d), typesets.typeset(spark, TARGET), WIDTH, SEED)


def scored(spark: SparkSession, d: str) -> DataFrame:
    return head.predict(vectors(spark, d, "target"), target_head(spark, d), SCALE)


def judged(spark: SparkSession, d: str) -> DataFrame:
    return gap.noisy_judge(gap.gate(scored(spark, d), DELTA), 0.807, 0.05, "judge")


def _long(rows: DataFrame) -> DataFrame:
    return rows.select("type_name", F.posexplode("w").alias("dim", "x")).select("type_name", "dim", F.round("x", 6).alias("w"))


# The same steps as SQL
C = {
    "e": "SELECT CAST(vec_id AS VARCHAR) AS column_id, vec_id, 't' || label AS type_name, label, unnest(range(0, 64)) AS dim, unnest(CAST(embedding AS DOUBLE[])) AS x FROM embeddings",
    "src": "SELECT * FROM e WHERE vec_id % 2 = 0 AND label <= 6",
    "tgt": "SELECT * FROM e WHERE vec_id % 2 = 1 AND label >= 3",
    "hs": "SELECT type_name, dim, avg(x) AS w FROM src GROUP BY ALL",
    "fresh": f"SELECT type_name, dim, ({sql_draw(str(SEED), 'type_name', 'dim')} / 4294967296.0 * 2 - 1) * 0.1 AS w FROM {_T}, (SELECT unnest(range(0, 64)) AS dim)",
    "ht": "SELECT f.type_name, f.dim, coalesce(hs.w, f.w) AS w, hs.w IS NOT NULL AS copied FROM fresh f LEFT JOIN hs ON f.type_name = hs.type_name AND f.dim = hs.dim",
    "sc": f"SELECT column_id, any_value(t.type_name) AS type_name, h.type_name AS pred, round(sum(x * w) * {SCALE}, 9) AS v FROM tgt t JOIN ht h ON t.dim = h.dim GROUP BY column_id, h.type_name",
    "pr": "SELECT column_id, any_value(type_name) AS type_name, arg_min(pred, (-v, pred)) AS pred, 1 / sum(exp(v - m)) AS phi FROM (SELECT *, max(v) OVER (PARTITION BY column_id) AS m FROM sc) GROUP BY column_id",
    "gt": f"SELECT * FROM pr WHERE phi < {DELTA}",
    "jd": f"""SELECT *, CASE WHEN {sql_draw('judge:silent', 'column_id')} / 4294967296.0 < 0.05 THEN 'unknown'
        WHEN (pred = type_name) = ({sql_draw('judge:right', 'column_id')} / 4294967296.0 < 0.807) THEN 'yes' ELSE 'no' END AS decision FROM gt""",
    "reg": f"SELECT coalesce(s.type_name, g.type_name) AS type_name, CASE WHEN g.type_name IS NULL THEN 'source_only' WHEN s.type_name IS NULL THEN 'target_only' ELSE 'shared' END AS region FROM {_S} FULL JOIN {_T} ON s.type_name = g.type_name",
    "c0": f"SELECT dim, x, k FROM tgt JOIN (SELECT column_id AS id, row_number() OVER (ORDER BY column_id) - 1 AS k FROM (SELECT DISTINCT column_id FROM tgt ORDER BY {sql_draw('km', 'column_id')}, column_id LIMIT {K})) ON id = column_id",
}
for _r in (1, 2, 3):
    C[f"a{_r}"] = f"SELECT column_id, k FROM (SELECT column_id, k, row_number() OVER (PARTITION BY column_id ORDER BY round(sum((t.x - c.x) * (t.x - c.x)), 9), k) AS r FROM tgt t JOIN c{_r - 1} c ON t.dim = c.dim GROUP BY column_id, k) WHERE r = 1"
    C[f"c{_r}"] = f"SELECT coalesce(n.dim, o.dim) AS dim, coalesce(n.x, o.x) AS x, coalesce(n.k, o.k) AS k FROM c{_r - 1} o FULL JOIN (SELECT dim, k, avg(x) AS x FROM tgt JOIN a{_r} USING (column_id) GROUP BY dim, k) n ON n.k = o.k AND n.dim = o.dim"


def sql(names: str, last: str) -> str:
    return "WITH " + ", ".join(f"{n} AS MATERIALIZED ({C[n]})" for n in names.split()) + " " + last


_PRED = "e src tgt hs fresh ht sc pr"
add = REGISTRY.add
add("prototype_head", lambda s, d: _long(source_head(s, d)), sql("e src hs", "SELECT type_name, CAST(dim AS INTEGER) AS dim, round(w, 6) AS w FROM hs"))
add("realign_head", lambda s, d: _long(target_head(s, d)), sql("e src hs fresh ht", "SELECT type_name, CAST(dim AS INTEGER) AS dim, round(w, 6) AS w FROM ht"))
def _types_of(s: SparkSession, d: str) -> DataFrame:
    return table(s, d, "orders").select(F.concat_ws("/", "o_orderpriority", "o_orderstatus").alias("type_name")).distinct()


add("realign_random", lambda s, d: _long(head.fresh(_types_of(s, d), WIDTH, SEED)), f"SELECT type_name, CAST(dim AS INTEGER) AS dim, round(({sql_draw(str(SEED), 'type_name', 'dim')} / 4294967296.0 * 2 - 1) * 0.1, 6) AS w FROM (SELECT DISTINCT concat_ws('/', o_orderpriority, o_orderstatus) AS type_name FROM orders), (SELECT unnest(range(0, 64)) AS dim)")
add("realign_report", lambda s, d: head.realign_report(source_head(s, d), typesets.typeset(s, TARGET)), sql("reg", "SELECT count(*) FILTER (region = 'shared') AS copied, count(*) FILTER (region = 'target_only') AS fresh, count(*) FILTER (region = 'source_only') AS released FROM reg"))
add("prototype_predict", lambda s, d: scored(s, d).select("column_id", "pred", F.round("phi", 6).alias("phi")), sql(_PRED, "SELECT column_id, pred, round(phi, 6) AS phi FROM pr"))
add("softmax_confidence", lambda s, d: vectors(s, d, "target").select("column_id", F.round(phi(F.transform("hidden", lambda x: x * 10.0)), 6).alias("phi")), sql("e src tgt", "SELECT column_id, round(1 / sum(exp(10 * x - m)), 6) AS phi FROM (SELECT *, max(10 * x) OVER (PARTITION BY column_id) AS m FROM tgt) GROUP BY column_id"))
add("doubt_gate", lambda s, d: gap.gate(scored(s, d), DELTA).select("column_id", "pred"), sql(f"{_PRED} gt", "SELECT column_id, pred FROM gt"))


def _gate_counts(s: SparkSession, d: str) -> DataFrame:
    return scored(s, d).agg(*[F.count_if(F.col("phi") < x).alias(f"below_{int(x * 100)}") for x in (0.8, 0.9, 0.95)], F.count("*").alias("n"))


add("gate_counts", _gate_counts, sql(_PRED, "SELECT count(*) FILTER (phi < 0.8) AS below_80, count(*) FILTER (phi < 0.9) AS below_90, count(*) FILTER (phi < 0.95) AS below_95, count(*) AS n FROM pr"))
GRID = [0.3, 0.5, 0.7, 0.9, 0.95, 1.0]
add("delta_sweep", lambda s, d: gap.delta_sweep(scored(s, d), GRID, 50, "held"), sql(_PRED, f"""SELECT CAST(delta AS DOUBLE) AS delta, round(avg(CASE WHEN (phi < delta) = (pred <> type_name) THEN 1.0 ELSE 0.0 END), 6) AS accuracy, count(*) FILTER (phi < delta) AS gated
    FROM (SELECT * FROM pr ORDER BY {sql_draw('held', 'column_id')}, column_id LIMIT 50), (SELECT unnest({GRID}) AS delta) GROUP BY delta"""))
add("noisy_judge", lambda s, d: judged(s, d).select("column_id", "pred", "decision"), sql(f"{_PRED} gt jd", "SELECT column_id, pred, decision FROM jd"))
add("flagged_set", lambda s, d: gap.flagged(judged(s, d)).select("column_id"), sql(f"{_PRED} gt jd", "SELECT column_id FROM jd WHERE decision <> 'yes'"))
add("flagged_no_judge", lambda s, d: gap.flagged(gap.constant_judge(gap.gate(scored(s, d), DELTA), "no")).select("column_id"), sql(f"{_PRED} gt", "SELECT column_id FROM gt"))


def _regions(s: SparkSession) -> DataFrame:
    return typesets.regions(typesets.typeset(s, SOURCE), typesets.typeset(s, TARGET))


add("flag_regions", lambda s, d: gap.flag_regions(judged(s, d), _regions(s)), sql(f"{_PRED} gt jd reg", "SELECT decision, region, count(*) AS n FROM jd JOIN reg USING (type_name) GROUP BY ALL"))
add("judge_quality", lambda s, d: metrics.judge_quality(judged(s, d)), sql(f"{_PRED} gt jd", """SELECT count(*) AS n, round(avg(CASE WHEN (type_name = pred AND decision = 'yes') OR (type_name <> pred AND decision = 'no') THEN 1.0 ELSE 0.0 END), 6) AS accuracy,
    round(avg(CASE WHEN decision = 'unknown' THEN 1.0 ELSE 0.0 END), 6) AS abstained, round(avg(CASE WHEN type_name = pred THEN 1.0 ELSE 0.0 END), 6) AS base_rate,
    round(count(*) FILTER (decision = 'no' AND type_name <> pred) / greatest(1, count(*) FILTER (decision = 'no')), 6) AS no_precision,
    round(count(*) FILTER (decision = 'no' AND type_name <> pred) / greatest(1, count(*) FILTER (type_name <> pred)), 6) AS no_recall FROM jd"""))


def _clusters(s: SparkSession, d: str) -> DataFrame:
    return weak.lloyd(vectors(s, d, "target"), K, 3, "km")


_KM = "c0 a1 c1 a2 c2 a3"
add("kmeans_lloyd", _clusters, sql(f"e src tgt {_KM}", "SELECT column_id, CAST(k AS INTEGER) AS cluster FROM a3"))
_FLAG5 = f"(SELECT column_id FROM jd WHERE decision <> 'yes' ORDER BY {sql_draw('five', 'column_id')}, column_id LIMIT 3)"


def _few(s: SparkSession, d: str) -> DataFrame:
    return smallest(gap.flagged(judged(s, d)), 3, "five", "column_id")


add("weak_clusters", lambda s, d: weak.weak_pool(_clusters(s, d), _few(s, d)).select("column_id", "cluster"), sql(f"{_PRED} gt jd {_KM}", f"SELECT column_id, CAST(k AS INTEGER) AS cluster FROM a3 WHERE k IN (SELECT k FROM a3 WHERE column_id IN {_FLAG5})"))
_WARM = f"(SELECT DISTINCT column_id FROM tgt ORDER BY {sql_draw('warm', 'column_id')}, column_id LIMIT 20)"


def _warm(s: SparkSession, d: str) -> DataFrame:
    return smallest(vectors(s, d, "target").select("column_id"), 20, "warm", "column_id")


add("warmup_sample", _warm, sql("e tgt", f"SELECT DISTINCT column_id FROM tgt WHERE column_id IN {_WARM}"))
add("probe_sample", lambda s, d: gap.probe(vectors(s, d, "target").select("column_id"), _warm(s, d), 64, "probe"), sql("e tgt", f"SELECT DISTINCT column_id FROM tgt WHERE column_id NOT IN {_WARM} ORDER BY {sql_draw('probe', 'column_id')}, column_id LIMIT 64"))
add("residual_sample", lambda s, d: gap.probe(vectors(s, d, "target").select("column_id"), _warm(s, d), 30, "rest"), sql("e tgt", f"SELECT DISTINCT column_id FROM tgt WHERE column_id NOT IN {_WARM} ORDER BY {sql_draw('rest', 'column_id')}, column_id LIMIT 30"))
add("weak_batch", lambda s, d: weak.batch(weak.weak_pool(_clusters(s, d), _few(s, d)), _warm(s, d), 15, 12, "batch").select("column_id"), sql(f"{_PRED} gt jd {_KM}", f"SELECT column_id FROM a3 WHERE k IN (SELECT k FROM a3 WHERE column_id IN {_FLAG5}) AND column_id NOT IN {_WARM} ORDER BY {sql_draw('batch', 'column_id')}, column_id LIMIT 12"))
add("cluster_purity", lambda s, d: metrics.purity(_clusters(s, d), weak.weak_pool(_clusters(s, d), _few(s, d)), scored(s, d)), sql(f"{_PRED} gt jd {_KM}", f"SELECT k IN (SELECT k FROM a3 WHERE column_id IN {_FLAG5}) AS weak, count(*) AS n, round(avg(CASE WHEN pred <> type_name THEN 1.0 ELSE 0.0 END), 6) AS wrong_share FROM a3 JOIN pr USING (column_id) GROUP BY 1"))
add("calibration_bins", lambda s, d: metrics.calibration(scored(s, d)), sql(_PRED, "SELECT CAST(least(floor(phi * 10), 9) AS INTEGER) AS bin, count(*) AS n, round(avg(phi), 6) AS confidence, round(avg(CASE WHEN pred = type_name THEN 1.0 ELSE 0.0 END), 6) AS accuracy FROM pr GROUP BY 1"))
add("forgetting", lambda s, d: metrics.forgetting(scored(s, d), _regions(s)), sql(f"{_PRED} reg", "SELECT region, count(*) AS n, round(avg(CASE WHEN pred = type_name THEN 1.0 ELSE 0.0 END), 6) AS recall FROM pr JOIN reg USING (type_name) GROUP BY region"))


def _loss(s: SparkSession, d: str) -> DataFrame:
    from lakeadapt.functions.vectors import dot

    truth = target_head(s, d).select("type_name", "w")
    own = scored(s, d).join(F.broadcast(truth), "type_name").withColumn("mine", F.round(dot("hidden", "w") * SCALE, 9))
    every = F.broadcast(target_head(s, d).agg(F.collect_list("w").alias("ws")))
    p = own.crossJoin(every).withColumn("all", F.transform("ws", lambda w: F.round(dot("hidden", w) * SCALE, 9)))
    top = F.array_max("all")
    lse = top + F.log(F.aggregate("all", F.lit(0.0), lambda a, v: a + F.exp(v - top)))
    return p.agg(F.round(F.avg(lse - F.col("mine")), 6).alias("loss"), F.count("*").alias("n"))


add("validation_loss", _loss, sql(_PRED, "SELECT round(avg(lse - mine), 6) AS loss, count(*) AS n FROM (SELECT column_id, max(v) + ln(sum(exp(v - m))) AS lse, max(v) FILTER (pred = type_name) AS mine FROM (SELECT *, max(v) OVER (PARTITION BY column_id) AS m FROM sc) GROUP BY column_id)"))

# -- bookkeeping on small traces ------------------------------------------------------------------------------------
def _batches(s: SparkSession, d: str) -> DataFrame:
    return table(s, d, "orders").groupBy((F.col("o_custkey") % 9).cast("long").alias("iter")).agg(F.count("*").alias("size"))


# the budget is half of the orders
add("budget_ledger", lambda s, d: weak.ledger(_batches(s, d), table(s, d, "orders").count() // 2), """WITH x AS (SELECT o_custkey % 9 AS iter, count(*) AS size FROM orders GROUP BY 1), b AS (SELECT count(*) // 2 AS b FROM orders), w AS (SELECT *, sum(size) OVER (ORDER BY iter) AS w FROM x, b)
    SELECT CAST(iter AS BIGINT) AS iter, size, CAST(least(w, b) - least(w - size, b) AS BIGINT) AS paid, CAST(least(w, b) AS BIGINT) AS spent, CAST(b - least(w, b) AS BIGINT) AS "left" FROM w""")
_TRACE = "SELECT CAST(vec_id % 7 AS BIGINT) AS iter, CAST(vec_id AS VARCHAR) AS column_id FROM embeddings"
add("replay_sets", lambda s, d: weak.replay(table(s, d, "embeddings").select((F.col("vec_id") % 7).alias("iter"), F.col("vec_id").cast("string").alias("column_id"))), f"WITH t AS ({_TRACE}) SELECT l.iter AS iter, count(DISTINCT t.column_id) AS n FROM t JOIN (SELECT DISTINCT iter FROM t) l ON t.iter <= l.iter GROUP BY l.iter")
add("early_stop_trace", lambda s, d: weak.stop_trace(table(s, d, "events").groupBy((1 + F.col("event_id") % 12).cast("long").alias("iter")).agg(F.round(F.avg("value"), 6).alias("loss")), 5), """WITH l AS (SELECT CAST(1 + event_id % 12 AS BIGINT) AS iter, round(avg(value), 6) AS loss FROM events GROUP BY 1),
    m AS (SELECT *, coalesce(loss < min(loss) OVER (ORDER BY iter ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), true) AS improved FROM l),
    b AS (SELECT *, max(CASE WHEN improved THEN iter END) OVER (ORDER BY iter) AS best FROM m)
    SELECT iter, loss, improved, best, iter - best AS alpha, coalesce(iter >= (SELECT min(iter) FROM b WHERE iter - best >= 5), false) AS stopped FROM b""")
add("early_stop_long", lambda s, d: weak.stop_trace(table(s, d, "orders").groupBy((F.col("o_orderkey") % 60).alias("iter")).agg(F.round(F.avg("o_totalprice"), 6).alias("loss")), 4).select("iter", "best", "alpha", "stopped"), """WITH m AS (SELECT o_orderkey % 60 AS iter, round(avg(o_totalprice), 6) AS loss FROM orders GROUP BY 1),
    f AS (SELECT *, coalesce(loss < min(loss) OVER (ORDER BY iter ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), true) AS improved FROM m), b AS (SELECT *, max(CASE WHEN improved THEN iter END) OVER (ORDER BY iter) AS best FROM f)
    SELECT iter, best, iter - best AS alpha, coalesce(iter >= (SELECT min(iter) FROM b WHERE iter - best >= 4), false) AS stopped FROM b""")


def _work(s: SparkSession, d: str) -> DataFrame:
    """A priority's orders as a run: a year is an iteration, the first year warms up, the others have batches of their mean size."""
    first = F.count_if(F.year("o_orderdate") == 1992)
    runs = table(s, d, "orders").groupBy(F.col("o_orderpriority").alias("run")).agg(
        (F.countDistinct(F.year("o_orderdate")) - 1).alias("p"), first.alias("first"), (F.count("*") - first).alias("later"), F.count_if(F.col("o_custkey") % 5 == 0).alias("n_valid"), F.count("*").alias("n"))
    names = ("replay_exact", "replay_lower", "clustering", "validation", "realign", "realign_paper")

    @F.udf("struct<" + ", ".join(f"{n}: long" for n in names) + ">")
    def counted(p, first, later, n_valid, n):
        w = cost.Work(p, first, later // max(1, p), 5, n_valid, 33, 78, n, 768, 20)
        return tuple(getattr(w, x)() for x in names)

    return runs.select("run", "p", counted("p", "first", "later", "n_valid", "n").alias("w")).select("run", "p", "w.*")


add("replay_cost", _work, """WITH r AS (SELECT o_orderpriority AS run, count(DISTINCT year(o_orderdate)) - 1 AS p, count(*) FILTER (year(o_orderdate) = 1992) AS f, count(*) FILTER (o_custkey % 5 = 0) AS v, count(*) AS n FROM orders GROUP BY 1),
    b AS (SELECT *, (n - f) // greatest(1, p) AS b FROM r)
    SELECT run, p, CAST(5 * (p * f + b * p * (p + 1) // 2) AS BIGINT) AS replay_exact, CAST(5 * (p * f + b * p * (p - 1) // 2) AS BIGINT) AS replay_lower, CAST(n * 78 * 768 * 20 * p AS BIGINT) AS clustering, CAST(p * 5 * v AS BIGINT) AS validation, CAST(111 AS BIGINT) AS realign, CAST(2574 AS BIGINT) AS realign_paper FROM b""")


def _calls(s: SparkSession, d: str) -> DataFrame:
    """Every event is a judge call: its kind names the transfer, its user the backbone and the lake of the unit cost."""
    backbone = F.element_at(F.array(*map(F.lit, "JCR")), (F.col("user_id") % 3 + 1).cast("int"))
    lake = F.when(F.col("event_type").isin("click", "view"), "V").otherwise("S")
    return table(s, d, "events").groupBy(F.col("event_type").alias("transfer"), backbone.alias("backbone"), lake.alias("lake")).agg(F.count("*").alias("judge_calls"))


add("overhead_cost", lambda s, d: cost.overhead(_calls(s, d)), "SELECT transfer, backbone, n AS judge_calls, round(n * CASE WHEN lake = 'V' THEN 1.2643 ELSE 1.0037 END, 1) AS seconds, round(n * CASE WHEN lake = 'V' THEN 0.00047 ELSE 0.0015 END, 2) AS usd FROM (SELECT event_type AS transfer, substr('JCR', CAST(user_id % 3 + 1 AS INTEGER), 1) AS backbone, CASE WHEN event_type IN ('click', 'view') THEN 'V' ELSE 'S' END AS lake, count(*) AS n FROM events GROUP BY ALL)")
add("prompt_cost", lambda s, d: table(s, d, "orders").groupBy(F.year("o_orderdate").cast("long").alias("year")).agg(F.countDistinct("o_custkey").alias("n_types")).select("year", "n_types", F.round(cost.prompt_dollars(F.col("n_types")), 9).alias("usd")), "SELECT year(o_orderdate) AS year, count(DISTINCT o_custkey) AS n_types, round(0.00047 + (0.0015 - 0.00047) / 197 * (count(DISTINCT o_custkey) - 78), 9) AS usd FROM orders GROUP BY 1")
def _budgets(s: SparkSession, d: str) -> DataFrame:
    """A priority's orders are its training set, and its budgets the orders up to each year."""
    years = table(s, d, "orders").groupBy(F.col("o_orderpriority").alias("transfer"), F.year("o_orderdate").alias("y")).agg(F.count("*").alias("n"))
    own = W.partitionBy("transfer")
    rows = years.select("transfer", F.sum("n").over(own).alias("n_train"), F.sum("n").over(own.orderBy("y")).alias("n_labels"))
    return rows.withColumn("fraction", F.round(F.col("n_labels") / F.col("n_train"), 4)).withColumn("regime", F.when(F.col("n_labels") * 10 < F.col("n_train"), "low").otherwise("high"))


add("budget_grid", _budgets, """WITH y AS (SELECT o_orderpriority AS transfer, year(o_orderdate) AS y, count(*) AS n FROM orders GROUP BY ALL),
    b AS (SELECT transfer, CAST(sum(n) OVER (PARTITION BY transfer) AS BIGINT) AS n_train, CAST(sum(n) OVER (PARTITION BY transfer ORDER BY y) AS BIGINT) AS n_labels FROM y)
    SELECT transfer, n_train, n_labels, round(n_labels / n_train, 4) AS fraction, CASE WHEN n_labels * 10 < n_train THEN 'low' ELSE 'high' END AS regime FROM b""")
#: Results of two methods by budget, measured on a table: a method's value is a mean over the orders of its half.
_RESULTS = "SELECT o_orderpriority AS transfer, CASE WHEN o_orderkey % 2 = 0 THEN 'full' ELSE 'plain' END AS method, 100 * (1 + o_custkey % 7) AS budget, round(avg(o_totalprice) / 250000, 6) AS value FROM orders GROUP BY ALL"


def _results(s: SparkSession, d: str) -> DataFrame:
    method = F.when(F.col("o_orderkey") % 2 == 0, "full").otherwise("plain")
    keys = [F.col("o_orderpriority").alias("transfer"), method.alias("method"), (100 * (1 + F.col("o_custkey") % 7)).cast("long").alias("budget")]
    return table(s, d, "orders").groupBy(*keys).agg(F.round(F.avg("o_totalprice") / 250000, 6).alias("value"))


add("avg_gain", lambda s, d: metrics.avg_gain(_results(s, d), "full", "plain"), f"WITH g AS ({_RESULTS}) SELECT a.transfer, round(avg(a.value / b.value - 1), 6) AS gain, count(*) AS n_budgets FROM g a JOIN g b ON a.transfer = b.transfer AND a.budget = b.budget AND a.method = 'full' AND b.method = 'plain' GROUP BY a.transfer")
add("labels_to_target", lambda s, d: metrics.labels_to_reach(_results(s, d).withColumnRenamed("budget", "n_labels"), 0.6), f"SELECT transfer, method, CAST(min(CASE WHEN value > 0.6 THEN budget END) AS BIGINT) AS n_labels FROM ({_RESULTS}) GROUP BY ALL")
add("query_counts", lambda s, d: cost.query_counts(table(s, d, "events").select(F.concat(F.lit("r"), F.col("user_id") % 3).alias("run"), (F.col("event_id") % 12).alias("iter"), F.when(F.col("event_type") == "click", "judge").otherwise("batch").alias("stage"), "event_id")), "SELECT 'r' || (user_id % 3) AS run, count(*) FILTER (event_type = 'click') AS judge_calls, count(DISTINCT CASE WHEN event_id % 12 > 0 THEN event_id % 12 END) AS iterations FROM events GROUP BY 1")

# -- accuracy measures on a truth table with planted mistakes and out-of-set answers ----------------------------------
_H = sql_draw("mistake", "vec_id")
_CONF = f"SELECT CAST(vec_id AS VARCHAR) AS column_id, 't' || label AS type_name, CASE WHEN {_H} % 10 < 6 THEN 't' || label WHEN {_H} % 10 < 9 THEN 't' || ((label + 1) % 10) ELSE 'elsewhere' END AS pred FROM embeddings"
_PER = f"WITH c AS ({_CONF}), n AS (SELECT t AS type_name, CAST(sum(tp) AS BIGINT) AS tp, CAST(sum(fp) AS BIGINT) AS fp, CAST(sum(fn) AS BIGINT) AS fn FROM (SELECT type_name AS t, CASE WHEN type_name = pred THEN 1 ELSE 0 END AS tp, 0 AS fp, CASE WHEN type_name <> pred THEN 1 ELSE 0 END AS fn FROM c UNION ALL SELECT pred, 0, 1, 0 FROM c WHERE pred <> type_name) GROUP BY t), p AS (SELECT type_name, tp, fp, fn, tp + fn AS support, round(coalesce(tp / nullif(tp + fp, 0), 0), 6) AS precision, round(coalesce(tp / nullif(tp + fn, 0), 0), 6) AS recall, round(coalesce(2 * tp / nullif(2 * tp + fp + fn, 0), 0), 6) AS f1 FROM n) "


def confused(s: SparkSession, d: str) -> DataFrame:
    h = draw("mistake", "vec_id") % 10
    other = F.concat(F.lit("t"), (F.col("label") + 1) % 10)
    return table(s, d, "embeddings").select(F.col("vec_id").cast("string").alias("column_id"), F.concat(F.lit("t"), "label").alias("type_name"), F.when(h < 6, F.concat(F.lit("t"), "label")).when(h < 9, other).otherwise("elsewhere").alias("pred"))


_ten = lambda s: typesets.typeset(s, [f"t{k}" for k in range(10)])
add("per_type_f1", lambda s, d: metrics.per_type(confused(s, d)), _PER + "SELECT * FROM p")
add("sw_f1", lambda s, d: metrics.sw_f1(metrics.per_type(confused(s, d))), _PER + "SELECT round(sum(f1 * support) / sum(support), 6) AS sw_f1 FROM p")
add("ma_f1", lambda s, d: metrics.ma_f1(metrics.per_type(confused(s, d)), _ten(s)), _PER + "SELECT round(avg(f1), 6) AS ma_f1, count(*) AS n_types FROM p WHERE type_name <> 'elsewhere'")
add("ood_rate", lambda s, d: metrics.ood_rate(confused(s, d), _ten(s)), f"SELECT round(avg(CASE WHEN pred = 'elsewhere' THEN 1.0 ELSE 0.0 END), 6) AS ood_rate, count(*) AS n FROM ({_CONF})")
add("long_tail", lambda s, d: metrics.long_tail(metrics.per_type(confused(s, d))), _PER + "SELECT CAST(bucket AS INTEGER) AS bucket, round(avg(f1), 6) AS ma_f1, CAST(sum(support) AS BIGINT) AS support, count(*) AS n_types FROM (SELECT *, ntile(3) OVER (ORDER BY support, type_name) AS bucket FROM p WHERE support > 0) GROUP BY bucket")
add("confusion_pivot", lambda s, d: confused(s, d).groupBy("type_name").pivot("pred", ["t0", "t1", "elsewhere"]).count().na.fill(0), f"SELECT type_name, count(*) FILTER (pred = 't0') AS t0, count(*) FILTER (pred = 't1') AS t1, count(*) FILTER (pred = 'elsewhere') AS elsewhere FROM ({_CONF}) GROUP BY type_name")
add("silhouette_exact", lambda s, d: metrics.silhouette_exact(vectors(s, d, "target").select("column_id", F.col("label").alias("cluster"), "hidden")), """WITH v AS (SELECT vec_id, label, unnest(range(0, 64)) AS dim, unnest(CAST(embedding AS DOUBLE[])) AS x FROM embeddings WHERE vec_id % 2 = 1 AND label >= 3),
    d AS (SELECT a.vec_id AS i, any_value(a.label) AS own, b.vec_id AS j, any_value(b.label) AS other, sqrt(sum((a.x - b.x) * (a.x - b.x))) AS d FROM v a JOIN v b ON a.dim = b.dim AND a.vec_id <> b.vec_id GROUP BY a.vec_id, b.vec_id),
    m AS (SELECT i, own, other, avg(d) AS d FROM d GROUP BY ALL), s AS (SELECT i, min(CASE WHEN own = other THEN d END) AS x, min(CASE WHEN own <> other THEN d END) AS y FROM m GROUP BY i)
    SELECT round(avg(CASE WHEN x IS NULL OR y IS NULL THEN 0 ELSE (y - x) / greatest(x, y) END), 6) AS silhouette, count(*) AS n FROM s""")
