"""Three iterations of the method as one chain, with prototypes for a head, on the vectors of `queries_core`: ids only come
out, so SQL can check the whole loop. The head of an iteration is the mean of the labelled vectors of each type, and the
realigned head for types without a label."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from lakeadapt.functions.draws import smallest, sql_draw
from lakeadapt.operators import gap, head, weak
from lakeadapt.plans.queries_core import DELTA, K, SCALE, C, target_head, vectors
from lakeadapt.session import REGISTRY
from lakeadapt.sources.store import written

ROUNDS, WARM, PROBE, BATCH = 3, 20, 32, 10


def adapt_prototype_3iters(spark: SparkSession, sf_dir: str) -> DataFrame:
    """iter, stage (batch, probe, flagged), column_id."""
    cols = written(vectors(spark, sf_dir, "target").select("column_id", "type_name", "hidden"), "chain")
    start = written(target_head(spark, sf_dir).select("type_name", "w"), "chain-head")
    schema = "iter int, stage string, column_id string"

    def noted(ids: DataFrame, l: int, stage: str) -> DataFrame:
        return ids.select(F.lit(l).alias("iter"), F.lit(stage).alias("stage"), "column_id")

    trace = written(noted(smallest(cols.select("column_id"), WARM, "chain0", "column_id"), 0, "batch"), "chain-trace")
    for l in range(1, ROUNDS + 1):
        bought = trace.where("stage = 'batch'").select("column_id").distinct()
        own = head.prototypes(cols.join(F.broadcast(bought), "column_id", "left_semi")).withColumnRenamed("w", "_w")
        now = start.join(F.broadcast(own), "type_name", "left").select("type_name", F.coalesce("_w", "w").alias("w"))
        probed = gap.probe(cols, trace.where("stage <> 'flagged'").select("column_id"), PROBE, f"chain-probe{l}")
        judged = gap.noisy_judge(gap.gate(head.predict(probed, now, SCALE), DELTA), 0.807, 0.05, f"chain-judge{l}")
        flags = written(noted(gap.flagged(judged), l, "flagged").unionByName(noted(probed, l, "probe")), "chain-flags")
        pool = weak.weak_pool(weak.lloyd(cols, K, 1, f"chain-km{l}"), flags.where("stage = 'flagged'"))
        new = weak.batch(pool, bought, BATCH, BATCH, f"chain-batch{l}")
        trace = written(trace.unionByName(flags).unionByName(noted(new, l, "batch")), "chain-trace")
    return trace.select(*[c.split()[0] for c in schema.split(", ")])


def _oracle() -> str:
    ctes = {n: C[n] for n in ("e", "src", "tgt", "hs", "fresh", "ht")}
    ids = "SELECT DISTINCT column_id FROM tgt"
    ctes["ids"] = ids
    ctes["t0"] = f"SELECT 0 AS iter, 'batch' AS stage, column_id FROM (SELECT column_id FROM ids ORDER BY {sql_draw('chain0', 'column_id')}, column_id LIMIT {WARM})"
    for l in range(1, ROUNDS + 1):
        before = f"t{l - 1}"
        ctes[f"own{l}"] = f"SELECT type_name, dim, avg(x) AS w FROM tgt WHERE column_id IN (SELECT column_id FROM {before} WHERE stage = 'batch') GROUP BY ALL"
        ctes[f"now{l}"] = f"SELECT h.type_name, h.dim, coalesce(o.w, h.w) AS w FROM ht h LEFT JOIN own{l} o ON h.type_name = o.type_name AND h.dim = o.dim"
        ctes[f"pb{l}"] = f"SELECT column_id FROM ids WHERE column_id NOT IN (SELECT column_id FROM {before} WHERE stage <> 'flagged') ORDER BY {sql_draw(f'chain-probe{l}', 'column_id')}, column_id LIMIT {PROBE}"
        ctes[f"sc{l}"] = f"SELECT column_id, any_value(t.type_name) AS type_name, h.type_name AS pred, round(sum(x * w) * {SCALE}, 9) AS v FROM tgt t JOIN now{l} h ON t.dim = h.dim WHERE column_id IN (SELECT column_id FROM pb{l}) GROUP BY column_id, h.type_name"
        ctes[f"pr{l}"] = f"SELECT column_id, any_value(type_name) AS type_name, arg_min(pred, (-v, pred)) AS pred, 1 / sum(exp(v - m)) AS phi FROM (SELECT *, max(v) OVER (PARTITION BY column_id) AS m FROM sc{l}) GROUP BY column_id"
        said = f"CASE WHEN {sql_draw(f'chain-judge{l}:silent', 'column_id')} / 4294967296.0 < 0.05 THEN 'unknown' WHEN (pred = type_name) = ({sql_draw(f'chain-judge{l}:right', 'column_id')} / 4294967296.0 < 0.807) THEN 'yes' ELSE 'no' END"
        ctes[f"fl{l}"] = f"SELECT column_id FROM (SELECT column_id, {said} AS decision FROM pr{l} WHERE phi < {DELTA}) WHERE decision <> 'yes'"
        ctes[f"c{l}"] = f"SELECT dim, x, k FROM tgt JOIN (SELECT column_id AS id, row_number() OVER (ORDER BY column_id) - 1 AS k FROM (SELECT column_id FROM ids ORDER BY {sql_draw(f'chain-km{l}', 'column_id')}, column_id LIMIT {K})) ON id = column_id"
        ctes[f"a{l}"] = f"SELECT column_id, k FROM (SELECT column_id, k, row_number() OVER (PARTITION BY column_id ORDER BY round(sum((t.x - c.x) * (t.x - c.x)), 9), k) AS r FROM tgt t JOIN c{l} c ON t.dim = c.dim GROUP BY column_id, k) WHERE r = 1"
        ctes[f"b{l}"] = (
            f"SELECT column_id FROM a{l} WHERE k IN (SELECT k FROM a{l} WHERE column_id IN (SELECT column_id FROM fl{l})) AND column_id NOT IN (SELECT column_id FROM {before} WHERE stage = 'batch') "
            f"ORDER BY {sql_draw(f'chain-batch{l}', 'column_id')}, column_id LIMIT {BATCH}"
        )
        new = " UNION ALL ".join(f"SELECT {l} AS iter, '{stage}' AS stage, column_id FROM {name}{l}" for stage, name in (("probe", "pb"), ("flagged", "fl"), ("batch", "b")))
        ctes[f"t{l}"] = f"SELECT * FROM {before} UNION ALL {new}"
    return "WITH " + ", ".join(f"{n} AS MATERIALIZED ({q})" for n, q in ctes.items()) + f" SELECT CAST(iter AS INTEGER) AS iter, stage, column_id FROM t{ROUNDS}"


REGISTRY.add("adapt_prototype_3iters", adapt_prototype_3iters, _oracle())
