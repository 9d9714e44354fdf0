"""Mixing sources to target weights over a domain - language - source tree.

The token budget flows down the tree by weight. A child that cannot use its share takes what it has, and its shortage
is shared among its siblings by weight before anything goes back to the parent's siblings: at each level this is one
water-filling, solved in closed form by windows over the (few) tree nodes. A leaf may be repeated for `max_epochs`.
Inside a leaf each epoch has its own seeded order; whole epochs come first, the last one gives a token-prefix: the
longest run from its start that fits. Only the hash range where the prefix ends is sorted. Texts are counted once, into a
slim table; a leaf's plan is three values (whole epochs, rest, last key of the prefix), by which any row is settled alone.

Tokens and weights are whole numbers and so are all shares; children are put in order by the quotient of two of them, of
which equal ones stay equal, so every engine and every partitioning gives the same rows.

Defined cases: null languages and sources are leaves of their own under the domain `other`; null and wordless texts
have 0 tokens and are taken only with a whole epoch or inside the prefix; repeated rows share their place in the order; an
empty table gives no rows; an unknown name has weight `default_weight`; whatever has weight 0, or lies below it, gives nothing.
"""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from lakeadapt.llm.common import SPACE, materialize, of_type


@dataclass(frozen=True)
class Mix:
    budget_percent: int = 60
    max_epochs: int = 2
    seed: int = 11
    default_weight: int = 1
    domain_of: dict[str, str] = field(default_factory=lambda: {"src0": "crawl", **{f"src{i}": "curated" for i in range(1, 10)}, **{f"src{i}": "forum" for i in range(10, 20)}})
    domain_weights: dict[str, int] = field(default_factory=lambda: {"crawl": 3, "curated": 5, "forum": 2})
    lang_weights: dict[str, int] = field(default_factory=lambda: {"en": 5, "de": 2, "fr": 2, "es": 2})
    source_weights: dict[str, int] = field(default_factory=lambda: {"src1": 3, "src2": 2, "src10": 2})


PRODUCTION = Mix()

#: Ranges that a leaf's order is cut into before the last one is sorted: the first three hex digits.
RANGE_DIGITS = 3
MAX_SENT = 100_000


def _lookup(column: str, values: dict, default) -> Column:
    if not values:
        return F.lit(default)
    pairs = F.create_map(*[F.lit(x) for kv in values.items() for x in kv])
    return F.coalesce(F.element_at(pairs, F.coalesce(F.col(column), F.lit("\0"))), F.lit(default))


def counted(docs: DataFrame) -> DataFrame:
    """documents -> doc_id, lang, source, n_tokens (words between ASCII white space)."""
    slim = of_type(docs, {"doc_id": "long", "lang": "string", "source": "string", "text": "string"})
    # a text that begins with white space has an empty first piece, one that ends with it an empty last one
    pieces = F.split(F.coalesce("text", F.lit("")), SPACE)
    n = F.size(pieces) - (F.get(pieces, F.lit(0)) == "").cast("int") - ((F.size(pieces) > 1) & (F.element_at(pieces, -1) == "")).cast("int")
    return slim.select("doc_id", "lang", "source", n.cast("long").alias("n_tokens"))


def _fill(nodes: DataFrame, parent: list[str], name: str, out: str) -> DataFrame:
    """nodes(parent..., name, cap, weight, given) -> with `out`, each child's part of what its parent is given."""
    by = Window.partitionBy(*parent)
    order = by.orderBy(F.try_divide("cap", "weight").asc_nulls_last(), F.col(name).asc_nulls_first())
    before = F.coalesce(F.sum("cap").over(order.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    left = F.sum("weight").over(order.rowsBetween(0, Window.unboundedFollowing))
    full = nodes.withColumn("_full", F.col("cap") * left <= (F.col("given") - before) * F.col("weight"))
    spent = F.coalesce(F.sum(F.when(F.col("_full"), F.col("cap"))).over(by), F.lit(0))
    open_ = F.sum(F.when(~F.col("_full"), F.col("weight"))).over(by)
    share = F.expr("(given - _spent) * weight div _open")
    return full.withColumn("_spent", spent).withColumn("_open", open_).withColumn(out, F.when(F.col("_full"), F.col("cap")).otherwise(share)).drop("_full", "_spent", "_open")


def leaf_quotas(leaves: DataFrame, mix: Mix) -> DataFrame:
    """leaves(domain, lang, source, tokens) -> with quota: tokens that each leaf is to give."""
    weights = [_lookup("domain", mix.domain_weights, mix.default_weight), _lookup("lang", mix.lang_weights, mix.default_weight), _lookup("source", mix.source_weights, mix.default_weight)]
    usable = (weights[0] > 0) & (weights[1] > 0) & (weights[2] > 0)
    leaves = leaves.withColumn("cap", F.when(usable, F.col("tokens") * mix.max_epochs).otherwise(F.lit(0)))
    sums = lambda keys: leaves.groupBy(*keys).agg(F.sum("cap").cast("long").alias("cap"))
    all_ = leaves.agg(F.coalesce(F.sum("cap"), F.lit(0)).cast("long").alias("_cap"), F.expr(f"coalesce(sum(tokens), 0) * {mix.budget_percent} div 100").alias("_want"))
    given = all_.select(F.least("_cap", "_want").alias("given"))
    d = sums(["domain"]).crossJoin(F.broadcast(given)).withColumn("weight", weights[0])
    d = _fill(d.withColumn("_root", F.lit(0)), ["_root"], "domain", "part").select("domain", F.col("part").alias("given"))
    by_lang = sums(["domain", "lang"]).join(F.broadcast(d), "domain").withColumn("weight", weights[1])
    by_lang = _fill(by_lang, ["domain"], "lang", "part").select(F.col("domain").alias("_d"), F.col("lang").alias("_l"), F.col("part").alias("given"))
    low = leaves.join(F.broadcast(by_lang), F.col("domain").eqNullSafe(F.col("_d")) & F.col("lang").eqNullSafe(F.col("_l")))
    low = low.withColumn("weight", weights[2])
    return _fill(low, ["domain", "lang"], "source", "quota").select("domain", "lang", "source", "tokens", "quota")


def bounded(leaf_rows: DataFrame, tag: str) -> DataFrame:
    """One row per leaf of the tree, written once; sent to every task while there are at most MAX_SENT leaves, so that the
    texts stay where they are. A larger tree is joined by a shuffle."""
    stored = materialize(leaf_rows, tag)
    return F.broadcast(stored) if stored.count() <= MAX_SENT else stored


def _order_key(seed: int, epoch: Column, doc_id: str) -> Column:
    return F.md5(F.concat_ws(":", F.lit(str(seed)), epoch.cast("string"), F.coalesce(F.col(doc_id).cast("string"), F.lit("none"))))


LEAF = ["domain", "lang", "source"]


def _on_leaf(rows: DataFrame, plan: DataFrame) -> DataFrame:
    """rows with the plan of their leaf; null names are names."""
    named = plan.select(*[F.col(c).alias(f"_{c}") for c in LEAF], *[c for c in plan.columns if c not in LEAF])
    same = [F.col(c).eqNullSafe(F.col(f"_{c}")) for c in LEAF]
    return rows.join(named, same[0] & same[1] & same[2]).drop(*[f"_{c}" for c in LEAF])


def leaf_plan(slim: DataFrame, mix: Mix) -> DataFrame:
    """slim(domain, lang, source, doc_id, n_tokens) -> per leaf: whole epochs, tokens of the last one, its last order key."""
    leaves = slim.groupBy(*LEAF).agg(F.sum("n_tokens").cast("long").alias("tokens"))
    quotas = leaf_quotas(leaves, mix).select(
        *LEAF, F.expr("CASE WHEN tokens > 0 THEN quota div tokens ELSE 0 END").alias("whole"), F.expr("CASE WHEN tokens > 0 THEN quota % tokens ELSE 0 END").alias("rest")
    )
    quotas = bounded(quotas, "mix-quotas")
    rows = _on_leaf(slim, quotas).withColumn("_h", _order_key(mix.seed, F.col("whole"), "doc_id")).withColumn("_r", F.substring("_h", 1, RANGE_DIGITS))
    # token sums of the hash ranges of each leaf, combined before the shuffle; then the range in which the prefix ends
    ranges = rows.groupBy(*LEAF, "rest", "_r").agg(F.sum("n_tokens").alias("_t"))
    upto = F.sum("_t").over(Window.partitionBy(*LEAF).orderBy("_r"))
    ends = ranges.withColumn("_upto", upto).where("_upto > rest").groupBy(*LEAF).agg(F.min(F.struct("_r", (F.col("_upto") - F.col("_t")).alias("_before"))).alias("_end"))
    ends = bounded(ends.select(*LEAF, F.col("_end._r").alias("_end"), F.col("_end._before").alias("_before")), "mix-ends")
    # only the rows of that range need an order
    last = _on_leaf(rows, ends).where("_r = _end").withColumn("_sum", F.sum("n_tokens").over(Window.partitionBy(*LEAF).orderBy("_h")))
    cut = last.groupBy(*LEAF, "_end").agg(F.max(F.when(F.col("_before") + F.col("_sum") <= F.col("rest"), F.col("_h"))).alias("_last"))
    # every key of an earlier range is smaller than the range's own digits
    cut = cut.select(*LEAF, F.coalesce("_last", "_end").alias("cut"))
    same = [F.col(f"q.{c}").eqNullSafe(F.col(f"c.{c}")) for c in LEAF]
    return quotas.alias("q").join(cut.alias("c"), same[0] & same[1] & same[2], "left").select(*[f"q.{c}" for c in LEAF], "whole", "rest", "cut")


def _copies(mix: Mix) -> Column:
    """How often a row with a plan is taken."""
    inside = (F.col("rest") > 0) & (_order_key(mix.seed, F.col("whole"), "doc_id") <= F.col("cut"))
    return F.col("whole") + F.coalesce(inside, F.lit(False)).cast("long")


def mix_documents(docs: DataFrame, mix: Mix = PRODUCTION) -> DataFrame:
    """documents -> doc_id, domain, lang, source, n_tokens, copies (times the document is taken)."""
    slim = materialize(counted(docs).withColumn("domain", _lookup("source", mix.domain_of, "other")), "mix-counts")
    return _on_leaf(slim, bounded(leaf_plan(slim, mix), "mix-plan")).select("doc_id", *LEAF, "n_tokens", _copies(mix).alias("copies"))


def mixed(docs: DataFrame, mix: Mix = PRODUCTION) -> DataFrame:
    """The mixture itself, with the columns of docs: each document as many times as it is taken."""
    slim = materialize(counted(docs).withColumn("domain", _lookup("source", mix.domain_of, "other")), "mix-counts")
    plan = bounded(leaf_plan(slim, mix), "mix-plan")
    rows = docs.select(
        F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("_kept"),
        F.col("doc_id").cast("long").alias("doc_id"), F.col("lang").cast("string").alias("lang"), F.col("source").cast("string").alias("source"),
    ).withColumn("domain", _lookup("source", mix.domain_of, "other"))
    taken = _on_leaf(rows, plan).withColumn("_copies", _copies(mix)).where("_copies > 0")
    again = taken.select("_kept", F.explode(F.sequence(F.lit(1).cast("long"), F.col("_copies"))).alias("_again"))
    return again.select(*[F.col("_kept").getField(c).alias(c) for c in docs.columns])


def op4_mix_sources(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mix_documents(spark.read.parquet(f"{sf_dir}/documents.parquet"))


def _oracle(mix: Mix = PRODUCTION) -> str:
    def case(column: str, values: dict, default: str) -> str:
        whens = " ".join(f"WHEN '{k}' THEN {v!r}" for k, v in values.items())
        return f"CASE {column} {whens} ELSE {default} END"

    def fill(source: str, parent: str, name: str, out: str) -> str:
        order = f"PARTITION BY {parent} ORDER BY cap / weight, {name} NULLS FIRST"
        return f"""
        SELECT *, CASE WHEN is_full THEN cap ELSE (given - coalesce(sum(CASE WHEN is_full THEN cap END) OVER (PARTITION BY {parent}), 0))
                 * weight // sum(CASE WHEN NOT is_full THEN weight END) OVER (PARTITION BY {parent}) END AS {out}
        FROM (SELECT *, cap * sum(weight) OVER ({order} ROWS BETWEEN CURRENT ROW AND UNBOUNDED FOLLOWING)
                 <= (given - coalesce(sum(cap) OVER ({order} ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0)) * weight AS is_full
              FROM ({source}))"""

    dom = case("source", mix.domain_of, "'other'")
    level1 = f"SELECT domain, 0 AS root, sum(cap) AS cap, {case('domain', mix.domain_weights, str(mix.default_weight))} AS weight, (SELECT least(sum(cap), sum(tokens) * {mix.budget_percent} // 100) FROM leaf) AS given FROM leaf GROUP BY domain"
    level2 = f"SELECT l.domain, lang, sum(l.cap) AS cap, {case('lang', mix.lang_weights, str(mix.default_weight))} AS weight, any_value(d.part) AS given FROM leaf l JOIN d ON l.domain = d.domain GROUP BY l.domain, lang"
    level3 = f"SELECT l.*, {case('source', mix.source_weights, str(mix.default_weight))} AS weight, g.part AS given FROM leaf l JOIN g ON l.domain = g.domain AND l.lang = g.lang"
    return rf"""
WITH doc AS (SELECT doc_id, lang, source, {dom} AS domain,
               CAST(len(regexp_extract_all(text, '[^\x20\x09-\x0D]+')) AS BIGINT) AS n_tokens FROM documents),
leaf AS (SELECT domain, lang, source, sum(n_tokens) AS tokens, sum(n_tokens) * {mix.max_epochs} AS cap FROM doc GROUP BY ALL),
d AS ({fill(level1, "root", "domain", "part")}),
g AS ({fill(level2, "domain", "lang", "part")}),
q AS ({fill(level3, "domain, lang", "source", "quota")}),
o AS (SELECT doc.*, quota // tokens AS whole, quota % tokens AS rest,
        sum(n_tokens) OVER (PARTITION BY doc.domain, doc.lang, doc.source
                            ORDER BY md5(concat({mix.seed}, ':', CAST(quota // tokens AS BIGINT), ':', doc_id))) AS upto
      FROM doc JOIN q ON doc.domain = q.domain AND doc.lang = q.lang AND doc.source = q.source)
SELECT doc_id, domain, lang, source, n_tokens, CAST(whole + CASE WHEN rest > 0 AND upto <= rest THEN 1 ELSE 0 END AS BIGINT) AS copies FROM o
"""


ORACLE = _oracle()
