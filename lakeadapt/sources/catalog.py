"""Type sets, transfers, the judge's knowledge and how given tables are cut into lake tables.

Cell expressions are SQL that Spark and DuckDB read alike, so one text serves the engine and its oracle.
"""

from __future__ import annotations

from dataclasses import dataclass


@dataclass(frozen=True)
class Cell:
    name: str
    plain: str
    shifted: str
    type_name: str
    coarse: str | None = None


@dataclass(frozen=True)
class Group:
    """One table that is cut into shards; even shards are rendered plainly, odd ones shifted.

    `by` names one of `values` for each row (any other row is `other`): each has shards of its own, and `{}` in a type name
    stands for it. A group that `repeats` has few rows at any scale: every shard holds all of them.
    """

    name: str
    table: str
    key: str
    cells: tuple[Cell, ...]
    by: str = "''"
    values: tuple[str, ...] = ("",)
    repeats: bool = False

    def types(self) -> list[tuple[str, str | None]]:
        every = [*self.values, "other"] if self.by != "''" else [""]
        return [(c.type_name.replace("{}", v), c.coarse) for v in every for c in self.cells]


def _date(c: str) -> str:
    return f"substr(CAST({c} AS STRING), 9, 2) || '/' || substr(CAST({c} AS STRING), 6, 2) || '/' || substr(CAST({c} AS STRING), 1, 4)"


def _money(c: str) -> str:
    return f"replace(CAST(CAST({c} AS DECIMAL(15, 2)) AS STRING), '.', ',')"


def _key(c: str) -> str:
    return f"lpad(CAST({c} AS STRING), 8, '0')"


def _s(c: str) -> str:
    return f"CAST({c} AS STRING)"


def text(c: str, type_name: str, coarse: str | None = None, lower: bool = True) -> Cell:
    return Cell(c, c, f"lower({c})" if lower else c, type_name, coarse)


def number(c: str, type_name: str, coarse: str | None = None) -> Cell:
    return Cell(c, _s(c), _s(c), type_name, coarse)


def money(c: str, type_name: str) -> Cell:
    return Cell(c, _s(c), _money(c), type_name, "money_amount")


def key(c: str, type_name: str) -> Cell:
    return Cell(c, _s(c), _key(c), type_name, "record_key")


def day(c: str, type_name: str) -> Cell:
    return Cell(c, f"substr({_s(c)}, 1, 10)", _date(c), type_name, "calendar_date")


def span(c: str, pattern: str, type_name: str, group: int = 0) -> Cell:
    """The first match in a text; rows without one have no cell."""
    found = f"nullif(regexp_extract({c}, '{pattern}', {group}), '')"
    return Cell(type_name, found, f"lower({found})", type_name)


#: Spans of prose and of markup, as tables made by extraction have them.
TEXT_SPANS = (
    span("text", "[A-Za-z0-9._]+@[A-Za-z0-9.]+", "mail_address"), span("text", "[0-9]{1,3}[.][0-9]{1,3}[.][0-9]{1,3}[.][0-9]{1,3}", "network_address"),
    span("text", "[0-9a-f]{40}", "secret_key"), span("text", "[0-9]{16}", "account_number"), span("text", "^[^ ]+", "first_word"), span("text", "(19|20)[0-9][0-9]", "year_mention"),
)
PAGE_SPANS = (
    span("url", "://([^/?#]*)", "host_name", 1), span("url", "://[^/?#]*(/[^?#]*)", "url_path", 1), span("html", "<title>([^<]*)</title>", "page_title", 1),
    span("html", "href=\"([^\"]*)\"", "link_target", 1), span("html", "<a [^>]*>([^<]*)</a>", "link_text", 1), span("html", "<h1>([^<]*)</h1>", "heading", 1),
)
GROUPS: tuple[Group, ...] = (
    Group("region", "region", "r_regionkey", (key("r_regionkey", "record_key"), text("r_name", "world_region", "world_region")), repeats=True),
    Group("nation", "nation", "n_nationkey", (key("n_nationkey", "record_key"), text("n_name", "nation_code", "nation_code")), repeats=True),
    Group("customer", "customer", "c_custkey", (key("c_custkey", "buyer_key"), text("c_name", "buyer_name", "party_name"), money("c_acctbal", "account_balance"), text("c_mktsegment", "market_segment", "market_segment"))),
    Group("supplier", "supplier", "s_suppkey", (key("s_suppkey", "vendor_key"), text("s_name", "vendor_name", "party_name"), money("s_acctbal", "account_balance"))),
    Group("part", "part", "p_partkey", (key("p_partkey", "part_key"), text("p_name", "product_name", "product_name"), text("p_brand", "brand_code", "brand_code"), text("p_type", "product_class", "product_class"), number("p_size", "product_size", "small_integer"), money("p_retailprice", "list_price"))),
    Group("orders", "orders", "o_orderkey", (key("o_orderkey", "order_key"), key("o_custkey", "buyer_key"), text("o_orderstatus", "order_status", "order_status"), money("o_totalprice", "order_total"), day("o_orderdate", "order_date"), text("o_orderpriority", "order_priority", "order_priority"))),
    Group("lineitem", "lineitem", "concat_ws('/', l_orderkey, l_linenumber, l_partkey, l_suppkey, l_quantity, l_extendedprice, CAST(l_shipdate AS STRING))", (key("l_orderkey", "order_key"), key("l_partkey", "part_key"), key("l_suppkey", "vendor_key"), number("l_linenumber", "line_number", "small_integer"), number("l_quantity", "quantity", "small_integer"), money("l_extendedprice", "line_price"), number("l_discount", "discount_rate", "rate_fraction"), number("l_tax", "tax_rate", "rate_fraction"), text("l_returnflag", "return_flag", "return_flag"), text("l_linestatus", "line_status", "line_status"), day("l_shipdate", "ship_date"))),
    Group("events", "events", "event_id", (Cell("ts", _s("ts"), _s("ts"), "event_time"), Cell("user_id", _s("user_id"), _key("user_id"), "user_key", "record_key"), text("event_type", "event_kind"), Cell("value", _s("value"), _money("value"), "event_value", "money_amount"), text("props", "json_props", lower=False))),
    Group("documents", "documents", "doc_id", (text("text", "prose_{}"), text("lang", "language_code"), text("source", "source_code"), number("n_chars", "char_count"), *TEXT_SPANS), by="lang", values=("en", "fr", "de", "es")),
    Group("pages", "pages", "page_id", (text("url", "web_address", lower=False), Cell("html", "html", "html", "markup"), *PAGE_SPANS)),
    Group("benchmark", "benchmark", "item_id", (text("text", "passage", lower=False),)),
    Group("labels", "labels", "doc_id", (number("quality", "quality_flag"), number("toxic", "toxicity_flag"))),
    Group("conversations", "conversations", "concat_ws('/', conv_id, turn)", (text("role", "speaker_role"), Cell("turn", _s("turn"), _s("turn"), "turn_number", "small_integer"), text("text", "utterance", lower=False))),
    Group("embeddings", "embeddings", "vec_id", (Cell("label", _s("label"), _s("label"), "cluster_code"), Cell("first", "CAST(CAST(embedding[1] AS DECIMAL(8, 4)) AS STRING)", "CAST(CAST(embedding[1] AS DECIMAL(8, 4)) AS STRING)", "vector_literal"))),
)

STAR = ("region", "nation", "customer", "supplier", "part", "orders", "lineitem")


def fine_types(groups: tuple[str, ...] | None = None) -> list[str]:
    return sorted({t for g in GROUPS if groups is None or g.name in groups for t, _ in g.types()})


def coarse_types() -> list[str]:
    return sorted({c.coarse for g in GROUPS if g.name in STAR for c in g.cells})


@dataclass(frozen=True)
class Transfer:
    name: str
    source: tuple[str, ...]
    target: tuple[str, ...]


_OTHER = tuple(t for t in fine_types() if t not in fine_types(STAR))
_EVENT = fine_types(("events",))
TX1 = Transfer("TX1", tuple(fine_types(STAR)), tuple(fine_types()))
TX2 = Transfer(
    "TX2", tuple(coarse_types()),
    tuple(sorted({{"user_key": "record_key", "event_value": "money_amount", "turn_number": "small_integer"}.get(t, t) for t in _OTHER} | {"buyer_name", "vendor_name", "order_date", "ship_date"})),
)
#: Another provenance: what was cut out of texts and pages, and what tables of texts hold.
TX3 = Transfer(
    "TX3", tuple(sorted({*fine_types(STAR), *_EVENT})),
    tuple(sorted({c.type_name for c in (*TEXT_SPANS, *PAGE_SPANS)} | {"web_address", "markup", "language_code", "source_code", "char_count", "speaker_role", "utterance", "passage", "turn_number", "quality_flag", "toxicity_flag", "event_kind", "event_time", "user_key", "json_props"})),
)
TRANSFERS = (TX1, TX2, TX3)

#: Coarse star types and the finer ones they cover in the target.
GRAIN = {"party_name": ("buyer_name", "vendor_name"), "calendar_date": ("order_date", "ship_date")}

#: Generic knowledge: a pattern that a share of the cells must match. Types that are missing here are beyond it.
KNOWLEDGE = (
    ("web_address", r"^https?://", 0.9),
    ("markup", r"^<!DOCTYPE|^<html", 0.9),
    ("json_props", r"^\{.*\}$", 0.9),
    ("event_time", r"^[0-9]{4}-[0-9]{2}-[0-9]{2} [0-9]{2}:[0-9]{2}", 0.9),
    ("order_date", r"^[0-9]{2}/[0-9]{2}/[0-9]{4}$|^[0-9]{4}-[0-9]{2}-[0-9]{2}$", 0.9),
    ("ship_date", r"^[0-9]{2}/[0-9]{2}/[0-9]{4}$|^[0-9]{4}-[0-9]{2}-[0-9]{2}$", 0.9),
    ("discount_rate", r"^0(\.[0-9]+)?$", 0.9),
    ("tax_rate", r"^0(\.[0-9]+)?$", 0.9),
    ("world_region", r"(?i)^(africa|america|asia|europe|middle east)$", 0.9),
    ("market_segment", r"(?i)^(automobile|building|furniture|household|machinery)$", 0.9),
    ("order_priority", r"(?i)^[1-5]-", 0.9),
    ("event_kind", r"^(view|click|purchase|signup|error|login|logout|cart|search)", 0.9),
    ("speaker_role", r"^(user|assistant|system)$", 0.9),
    ("language_code", r"^(en|fr|de|es)$", 0.9),
    ("buyer_name", r"(?i)^customer#", 0.9),
    ("vendor_name", r"(?i)^supplier#", 0.9),
    ("return_flag", r"(?i)^[anr]$", 0.95),
    ("order_status", r"(?i)^[fop]$", 0.95),
    ("line_status", r"(?i)^[fo]$", 0.95),
    ("brand_code", r"(?i)^brand#", 0.9),
    ("quality_flag", r"^[01]$", 0.95),
    ("toxicity_flag", r"^[01]$", 0.95),
    ("account_balance", r"^-?[0-9]+[.,][0-9]{1,2}$", 0.9),
    ("order_total", r"^[0-9]{3,}[.,][0-9]{1,2}$", 0.9),
    ("line_price", r"^[0-9]{3,}[.,][0-9]{1,2}$", 0.9),
    ("list_price", r"^[0-9]{3,}[.,][0-9]{1,2}$", 0.9),
)
