"""Where queries and their SQL are kept, and the data graphs they run over."""

from __future__ import annotations

from collections.abc import Callable

from branchwise.operators.graph import LabeledGraph
from branchwise.operators.storage import version
from branchwise.sources import graphs as src

QUERIES: dict[str, Callable] = {}
ORACLE_SQL: dict[str, str] = {}

PARTS, TRADE = ("lineitem", "part"), ("customer", "orders", "part", "supplier", "nation", "region", "lineitem")


def _parts(rule: str, label: str, label_sql: str | None = None, loops: bool = False):
    return lambda s, d: src.part_pairs(s, d, rule, label, loops), src.part_pairs_sql(rule, label_sql or label, loops), PARTS


_TYPE = ("split(p_type, ' ')[0]", "split_part(p_type, ' ', 1)")
#: name -> builder, SQL of its views, tables it is made of.
GRAPHS = {
    "gd": _parts("flag", "p_brand"),
    "gs": _parts("flag_half", "p_brand"),
    "gs_name": _parts("flag_half", "p_name"),
    "gs_size": _parts("flag_half", "p_size"),
    "gd_type": _parts("flag", *_TYPE),
    "gs_type": _parts("flag_half", *_TYPE),
    "gs_loops": _parts("flag_half", *_TYPE, loops=True),
    "gd_size": _parts("flag", "p_size"),
    "gd_name": _parts("flag", "p_name"),
    "gc": _parts("order", "p_brand"),
    "gt": (lambda s, d: src.trade_entities(s, d, "o_orderpriority", "p_brand"), src.trade_entities_sql("o_orderpriority", "p_brand"), TRADE),
    "gt_kind": (src.trade_entities, src.trade_entities_sql(), TRADE),
    "ge": (src.vector_proximity, src.vector_proximity_sql(), ("embeddings",)),
    "gu": (src.user_proximity, src.user_proximity_sql(), ("events",)),
    "gk": (src.shared_lines, src.shared_lines_sql(), ("documents",)),
    "gl": (src.document_lines, src.document_lines_sql(), ("documents",)),
    "gp": (src.page_links, src.page_links_sql(), ("pages",)),
    "gv": (src.turn_chain, src.turn_chain_sql(), ("conversations",)),
}
_SETTLED: dict[tuple, tuple] = {}


def graph(name: str, spark, sf_dir) -> LabeledGraph:
    """The graph with its labelled edges in storage: made once per session, and again when a table it is made of has changed."""
    build, _, tables = GRAPHS[name]
    key, now = (spark.sparkContext.applicationId, name, sf_dir), version(spark, [f"{sf_dir}/{t}.parquet" for t in tables])
    if _SETTLED.get(key, (None,))[0] != now:
        _SETTLED[key] = now, build(spark, sf_dir).settled(name)
    return _SETTLED[key][1]


def query(name: str, sql: str | None = None):
    """Registers a function of (spark, sf_dir)."""

    def add(f):
        QUERIES[name] = f
        if sql is not None:
            ORACLE_SQL[name] = sql
        return f

    return add


def on(name: str, sql: str) -> str:
    """SQL over the views of a graph."""
    return f"{GRAPHS[name][1]} {sql}"


def with_views(name: str, views: str, sql: str) -> str:
    return f"{GRAPHS[name][1]}, {views} {sql}"
