"""One entrance to all engines, and where results go."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from branchwise.plans.pattern import PatternGraph

from . import dfs, joins, regions, waves
from .candidates import label_domains
from .graph import LabeledGraph

ENGINES = ("join", "level", "dfs", "region", "wave", "shared")
#: Up to so many vertices a pattern is a short chain of joins, whatever the graph.
SHORT = 6


def choose_engine(g: LabeledGraph, p: PatternGraph, limit: int | None = None) -> str:
    """join for short or unconnected patterns; else the search, over a broadcast graph if it fits and by regions if not."""
    if p.n <= SHORT or not p.is_connected() or not p.edges:
        return "join"
    return "dfs" if dfs.fits(g, sorted(set(p.labels))) else "region"


def match(g: LabeledGraph, p: PatternGraph, engine: str = "auto", mode: str = "learned", limit: int | None = None, order: tuple[int, ...] | None = None, filters: tuple[str, ...] = dfs.STRUCTURAL,
          where: dict | None = None) -> DataFrame:
    """m1..mn of all embeddings, with a limit the least ones. where: by vertex of the pattern an SQL condition on the columns of
    vertices, and by a pair of vertices (u, w) a comparison operator for their images, for example {1: "price > 10",
    (1, 3): "<"}. Every engine gives the same rows; join, dfs and region take conditions, join and dfs comparisons."""
    single = {u: c for u, c in (where or {}).items() if isinstance(u, int)}
    checks = tuple((u[0], op, u[1]) for u, op in (where or {}).items() if not isinstance(u, int))
    if bad := [op for _, op, _ in checks if op not in dfs.OPERATORS]:
        raise ValueError(f"no comparison {bad}")
    if engine == "auto":
        engine = choose_engine(g, p, limit)
        if engine == "region" and checks:
            engine = "join"
    if where and (engine not in ("join", "dfs", "region") or checks and engine == "region"):
        raise ValueError(f"{engine} takes no such conditions")
    if engine == "join":
        out = joins.join_match(g, p, order, domains=label_domains(g, p, single) if single else None, checks=checks)
    elif engine == "dfs":
        allowed = {u: {r.vid for r in g.vertices.filter((F.col("label") == p.labels[u - 1]) & F.expr(c)).select("vid").collect()} for u, c in single.items()} if dfs.fits(g, sorted(set(p.labels))) else None
        return dfs.dfs_match(g, p, dfs.Method(mode, filters, "given" if order or limit is not None else "tree_path"), limit, allowed=allowed, checks=checks)
    elif engine == "region":
        out = regions.region_match(g, p, mode, tuple(f for f in filters if f in ("degree", "labels", "arcs")), where=single)
    elif engine == "level":
        out = joins.as_wide(joins.level_match(g, joins.query_set(g.vertices.sparkSession, [p], [order] if order else None)), p.n)
    elif engine == "wave":
        out = waves.wave_match(g, p, order=order)[0]
    elif engine == "shared":
        out = joins.shared_match(g, p, order)[0]
    else:
        raise ValueError(f"no engine {engine}; there are {ENGINES}")
    return out if limit is None else out.orderBy(*out.columns).limit(limit)


def write_embeddings(found: DataFrame, path: str, by: tuple[str, ...] = ()) -> None:
    """Embeddings (or statistics) as Parquet, in folders by columns such as query_id or n_vertices; rows of one folder are brought together first."""
    (found.repartition(*by) if by else found).write.partitionBy(*by).parquet(path)


def write_nogoods(g: LabeledGraph, queries: DataFrame, path: str, **options) -> None:
    """What the search of a query set learns and keeps: query_id, pos, vid, positions, reason, prefix and values."""
    found = dfs.dfs_search(g, queries, {"learned": dfs.Method()}, embeddings=False, nogoods=True, **options).filter("kind = 'nogood'")
    found.select("query_id", "n_vertices", "pos", "vid", "positions", "reason", "prefix_len", "prefix_id", "vals").write.parquet(path)
