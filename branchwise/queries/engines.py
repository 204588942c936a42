"""All engines and variants of the search on the same patterns, frontier sizes and what the waves learn."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from branchwise.operators import dfs, joins, regions, waves, workloads
from branchwise.operators.storage import settled
from branchwise.plans.pattern import PatternGraph
from branchwise.plans.sqlgen import to_sql

from .patterns import CLIQUE, PATTERNS, X1, X1_PATTERN, A, B, C, cycle, inline, path
from .registry import graph, on, query, with_views

ENGINES = {
    "join": joins.join_match,
    "level": lambda g, p: joins.as_wide(joins.level_match(g, joins.query_set(g.vertices.sparkSession, [p])), p.n),
    "shared": lambda g, p: joins.shared_match(g, p)[0],
    "region": regions.region_match,
    "region_split": lambda g, p: regions.region_match(g, p, unit_edges=4),
    "wave": lambda g, p: waves.wave_match(g, p)[0],
}
#: Variants of the search over a broadcast graph: one job runs them all.
SEARCHES = {
    "dfs": dfs.METHODS["learned"], "dfs_plain": dfs.METHODS["plain"], "dfs_no_lookup": dfs.METHODS["no_lookup"], "dfs_subset": dfs.Method(match="subset"), "dfs_all_patterns": dfs.Method(store="set"), "dfs_smallest": dfs.Method(policy="smallest"), "dfs_unit_roots": dfs.Method(unit_roots=8),
    **{m: dfs.METHODS[m] for m in ("structure_first", "rare_edge_order", "profile_refine")}, **{f"order_{o}": dfs.Method(order=o) for o in ("given", "smallest", "join_size", "tree_path", "dense", "rare_edge")},
}
AGREE = {"gd": PATTERNS["q_tailed_triangle"][1], "gs": path(A, B, C, A)}


def agreement(g, p: PatternGraph, engines: dict) -> DataFrame:
    """engine, found, missing and extra rows beside the join engine."""
    want = settled(joins.join_match(g, p), "want")
    parts = []
    for name, f in engines.items():
        rows = settled(f(g, p), "got")
        parts.append(rows.agg(F.count(F.lit(1)).alias("found")).join(workloads.result_diff(want, rows)).select(F.lit(name).alias("engine"), "found", "missing", "extra"))
    return reduce(DataFrame.unionByName, parts)


def search_agreement(g, p: PatternGraph, methods: dict, shares: int = 3) -> DataFrame:
    """The same for variants of the search: embeddings of each found together, two-way differences by full join."""
    want = joins.join_match(g, p).select(F.array(*(f"m{i}" for i in range(1, p.n + 1))).alias("asg"))
    found = settled(dfs.dfs_search(g, joins.query_set(g.vertices.sparkSession, [p]), methods, None, None, shares=shares).filter("kind = 'embedding'").select("method", "asg"), "got")
    asked = want.withColumn("method", F.explode(F.array(*map(F.lit, methods))))
    both = asked.withColumn("w", F.lit(1)).join(found.withColumn("f", F.lit(1)), ["method", "asg"], "full")
    by = both.groupBy("method").agg(F.count("f").alias("found"), F.count_if(F.col("f").isNull()).alias("missing"), F.count_if(F.col("w").isNull()).alias("extra"))
    named = want.sparkSession.createDataFrame([(m,) for m in methods], "method string")
    return named.join(by, "method", "left").select(F.col("method").alias("engine"), *(F.coalesce(c, F.lit(0)).alias(c) for c in ("found", "missing", "extra")))


for _n, _q in AGREE.items():
    for _kind, _names, _run in (("engines", ENGINES, agreement), ("searches", SEARCHES, search_agreement)):
        _sql = f"SELECT engine, (SELECT count(*) FROM ({to_sql(_q)})) AS found, 0 AS missing, 0 AS extra FROM (VALUES {', '.join(f'({chr(39)}{e}{chr(39)})' for e in _names)}) AS t(engine)"
        query(f"q_{_kind}_agree_{_n}", on(_n, _sql))(lambda s, d, r=_run, m=_names, n=_n, p=_q: r(graph(n, s, d), p, m))
for _e in ("level", "shared", "region", "wave"):
    query(f"q_engine_{_e}", on("gd", to_sql(AGREE["gd"])))(lambda s, d, f=ENGINES[_e]: f(graph("gd", s, d), AGREE["gd"]))
for _m in ("learned", "structure_first", "rare_edge_order", "profile_refine"):
    query(f"q_search_{_m}", on("gd", to_sql(AGREE["gd"])))(lambda s, d, m=_m: dfs.dfs_match(graph("gd", s, d), AGREE["gd"], m))


@query("q_nogoods_sound", "SELECT 0 AS violations")
def q_nogoods_sound(spark, sf_dir):
    """Embeddings that agree with a nogood of the wave engine at all its positions: there must be none."""
    g, p = graph("gs", spark, sf_dir), path(A, B, C, A)
    _, learnt, _ = waves.wave_match(g, p)
    rows = joins.as_array(joins.join_match(g, p))
    masks = [r.reason for r in learnt.select("reason").distinct().collect()] or [0]
    probes = rows.withColumn("reason", F.explode(F.array(*(F.lit(m).cast("bigint") for m in masks)))).select("reason", waves._values("reason").alias("vals"))
    return probes.join(learnt, ["reason", "vals"], "left_semi").agg(F.count(F.lit(1)).cast("int").alias("violations"))


def prefix(p: PatternGraph, k: int) -> PatternGraph:
    return PatternGraph(p.labels[:k], tuple(e for e in p.edges if max(e) <= k))


LEVELS = path(A, B, C, A)
_level_sql = " UNION ALL ".join(f"SELECT {k} AS level, count(*) AS rows FROM ({to_sql(prefix(LEVELS, k))})" for k in range(1, 5))


@query("q_level_sizes", on("gd", _level_sql))
def q_level_sizes(spark, sf_dir):
    return joins.level_sizes(graph("gd", spark, sf_dir), joins.query_set(spark, [LEVELS])).select("level", "rows")


@query("q_shared_levels", on("gd", f"""SELECT level, rows, projections, dead FROM (SELECT 1 AS level, count(*) AS rows, 0 AS projections, 0 AS dead FROM ({to_sql(prefix(LEVELS, 1))})
UNION ALL SELECT 2, (SELECT count(*) FROM ({to_sql(prefix(LEVELS, 2))})), count(DISTINCT m1), count(DISTINCT m1) - (SELECT count(DISTINCT m1) FROM ({to_sql(prefix(LEVELS, 2))})) FROM ({to_sql(prefix(LEVELS, 1))})
UNION ALL SELECT 3, (SELECT count(*) FROM ({to_sql(prefix(LEVELS, 3))})), count(DISTINCT m2), count(DISTINCT m2) - (SELECT count(DISTINCT m2) FROM ({to_sql(prefix(LEVELS, 3))})) FROM ({to_sql(prefix(LEVELS, 2))}))"""))
def q_shared_levels(spark, sf_dir):
    """Rows, distinct projections and projections without an image, for the first three levels of a path."""
    return joins.shared_match(graph("gd", spark, sf_dir), LEVELS, (1, 2, 3, 4))[1].filter("level < 4")


@query("q_plain_calls", on("gd", f"SELECT 1 + CAST(sum(rows) AS BIGINT) AS search_calls FROM ({_level_sql})"))
def q_plain_calls(spark, sf_dir):
    found = workloads.run_experiment(graph("gd", spark, sf_dir), joins.query_set(spark, [LEVELS]), {"plain": dfs.Method("plain")}, cap=None)
    return found.select("search_calls")


# Why nothing is found: prefixes of the clique, none of which can be completed.
_steps = {k: to_sql(prefix(CLIQUE, k)) for k in range(1, 5)}
_columns = {k: ", ".join(f"m{i}" for i in range(1, k + 1)) for k in range(1, 5)}
_views = ", ".join([*(f"p{k} AS MATERIALIZED ({s})" for k, s in _steps.items())])
_causes = "SELECT 0 AS level, CASE WHEN EXISTS (SELECT 1 FROM p1) THEN 'CHILD' ELSE 'WIPEOUT' END AS cause, 1 AS rows WHERE NOT EXISTS (SELECT 1 FROM p4)" + "".join(
    f" UNION ALL SELECT {k}, cause, count(*) FROM (SELECT CASE WHEN ({_columns[k]}) IN (SELECT ({_columns[k]}) FROM p{k + 1}) THEN 'CHILD' ELSE 'WIPEOUT' END AS cause FROM p{k} WHERE ({_columns[k]}) NOT IN (SELECT ({_columns[k]}) FROM p4)) GROUP BY cause" for k in (1, 2, 3)
)


@query("o_explain_empty", with_views("gd", _views, f"SELECT level, cause, CAST(rows AS BIGINT) AS rows FROM ({_causes})"))
def o_explain_empty(spark, sf_dir):
    return waves.explain_empty(graph("gd", spark, sf_dir), CLIQUE).groupBy("level", "cause").agg(F.sum("rows").alias("rows"))


@query("o_reason_bits", "SELECT * FROM (VALUES (1, 'WIPEOUT', 1, 1, 1), (3, 'WIPEOUT', 4, 1, 0), (4, 'REUSE', 9, 2, 6)) AS t(level, cause, reason, bits, rows) WHERE rows > 0")
def o_reason_bits(spark, sf_dir):
    found = waves.explain_empty(inline(spark, *X1), X1_PATTERN).filter("cause IN ('WIPEOUT', 'REUSE')")
    return found.select("level", "cause", F.col("reason").cast("int").alias("reason"), F.bit_count("reason").alias("bits"), F.col("rows").cast("int").alias("rows"))


@query("o_wave_stats", on("gd", f"SELECT 3 AS level, count(*) AS rows FROM ({to_sql(cycle(A, B, C))})"))
def o_wave_stats(spark, sf_dir):
    """Candidates of the first level after the split, over all waves: the triangles of the clique, whatever is learnt."""
    return waves.wave_match(graph("gd", spark, sf_dir), CLIQUE)[2].groupBy("level").agg(F.sum("rows").alias("rows")).filter("level = 3")
