"""One pattern, one query: shapes, entity graphs, sweeps over labels and degrees, worked examples, variants of the problem."""

from __future__ import annotations

from pyspark.sql import functions as F

from branchwise.operators import dfs, joins, match, workloads
from branchwise.operators.graph import LabeledGraph
from branchwise.plans.pattern import PatternGraph
from branchwise.plans.sqlgen import LABELLED, to_sql

from .registry import graph, on, query, with_views

A, B, C = "Brand#4", "Brand#19", "Brand#2"


def path(*labels: str) -> PatternGraph:
    return PatternGraph(labels, tuple((i, i + 1) for i in range(1, len(labels))))


def cycle(*labels: str) -> PatternGraph:
    return PatternGraph(labels, tuple((i, i % len(labels) + 1) for i in range(1, len(labels) + 1)))


CLIQUE = PatternGraph((A, B, C, A), ((1, 2), (1, 3), (1, 4), (2, 3), (2, 4), (3, 4)))
TYPES = path("MEDIUM", "STANDARD", "LARGE", "MEDIUM")
#: key -> graph, pattern.
PATTERNS: dict[str, tuple[str, PatternGraph]] = {
    "q_edge": ("gs", path(A, B)),
    "q_path3": ("gd", path(A, B, C)),
    "q_path4_abca": ("gd", path(A, B, C, A)),
    "q_path4_abca_sparse": ("gs", path(A, B, C, A)),
    "q_path4_size": ("gd_size", path("2", "35", "48", "2")),
    "q_triangle_abc": ("gd", cycle(A, B, C)),
    "q_triangle_aab": ("gd", cycle(A, A, B)),
    "q_cycle4": ("gd", cycle(A, B, A, B)),
    "q_star3": ("gd", PatternGraph((A, B, B, B), ((1, 2), (1, 3), (1, 4)))),
    "q_diamond": ("gd", PatternGraph((A, B, A, B), ((1, 2), (2, 3), (3, 4), (4, 1), (1, 3)))),
    "q_tailed_triangle": ("gd", PatternGraph((A, B, C, A), ((1, 2), (2, 3), (3, 1), (3, 4)))),
    "q_clique4": ("gd", CLIQUE),
    "q_clique4_dense": ("gc", CLIQUE),
    "q_bowtie": ("gd", PatternGraph((A, B, C, B, C), ((1, 2), (2, 3), (3, 1), (1, 4), (4, 5), (5, 1)))),
    "q_tree6": ("gd", PatternGraph((A, B, C, A, B, C), ((1, 2), (1, 3), (2, 4), (2, 5), (3, 6)))),
    "q_path6": ("gd", path(A, B, C, A, B, C)),
    "q_house5": ("gd", PatternGraph((A, B, C, A, B), ((1, 2), (2, 3), (3, 4), (4, 1), (1, 5), (2, 5)))),
    "q_trade_pair": ("gt", path("customer", "1-URGENT", A, "1-URGENT", "customer")),
    "q_trade_local": ("gt_kind", cycle("customer", "nation", "supplier", "order")),
    "q_vector_wedge": ("ge", path("0", "1", "0")),
    "q_vector_triangle": ("ge", cycle("0", "0", "0")),
    "q_user_wedge": ("gu", path("click", "view", "click")),
    "q_doc_copies": ("gk", cycle("es", "es", "es")),
    "q_docs_of_a_line": ("gl", path("es", "line", "es")),
    "q_page_host_fan": ("gp", cycle("page", "host", "page", "href")),
    "q_turn_chain": ("gv", path("system", "user", "assistant")),
    "q_turn_chain4": ("gv", path("user", "assistant", "user", "assistant")),
    "q_single_vertex": ("gs", PatternGraph((A,), ())),
    "q_missing_label": ("gs", path(A, "no such brand")),
    "q_disconnected": ("gs", PatternGraph((A, B, C), ((2, 3),))),
    # The same path over 6, 25, 50 and 64 labels, and over graphs of rising degree.
    "w_label_sweep_type": ("gs_type", TYPES),
    "w_label_sweep_brand": ("gs", path(A, B, C)),
    "w_label_sweep_size": ("gs_size", path("2", "35", "48")),
    "w_label_sweep_name": ("gs_name", path("red plate", "small widget", "hot plate")),
    "w_degree_sweep_sparse": ("gs", cycle(A, B, C)),
    "w_degree_sweep_middle": ("gd", PatternGraph((A, B, C), ((1, 2), (1, 3), (2, 3)))),
    "w_degree_sweep_dense": ("gc", cycle(A, B, C)),
}

for _key, (_name, _p) in PATTERNS.items():
    query(_key, on(_name, to_sql(_p)))(lambda s, d, n=_name, p=_p: joins.join_match(graph(n, s, d), p))

# Variants of the problem.
query("q_capped_1000", on("gd_type", to_sql(TYPES, 1000)))(lambda s, d: joins.join_match(graph("gd_type", s, d), TYPES, limit=1000))
query("q_capped_1000_dfs", on("gd_type", to_sql(TYPES, 1000)))(lambda s, d: dfs.dfs_match(graph("gd_type", s, d), TYPES, cap=1000))
query("q_count", on("gs_type", to_sql(TYPES, select="count(*) AS n_found")))(lambda s, d: joins.count_matches(graph("gs_type", s, d), TYPES))
query("q_homomorphism", on("gs", to_sql(path(A, B, A), injective=False)))(lambda s, d: joins.join_match(graph("gs", s, d), path(A, B, A), injective=False))
query("q_facade", on("gd", to_sql(cycle(A, B, C))))(lambda s, d: match.match(graph("gd", s, d), cycle(A, B, C)))
query("q_facade_long", on("gs", to_sql(path(A, B, C, A, B, C, A))))(lambda s, d: match.match(graph("gs", s, d), path(A, B, C, A, B, C, A)))
_WHERE = {2: "vid % 2 = 0", (1, 3): "<"}
for _engine in ("join", "dfs"):
    query(f"q_where_{_engine}", on("gd", f"SELECT * FROM ({to_sql(cycle(A, B, A, B))}) WHERE m2 % 2 = 0 AND m1 < m3"))(lambda s, d, e=_engine: match.match(graph("gd", s, d), cycle(A, B, A, B), engine=e, where=_WHERE))


@query("q_exists", on("gd", f"SELECT count(*) > 0 AS found FROM ({to_sql(cycle(A, B, C))})"))
def q_exists(spark, sf_dir):
    return spark.createDataFrame([(joins.exists_match(graph("gd", spark, sf_dir), cycle(A, B, C)),)], "found boolean")


@query("q_count_estimate", on("gs_type", f"SELECT count(*) / 0.5 AS estimate FROM ({to_sql(TYPES)}) WHERE (m1 * 2654435761) % 4294967296 < {2**31}"))
def q_count_estimate(spark, sf_dir):
    return workloads.estimate_count(graph("gs_type", spark, sf_dir), TYPES, 0.5)


# Worked examples on inline graphs, for tests; the queries below them do the same on the tables.
def inline(spark, vertices: dict[str, list[int]], pairs: list[tuple[int, int]]) -> LabeledGraph:
    rows = [(v, x) for x, ids in vertices.items() for v in ids]
    return LabeledGraph.from_edges(spark.createDataFrame(rows, "vid bigint, label string"), spark.createDataFrame(pairs, "a bigint, b bigint"), loops=True)


def inline_sql(vertices: dict[str, list[int]], pairs: list[tuple[int, int]]) -> str:
    v = ", ".join(f"({i}, '{x}')" for x, ids in vertices.items() for i in ids)
    e = ", ".join(f"({a}, {b}), ({b}, {a})" for a, b in pairs if a != b)
    loops = ", ".join(f"({a})" for a, b in pairs if a == b) or "(-1)"
    return f"""WITH v(vid, label) AS (SELECT CAST(a AS BIGINT), b FROM (VALUES {v}) AS t(a, b)),
e(src, dst) AS (SELECT CAST(a AS BIGINT), CAST(b AS BIGINT) FROM (VALUES {e}) AS t(a, b)),
loops(vid) AS (SELECT CAST(a AS BIGINT) FROM (VALUES {loops}) AS t(a)), {LABELLED}"""


X1 = ({"a": [1, 8], "b": [2, 3, 4], "c": [5, 6, 7]}, [(1, 2), (1, 3), (1, 4), *((i, j) for i in (2, 3, 4) for j in (5, 6, 7)), (5, 8), (6, 1), (7, 1)])
X2 = ({"a": [1, 5], "b": [2, 3], "c": [4]}, [(1, 2), (1, 3), (1, 4), (3, 5)])
X1_PATTERN, X2_PATTERN = path(*"abca"), PatternGraph(tuple("abca"), ((1, 2), (1, 3), (2, 4)))
#: X1 with edges from two vertices to themselves.
LOOPED = (X1[0], [*X1[1], (3, 3), (4, 4), (7, 7)])
LOOPED_PATTERN = PatternGraph(tuple("abca"), ((1, 2), (2, 2), (2, 3), (3, 4)))

EXAMPLE, TRAP = path(A, B, C, A), PatternGraph((A, B, C, A), ((1, 2), (1, 3), (2, 4)))
LOOPED_TYPES = PatternGraph(TYPES.labels, (*TYPES.edges, (2, 2)))

query("q_worked_example", on("gs", to_sql(EXAMPLE)))(lambda s, d: dfs.dfs_match(graph("gs", s, d), EXAMPLE, dfs.Method()))
query("q_reuse_trap", on("gs", to_sql(TRAP)))(lambda s, d: dfs.dfs_match(graph("gs", s, d), TRAP, dfs.Method()))
query("q_self_loop", on("gs_loops", to_sql(LOOPED_TYPES)))(lambda s, d: joins.join_match(graph("gs_loops", s, d), LOOPED_TYPES))
query("q_self_loop_dfs", on("gs_loops", to_sql(LOOPED_TYPES)))(lambda s, d: dfs.dfs_match(graph("gs_loops", s, d), LOOPED_TYPES))

#: What the search of EXAMPLE in the given order learns, by hand. A third vertex without a neighbour of the first label fails under
#: every root (lone); one whose only such neighbour is the root fails under that root (c_near: n = 1). A second vertex all of
#: whose third ones are lone, or that has none, fails under every root (dead); a failure under every root is met once.
_LEARNT = f"""ab AS MATERIALIZED (SELECT src AS a, dst AS b FROM le WHERE sl = '{A}' AND dl = '{B}'), bc AS MATERIALIZED (SELECT src AS b, dst AS c FROM le WHERE sl = '{B}' AND dl = '{C}'),
c_near AS MATERIALIZED (SELECT src AS c, count(*) AS n, min(dst) AS one FROM le WHERE sl = '{C}' AND dl = '{A}' GROUP BY src),
b_live AS MATERIALIZED (SELECT DISTINCT b FROM bc JOIN c_near USING (c)), abc AS MATERIALIZED (SELECT a, b, c FROM ab JOIN bc USING (b)),
lone AS MATERIALIZED (SELECT DISTINCT c FROM abc WHERE c NOT IN (SELECT c FROM c_near)), dead AS MATERIALIZED (SELECT DISTINCT b FROM ab WHERE b NOT IN (SELECT b FROM b_live)),
again AS MATERIALIZED (SELECT DISTINCT a, c FROM abc JOIN c_near USING (c) WHERE n = 1 AND one = a), full_rows AS MATERIALIZED ({to_sql(EXAMPLE)})"""
_PLAIN_CALLS = f"1 + (SELECT count(*) FROM v WHERE label = '{A}') + (SELECT count(*) FROM ab) + (SELECT count(*) FROM abc) + (SELECT count(*) FROM full_rows)"
_LEARNED_CALLS = f"""1 + (SELECT count(*) FROM v WHERE label = '{A}') + (SELECT count(*) FROM ab JOIN b_live USING (b)) + (SELECT count(*) FROM dead) + (SELECT count(*) FROM lone)
+ (SELECT count(*) FROM again) + (SELECT count(*) FROM abc JOIN c_near USING (c) WHERE n > 1 OR one <> a) + (SELECT count(*) FROM full_rows)"""


@query("q_worked_example_calls", with_views("gs", _LEARNT, f"SELECT method, CAST(calls AS INTEGER) AS search_calls FROM (SELECT 'plain' AS method, {_PLAIN_CALLS} AS calls UNION ALL SELECT 'no_lookup', {_PLAIN_CALLS} UNION ALL SELECT 'learned', {_LEARNED_CALLS})"))
def q_worked_example_calls(spark, sf_dir):
    found = workloads.run_experiment(graph("gs", spark, sf_dir), joins.query_set(spark, [EXAMPLE]), {m: dfs.Method(m) for m in ("plain", "no_lookup", "learned")}, None, None)
    return found.select("method", F.col("search_calls").cast("int").alias("search_calls"))


@query("q_nogoods", with_views("gs", _LEARNT, f"""SELECT pos, CAST(vid AS INTEGER) AS vid, reason, prefix_len FROM (
SELECT 0 AS pos, vid, 1 AS reason, 0 AS prefix_len FROM v WHERE label = '{A}' AND vid NOT IN (SELECT m1 FROM full_rows)
UNION ALL SELECT 1, b, 2, 0 FROM dead UNION ALL SELECT 2, c, 4, 0 FROM lone UNION ALL SELECT 2, c, 5, 1 FROM again
UNION ALL SELECT 1, b, 3, 1 FROM (SELECT DISTINCT a, b FROM ab JOIN b_live USING (b)) t WHERE NOT EXISTS (SELECT 1 FROM full_rows WHERE m1 = t.a AND m2 = t.b))"""))
def q_nogoods(spark, sf_dir):
    found = dfs.dfs_search(graph("gs", spark, sf_dir), joins.query_set(spark, [EXAMPLE]), {"learned": dfs.Method()}, None, None, embeddings=False, nogoods=True).filter("kind = 'nogood'")
    return found.select("pos", *(F.col(c).cast("int").alias(c) for c in ("vid", "reason", "prefix_len")))
