"""The experiments: query sets cut from the data by random walks, searched by the method and by what it is compared with.

Sizes, counts and budgets are arguments; the registered ones are stated beside them. ``main`` prints the tables of larger runs.
"""

from __future__ import annotations

import sys

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from branchwise.operators import dfs, workloads
from branchwise.operators.joins import query_set
from branchwise.operators.kernel import MODES
from branchwise.operators.storage import settled
from branchwise.plans.pattern import PatternGraph
from branchwise.plans.sqlgen import to_sql

from .patterns import A, B, C, cycle, path
from .registry import graph, on, query

COMPARATORS = ["learned", "structure_first", "rare_edge_order", "profile_refine"]
M = dfs.Method


def patterns(g, sizes: list[int], count: int, induced: bool, seed: int = 1) -> DataFrame:
    return settled(workloads.random_walk_patterns(g, sizes, count, seed, induced), "patterns")


def experiment(graph_name: str, sizes: list[int], methods, count: int, induced: bool = False, budget: float = 0.25, cap: int | None = 1000, set_budget: float | None = None):
    """Statistics of a query set: count patterns a size, budget seconds a query, cap embeddings."""

    def run(spark, sf_dir) -> DataFrame:
        g = graph(graph_name, spark, sf_dir)
        return workloads.run_experiment(g, patterns(g, sizes, count, induced), methods, cap, budget, set_budget)

    return run


#: Registered sets: patterns a size; every size of the published ranges that the walk reaches.
SPARSE, DENSE, COUNT = [4, 8, 12, 16, 20, 26, 32, 36], [4, 6, 8, 10, 12, 14], 25
#: Seconds of a query by the published rule: a set of 10000 that takes more than a day is unfinished. It is the set's time that is bounded: one
#: search may take all of it, and only then is it ended.
A_QUERY = 86_400 / 10_000
TIMED = {"sparse": experiment("gs_name", SPARSE, COMPARATORS, COUNT, budget=A_QUERY * COUNT), "dense": experiment("gd_size", DENSE, COMPARATORS, COUNT, budget=0.1)}
CALLS = {
    "sparse": experiment("gs_type", [4, 8, 12, 16, 18, 20], ["learned", "no_lookup"], COUNT, induced=True),
    "dense": experiment("gd_size", [4, 6, 8, 9], ["learned", "no_lookup"], COUNT, induced=True),
}
for _kind in ("sparse", "dense"):
    query(f"w_time_{_kind}")(lambda s, d, k=_kind: workloads.summarise(TIMED[k](s, d), A_QUERY if k == "sparse" else None))
    query(f"w_speedup_{_kind}")(lambda s, d, k=_kind: workloads.compare_all(TIMED[k](s, d)))
    query(f"w_calls_{_kind}")(lambda s, d, k=_kind: workloads.compare(CALLS[k](s, d), "no_lookup", "learned"))
_DNF = ["size", "method", "queries", "dnf_share", "capped_share"]


#: Leaves that are searched before a clique at the same root, which mostly is not there: the same failure under every choice of leaves.
LEAVES, HARD = ("SMALL", "ECONOMY", "SMALL"), (0, 1, 2, 3)


def hard(leaves: int) -> PatternGraph:
    k = leaves + 1
    return PatternGraph(("MEDIUM", *LEAVES[:leaves], "STANDARD", "LARGE", "PROMO"), (*((1, i) for i in range(2, k + 1)), (1, k + 1), (1, k + 2), (1, k + 3), (k + 1, k + 2), (k + 1, k + 3), (k + 2, k + 3)))


#: Roots of a share: graphs up to some 30000 vertices are searched by one task a pattern and method.
SHARE_ROOTS = 5000


def _hard_stats(spark, sf_dir, modes=("learned", "no_lookup")) -> DataFrame:
    """Searched as numbered and without filters, so that only what is learnt can help; no cap, no budget."""
    methods = {m: M(m) for m in modes}
    g = graph("gd_type", spark, sf_dir)
    roots = g.vertices.filter(F.col("label") == hard(0).labels[0]).count()
    return workloads.run_experiment(g, query_set(spark, [hard(k) for k in HARD]), methods, None, None, shares=max(1, -(-roots // SHARE_ROOTS)))


@query("w_hard")
def w_hard(spark, sf_dir):
    """Calls and time with and without look-up, by the number of leaves."""
    return workloads.compare(_hard_stats(spark, sf_dir), "no_lookup", "learned").select((F.col("size") - 4).alias("leaves"), "calls_base", "calls_other", "call_ratio", "speedup", "differing")


_hard_found = " UNION ALL ".join(f"SELECT {k} AS leaves, count(*) AS n_found, 3 AS agreeing, true AS fewer FROM ({to_sql(hard(k))})" for k in HARD)


@query("w_hard_found", on("gd_type", _hard_found))
def w_hard_found(spark, sf_dir):
    """The same searches: what all methods find, and that learning needs no more calls."""
    calls = lambda m: F.max(F.when(F.col("method") == m, F.col("search_calls")))
    by = _hard_stats(spark, sf_dir, MODES).groupBy("n_vertices").agg(F.max("n_found").alias("n_found"), F.count(F.lit(1)).alias("agreeing"), (calls("learned") <= calls("no_lookup")).alias("fewer"), F.count_distinct("n_found").alias("kinds"))
    return by.filter("kinds = 1").select((F.col("n_vertices") - 4).alias("leaves"), "n_found", "agreeing", "fewer")


@query("w_dnf")
def w_dnf(spark, sf_dir):
    """Shares of unfinished searches on the three graphs, with a budget for each query and one for the whole set."""
    parts = [workloads.summarise(experiment(g, [k], ["learned", "no_lookup", "plain"], 5, budget=0.1, set_budget=60)(spark, sf_dir)).select(F.lit(g).alias("graph"), *_DNF) for g, k in (("gs_type", 20), ("gd_size", 12), ("gc", 8))]
    return parts[0].unionByName(parts[1]).unionByName(parts[2])


INVARIANT = {"gs_type": [4, 8, 12], "gd_size": [4, 6, 8]}
_SETS = 30


@query("w_invariants", "SELECT * FROM (VALUES " + ", ".join(f"('{g}', {_SETS * len(k)}, 0, 0, 0, 0)" for g, k in INVARIANT.items()) + ") AS t(graph, queries, unmatched, differing, more_calls, disconnected)")
def w_invariants(spark, sf_dir):
    """Whatever the data: every pattern cut from it is connected and found, all methods agree, and learning never adds a call. No search
    has a budget, so that none is left out."""
    parts = []
    for name, sizes in INVARIANT.items():
        g = graph(name, spark, sf_dir)
        q = patterns(g, sizes, _SETS, True, 3)
        stats = workloads.run_experiment(g, q, ["learned", "no_lookup", "structure_first", "profile_refine"], 100, None)
        parts.append(workloads.invariants(q, stats).select(F.lit(name).alias("graph"), "queries", "unmatched", "differing", "more_calls", "disconnected"))
    return parts[0].unionByName(parts[1])


@query("w_walk_patterns", "SELECT * FROM (VALUES (4, 20, 80, true), (8, 20, 160, true), (12, 20, 240, true)) AS t(size, patterns, vertices, tied)")
def w_walk_patterns(spark, sf_dir):
    """Per size: how many patterns, their vertices, and whether each has the edges a connected one needs."""
    q = patterns(graph("gs_name", spark, sf_dir), [4, 8, 12], 20, True)
    return q.groupBy(F.col("n_vertices").alias("size")).agg(F.count(F.lit(1)).alias("patterns"), F.sum(F.size("vertices")).alias("vertices"), F.bool_and(F.size("edges") >= F.col("n_vertices") - 1).alias("tied"))


def variants(graph_name: str, methods: dict, sizes: list[int], count: int = 10):
    def run(spark, sf_dir) -> DataFrame:
        stats = experiment(graph_name, sizes, methods, count)(spark, sf_dir)
        return workloads.summarise(stats).select("size", "method", "queries", "search_calls", "n_found", "slot_hits", "slots_used", "avg_ms", "dnf_share")

    return run


UNITS = {f"roots_{k or 'all'}": M(filters=dfs.STRUCTURAL, order="tree_path", unit_roots=k) for k in (1, 8, 64, 0)}
POLICIES = {f"{m}_{p}_{t}": M(filters=dfs.STRUCTURAL, order="tree_path", match=m, policy=p, store=t) for m in ("prefix", "subset") for p in ("last", "smallest") for t in ("slots", "set")}
query("w_unit_size")(variants("gs_type", UNITS, [6, 10]))
query("w_slot_policy")(variants("gs_type", POLICIES, [6, 10]))


@query("w_shares", on("gs_type", f"SELECT shares, (SELECT count(*) FROM ({to_sql(path('MEDIUM', 'STANDARD', 'LARGE', 'MEDIUM'))})) AS n_found, true AS within FROM (VALUES (1), (4), (16)) AS t(shares)"))
def w_shares(spark, sf_dir):
    """One query over so many parallel shares: the same embeddings, and never more calls than without look-up."""
    g, p = graph("gs_type", spark, sf_dir), path("MEDIUM", "STANDARD", "LARGE", "MEDIUM")
    parts = []
    for n in (1, 4, 16):
        found = dfs.dfs_search(g, query_set(spark, [p]), {m: dfs.METHODS[m] for m in ("learned", "no_lookup")}, None, None, embeddings=False, shares=n).filter("kind = 'stats'")
        calls = lambda m: F.max(F.when(F.col("method") == m, F.col("search_calls")))
        parts.append(found.agg(F.lit(n).alias("shares"), F.max("n_found").alias("n_found"), (calls("learned") <= calls("no_lookup")).alias("within")))
    return parts[0].unionByName(parts[1]).unionByName(parts[2])


_scale = [("gs", cycle(A, B, C)), ("gd", cycle(A, B, C)), ("gc", cycle(A, B, C))]
_edges = {"gs": "l_orderkey, l_returnflag, l_linestatus, (l_quantity <= 25)", "gd": "l_orderkey, l_returnflag", "gc": "l_orderkey"}


def _scale_sql(name: str, keys: str) -> str:
    cols = ", ".join(f"{k} AS k{i}" for i, k in enumerate(keys.split(", ")))
    using = ", ".join(f"k{i}" for i in range(len(keys.split(", "))))
    return f"SELECT '{name}' AS graph, count(*) AS n_edges FROM (SELECT DISTINCT x.p AS a, y.p AS b FROM (SELECT DISTINCT {cols}, l_partkey AS p FROM lineitem) x JOIN (SELECT DISTINCT {cols}, l_partkey AS p FROM lineitem) y USING ({using}) WHERE x.p < y.p)"


@query("w_scale", " UNION ALL ".join(_scale_sql(n, k) for n, k in _edges.items()))
def w_scale(spark, sf_dir):
    """Edges of the three graphs; their time over scale factors is in the bench and in ``main``."""
    parts = [graph(n, spark, sf_dir).stats().select(F.lit(n).alias("graph"), "n_edges") for n in _edges]
    return parts[0].unionByName(parts[1]).unionByName(parts[2])


def main(sf_dir: str = "/root/testdata/sf0.01", count: int = 100, budget: float = 0.5, cores: str = "*") -> None:
    """python -m branchwise.queries.experiments [folder] [patterns a size] [seconds a query] [cores]"""
    from pyspark.sql import SparkSession

    spark = SparkSession.builder.master(f"local[{cores}]").config("spark.sql.shuffle.partitions", "16").config("spark.driver.memory", "6g").config("spark.ui.showConsoleProgress", "false").getOrCreate()
    spark.sparkContext.setLogLevel("ERROR")
    for name, sizes, cap in (("gs_type", [4, 8, 12, 16, 18, 20, 24], 1000), ("gs", [8, 12, 16, 20], 1000), ("gd_size", [4, 6, 8, 9], 1000)):
        for induced in (False, True):
            print(name, "induced" if induced else "walked", "calls without look-up over with it")
            stats = experiment(name, sizes, ["learned", "no_lookup"], count, induced, budget, cap)(spark, sf_dir)
            workloads.compare(stats, "no_lookup", "learned").orderBy("size").show(50, False)
    for name, sizes in (("gs_name", SPARSE), ("gd_size", DENSE)):
        print(name, "time of the comparators over ours")
        stats = experiment(name, sizes, COMPARATORS, count, False, budget)(spark, sf_dir)
        workloads.compare_all(stats).select("base", "size", "queries", "finished", "speedup", "speedup_with_prep", "best_speedup", "dnf_base", "dnf_other").orderBy("base", "size").show(50, False)


if __name__ == "__main__":
    main(*[t(x) for t, x in zip((str, int, float, str), sys.argv[1:])])
