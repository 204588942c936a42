"""Query sets by random walks, experiments over methods, and their measures."""

from __future__ import annotations

import json
import random
import time
from functools import reduce

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from branchwise.plans.pattern import QUERY_SET

from .dfs import METHODS, Method, broadcast_graph, dfs_search, local_graph
from .graph import LabeledGraph
from .storage import settled


def random_walk_patterns(g: LabeledGraph, sizes: list[int], count: int, seed: int = 0, induced: bool = True) -> DataFrame:
    """A query set: per size, patterns cut from the data by seeded random walks until so many distinct vertices are seen. A walk
    that stays too long starts anew elsewhere; when no start is left that is an error, so a set is never smaller than
    asked for. induced: all data edges among them, else the walked ones."""
    spark = g.vertices.sparkSession
    box = broadcast_graph(g)
    wanted = spark.createDataFrame([(i, k) for i, k in enumerate(k for k in sizes for _ in range(count))], "query_id int, k int")

    def walked_set(graph, v, k, rng):
        """Numbers of the k vertices of a walk from v in the order they were seen, and the walked edges; None if it stays too long."""
        number, walked = {v: 1}, set()
        for _ in range(50 * k):
            if len(number) == k:
                break
            w = rng.choice(graph.near(v))
            number.setdefault(w, len(number) + 1)
            walked.add((min(number[v], number[w]), max(number[v], number[w])))
            v = w
        return (number, walked) if len(number) == k else None

    def run(parts):
        graph = local_graph(box)
        starts = graph.starts()
        for part in parts:
            out = []
            for q, k in zip(part["query_id"], part["k"]):
                rng = random.Random(f"{seed}-{q}")
                found = next((f for v in rng.sample(starts, len(starts)) if (f := walked_set(graph, v, k, rng))), None)
                if found is None:
                    raise ValueError(f"no walk sees {k} vertices: the graph has no component of that size, or none that a walk crosses")
                number, walked = found
                edges = {(min(number[a], number[b]), max(number[a], number[b])) for a in number for b in graph.adjacency[a] if b in number} if induced else walked
                out.append((q, json.dumps([{"u": i, "label": graph.label(x)} for x, i in number.items()]), json.dumps([{"a": a, "b": b} for a, b in sorted(edges)])))
            yield pd.DataFrame(out, columns=["query_id", "vertices", "edges"])

    rows = wanted.repartition(spark.sparkContext.defaultParallelism, "query_id").mapInPandas(run, "query_id int, vertices string, edges string")
    parsed = rows.select("query_id", F.from_json("vertices", "array<struct<u: int, label: string>>").alias("vertices"), F.from_json("edges", "array<struct<a: int, b: int>>").alias("edges"))
    return parsed.select("query_id", F.size("vertices").alias("n_vertices"), "vertices", "edges", F.sequence(F.lit(1), F.size("vertices")).alias("match_order")).to(spark.createDataFrame([], QUERY_SET).schema)


def run_experiment(g: LabeledGraph, queries: DataFrame, methods: list[str] | dict[str, Method] = ("learned", "no_lookup"), cap: int | None = 1000, query_budget_s: float | None = 8.64, set_budget_s: float | None = None, shares: int = 1) -> DataFrame:
    """The search statistics of every query and method: settled, with the wall time of the whole job beside each row (job_ms). shares:
    tasks over which the roots of a query are dealt; statistics are those of the whole query."""
    chosen = methods if isinstance(methods, dict) else {m: METHODS[m] for m in methods}
    began = time.perf_counter()
    found = settled(dfs_search(g, queries, chosen, cap, query_budget_s, set_budget_s, embeddings=False, shares=shares).filter("kind = 'stats'").drop("kind", "asg", "pos", "vid", "reason", "positions", "prefix_len", "prefix_id", "vals"), "experiment")
    return found.withColumn("job_ms", F.lit((time.perf_counter() - began) * 1000))


def summarise(stats: DataFrame, a_query_s: float | None = None) -> DataFrame:
    """Per size and method: mean times, calls of the set, failures by cause, slots, and the share that did not finish. a_query_s: what
    a set may take for each of its queries, all together; one that takes more is unfinished (set_dnf) and has no mean times."""
    sums = [F.sum(c).alias(c) for c in ("search_calls", "n_found", "f_wipeout", "f_reuse", "f_known", "f_child", "f_check", "slot_writes", "slot_overwrites", "slot_hits", "slots_used")]
    out = stats.groupBy(F.col("n_vertices").alias("size"), "method").agg(
        F.count(F.lit(1)).alias("queries"), (F.avg("elapsed_ns") / 1e6).alias("search_ms"), (F.avg("prep_ns") / 1e6).alias("prep_ms"), ((F.avg("elapsed_ns") + F.avg("prep_ns")) / 1e6).alias("avg_ms"),
        F.avg(F.col("dnf").cast("int")).alias("dnf_share"), F.avg(F.col("capped").cast("int")).alias("capped_share"), *sums,
    )
    if a_query_s is None:
        return out
    late = (F.col("avg_ms") > a_query_s * 1000) | (F.col("dnf_share") > 0)
    return out.withColumn("set_dnf", late).withColumns({c: F.when(~F.col("set_dnf"), F.col(c)) for c in ("search_ms", "prep_ms", "avg_ms")})


def compare(stats: DataFrame, base: str, other: str) -> DataFrame:
    """Per size: how many times more calls and time base takes than other, over the queries both finished (null if there are
    none; an unfinished search has cut sums). overhead: time of other over time of base where nothing was pruned, that is
    where the calls are equal. more_calls: queries in which other needs more."""
    side = lambda m, s: stats.filter(F.col("method") == m).select("query_id", F.col("n_vertices").alias("size"), F.col("search_calls").alias(f"calls_{s}"), F.col("elapsed_ns").alias(f"ns_{s}"), (F.col("elapsed_ns") + F.col("prep_ns")).alias(f"all_{s}"), F.col("n_found").alias(f"found_{s}"), F.col("dnf").alias(f"dnf_{s}"))
    both = side(base, "base").join(side(other, "other"), ["query_id", "size"])
    done = ~F.col("dnf_base") & ~F.col("dnf_other")
    total = lambda c, when=done: F.sum(F.when(when, F.col(c)))
    same = done & (F.col("calls_base") == F.col("calls_other"))
    return both.groupBy("size").agg(
        F.count(F.lit(1)).alias("queries"), F.count_if(done).alias("finished"), total("calls_base").alias("calls_base"), total("calls_other").alias("calls_other"),
        (total("calls_base") / total("calls_other")).alias("call_ratio"), (total("ns_base") / total("ns_other")).alias("speedup"), (total("all_base") / total("all_other")).alias("speedup_with_prep"), F.max(F.when(done, F.col("all_base") / F.col("all_other"))).alias("best_speedup"),
        (total("ns_other", same) / total("ns_base", same)).alias("overhead"), F.count_if((F.col("found_base") != F.col("found_other")) & done).alias("differing"), F.count_if((F.col("calls_other") > F.col("calls_base")) & done).alias("more_calls"),
        F.count_if("dnf_base").alias("dnf_base"), F.count_if("dnf_other").alias("dnf_other"),
    )


def compare_all(stats: DataFrame, other: str = "learned") -> DataFrame:
    """compare with every other method of an experiment, one row per method (base) and size."""
    names = sorted(r.method for r in stats.select("method").distinct().collect())  # a handful
    parts = [compare(stats, m, other).select(F.lit(m).alias("base"), "*") for m in names if m != other]
    return reduce(DataFrame.unionByName, parts)


def invariants(queries: DataFrame, stats: DataFrame, other: str = "learned") -> DataFrame:
    """One row of what must hold for a set cut from the data: queries, patterns that are not connected (disconnected), searches without
    an embedding (unmatched), queries whose methods differ in embeddings (differing), and searches of ``other`` that need
    more calls than plain or no_lookup (more_calls). A search that did not finish shows nothing, so it counts as a failure of each."""
    ends = F.explode(F.col("vertices.u")).alias("u")
    tied = queries.select("query_id", F.explode("edges").alias("e")).select("query_id", F.explode(F.array("e.a", "e.b")).alias("u")).distinct()
    earlier = queries.select("query_id", F.explode("edges").alias("e")).select("query_id", F.greatest("e.a", "e.b").alias("u")).distinct()
    # A walk numbers vertices as it sees them: all but the first are tied to an earlier one.
    loose = queries.select("query_id", ends).join(tied, ["query_id", "u"], "left_anti").unionByName(queries.select("query_id", ends).filter("u > 1").join(earlier, ["query_id", "u"], "left_anti"))
    by = stats.groupBy("query_id").agg(
        F.count_if(F.col("dnf") | (F.col("n_found") == 0)).alias("unmatched"), (F.bool_or("dnf") | (F.count_distinct("n_found") > 1)).alias("differing"), F.coalesce(F.bool_or(F.col("dnf") & F.col("method").isin(other, "plain", "no_lookup")), F.lit(False)).alias("cut"),
        F.max(F.when(F.col("method") == other, F.col("search_calls"))).alias("own"), F.min(F.when(F.col("method").isin("plain", "no_lookup"), F.col("search_calls"))).alias("others"),
    )
    held = by.agg(F.count(F.lit(1)).alias("queries"), F.sum("unmatched").alias("unmatched"), F.count_if("differing").alias("differing"), F.count_if(F.col("cut") | (F.col("own") > F.col("others"))).alias("more_calls"))
    return held.join(loose.agg(F.count_distinct("query_id").alias("disconnected")))  # one row beside one row


def plan_costs(df: DataFrame) -> dict[str, int]:
    """How often the executed plan moves rows, and by which joins: before and without running it."""
    plan = df._jdf.queryExecution().executedPlan().toString()
    names = ("Exchange hashpartitioning", "Exchange rangepartitioning", "Exchange SinglePartition", "BroadcastExchange", "ReusedExchange", "SortMergeJoin", "BroadcastHashJoin", "ShuffledHashJoin", "BroadcastNestedLoopJoin", "CartesianProduct", "FileScan", "MapInArrow")
    return {n: plan.count(n) for n in names}


def result_diff(a: DataFrame, b: DataFrame) -> DataFrame:
    """missing (in a only) and extra (in b only) rows."""
    missing = a.exceptAll(b).agg(F.count(F.lit(1)).alias("missing"))
    return missing.join(b.exceptAll(a).agg(F.count(F.lit(1)).alias("extra")))


def estimate_count(g: LabeledGraph, p, frac: float, seed: int = 0) -> DataFrame:
    """An estimate of the number of embeddings from a hashed share of the roots; not exact by design."""
    from .joins import join_match

    pick = F.expr(f"pmod(vid * 2654435761 + {seed}, 4294967296) < {int(frac * 2**32)}")  # fixed value: a multiplier that spreads numbers
    roots = g.vertices.filter((F.col("label") == p.labels[0]) & pick).select(F.col("vid").alias("m1"))
    return join_match(g, p).join(roots, "m1", "left_semi").agg((F.count(F.lit(1)) / frac).alias("estimate"))
