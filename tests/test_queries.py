"""Every registered query beside its SQL on the smallest tables, and plans, measures and streams."""

import os
import threading
from collections import Counter

import duckdb
import numpy as np
import pytest
from oracle import differences, duck
from pyspark.sql import functions as F

import __spark_entry__
from branchwise import queries
from branchwise.operators import dfs, joins, local_graph, match, regions, udtf, waves, workloads
from branchwise.operators.graph import GraphSchemaError, LabeledGraph
from branchwise.plans.pattern import PatternGraph
from branchwise.plans.sqlgen import brute_force_sql, to_sql
from branchwise.queries.patterns import A, B, C, X1, X1_PATTERN, cycle, inline, path
from branchwise.queries.registry import graph
from branchwise.sources import graphs as src
from branchwise.streaming import deltas

from conftest import DATA

BY_SQL = list(queries.ORACLE_SQL)


@pytest.fixture(scope="module")
def con():
    return duck(DATA)


@pytest.mark.parametrize("name", BY_SQL)
def test_query_equals_sql(spark, con, name):
    missing, extra, _ = differences(queries.QUERIES[name](spark, DATA), con, queries.ORACLE_SQL[name])
    assert (missing, extra) == (0, 0)


def test_arc_fixpoint_stops_where_its_sql_does(spark, tmp_path):
    """A long path loses a vertex of each end a round: more rounds than the SQL has."""
    n = 45
    spark.createDataFrame([(i, [A, B, C][i % 3]) for i in range(n)], "p_partkey bigint, p_brand string").coalesce(1).write.parquet(f"{tmp_path}/part.parquet")
    spark.createDataFrame([(i, i + k, "N") for i in range(n - 1) for k in (0, 1)], "l_orderkey bigint, l_partkey bigint, l_returnflag string").coalesce(1).write.parquet(f"{tmp_path}/lineitem.parquet")
    con = duckdb.connect()
    for t in ("part", "lineitem"):
        con.sql(f"CREATE VIEW {t} AS SELECT * FROM '{tmp_path}/{t}.parquet/*.parquet'")
    assert differences(queries.QUERIES["q_arc_fixpoint"](spark, str(tmp_path)), con, queries.ORACLE_SQL["q_arc_fixpoint"])[:2] == (0, 0)


@pytest.mark.parametrize("name", ["q_nogoods", "q_reuse_trap", "q_self_loop", "q_self_loop_dfs", "q_worked_example", "q_worked_example_calls"])
def test_worked_examples_read_the_tables(spark, tmp_path, name):
    with pytest.raises(Exception, match="(?i)not.*exist|no such file"):
        queries.QUERIES[name](spark, str(tmp_path / "nowhere")).collect()


@pytest.mark.parametrize("name", ["q_nogoods", "q_reuse_trap", "q_self_loop", "q_self_loop_dfs", "q_worked_example", "q_worked_example_calls"])
def test_worked_examples_at_the_next_size(spark, name):
    missing, extra, rows = differences(queries.QUERIES[name](spark, "/root/testdata/sf0.01"), duck("/root/testdata/sf0.01"), queries.ORACLE_SQL[name])
    assert (missing, extra) == (0, 0) and rows


@pytest.mark.parametrize("name", BY_SQL)
def test_sql_needs_no_planner(name):
    """Every text is a chain of keyed joins over settled steps: with the optimiser off it still ends at once."""
    con = duck("/root/testdata/sf0.01")
    con.execute("PRAGMA disable_optimizer")
    stop = threading.Timer(20, con.interrupt)
    stop.start()
    con.sql(queries.ORACLE_SQL[name]).fetchall()
    stop.cancel()


@pytest.mark.parametrize("name", ["q_triangle_aab", "q_cycle4", "q_disconnected", "q_self_loop", "q_worked_example"])
def test_sql_is_the_definition(con, name):
    """The generated joins against the plain product of label domains."""
    if name in queries.patterns.PATTERNS:
        graph_name, p = queries.patterns.PATTERNS[name]
        views = queries.registry.GRAPHS[graph_name][1]
    else:
        given, p = {"q_self_loop": (queries.patterns.LOOPED, queries.patterns.LOOPED_PATTERN), "q_worked_example": (queries.patterns.X1, queries.patterns.X1_PATTERN)}[name]
        views = queries.patterns.inline_sql(*given)
    assert sorted(con.sql(f"{views} {to_sql(p)}").fetchall()) == sorted(con.sql(f"{views} {brute_force_sql(p)}").fetchall())


def test_entry(spark):
    assert __spark_entry__.entry(spark).columns == ["m1", "m2", "m3", "m4"]


def test_plan_of_a_connected_pattern_has_no_product(spark):
    plan = joins.join_match(graph("gd", spark, DATA), queries.patterns.PATTERNS["q_clique4"][1])._jdf.queryExecution().executedPlan().toString()
    assert "Cartesian" not in plan and "NestedLoop" not in plan


def test_a_cycle_through_hubs_is_joined_by_pairs(spark):
    """Pages of one host that link to one target: the pairs of pages of a host are never made."""
    hosts, pages, targets = 2, 200, 40
    rows = [(1000 + i, "host") for i in range(hosts)] + [(i, "page") for i in range(pages)] + [(2000 + i, "href") for i in range(targets)]
    pairs = [(i, 1000 + i % hosts) for i in range(pages)] + [(i, 2000 + i % targets) for i in range(pages)]
    g = LabeledGraph.from_edges(spark.createDataFrame(rows, "vid bigint, label string"), spark.createDataFrame(pairs, "a bigint, b bigint")).settled()
    p = queries.patterns.PATTERNS["q_page_host_fan"][1]
    found = joins.join_match(g, p)
    plan = found._jdf.queryExecution().optimizedPlan().toString()
    assert plan.count("LeftSemi") == 0
    want = [(a, 1000 + a % hosts, b, 2000 + a % targets) for a in range(pages) for b in range(pages) if a != b and a % hosts == b % hosts and a % targets == b % targets]
    assert sorted(map(tuple, found.collect())) == want


def test_an_edge_meets_its_labels_as_one_row(spark):
    """Both labels are found before an edge is turned, so that half the rows move."""
    v = spark.createDataFrame([(1, "a"), (2, "b")], "vid bigint, label string")
    g = LabeledGraph.from_edges(v, spark.createDataFrame([(2, 1), (1, 2), (1, 9)], "a bigint, b bigint"))
    assert sorted(map(tuple, g.edges.select("src", "dst", "src_label", "dst_label").collect())) == [(1, 2, "a", "b"), (2, 1, "b", "a")]
    plan = g.edges._jdf.queryExecution().optimizedPlan().toString()
    assert plan.index("Generate") < plan.index("Join")  # the plan's text begins with its last step


def test_regions_need_a_connected_pattern(spark):
    with pytest.raises(ValueError):
        regions.region_match(graph("gd", spark, DATA), queries.patterns.PATTERNS["q_disconnected"][1])


def test_schema_is_validated(spark):
    v = spark.createDataFrame([(1, "a"), (1, "b")], "vid bigint, label string")
    with pytest.raises(GraphSchemaError):
        LabeledGraph.from_edges(v, spark.createDataFrame([(1, 1)], "a bigint, b bigint"), validate=True)


def test_large_graphs_are_not_broadcast(spark, monkeypatch):
    monkeypatch.setattr(dfs, "MAX_BYTES", 160)
    with pytest.raises(dfs.GraphTooLarge):
        dfs.dfs_match(graph("gd", spark, DATA), queries.patterns.PATTERNS["q_triangle_abc"][1])


def test_experiments_run_over_graphs_of_any_size(spark, monkeypatch):
    """A graph above the bound of a single pattern, in many chunks: the same patterns and statistics."""
    g = graph("gs_type", spark, DATA)

    def run():
        q = workloads.random_walk_patterns(g, [4, 6], 3, induced=True).cache()
        stats = workloads.run_experiment(g, q, ["learned", "no_lookup", "structure_first", "profile_refine"], cap=50, query_budget_s=60)
        return sorted(map(str, q.collect())), sorted(map(str, stats.drop("prep_ns", "elapsed_ns", "job_ms").collect()))

    want = run()
    monkeypatch.setattr(dfs, "MAX_BYTES", 160)
    monkeypatch.setattr(dfs, "CHUNK", 300)
    assert run() == want


def test_filters_by_label_pair(monkeypatch):
    """At 60 x sf0.1 filters that read whole lists used up the budget of every query: with the lists by label pair they read none and leave the same."""
    rng = np.random.default_rng(3)
    n, names = 400, ["A", "B", "C", "D"]
    vids, codes = np.sort(rng.choice(5000, n, replace=False)).astype(np.int64), rng.integers(0, 4, n).astype(np.int32)
    e = np.unique(np.sort(rng.integers(0, n, (1500, 2)), 1), axis=0)
    e = e[e[:, 0] != e[:, 1]]
    e = np.unique(np.concatenate([e, e[:, ::-1]]), axis=0)
    first = [0, 100, 300]
    chunks = [e[(e[:, 0] >= lo) & (e[:, 0] < hi), 1].astype(np.int32) for lo, hi in zip(first, [*first[1:], n])]
    counts = Counter((names[codes[a]], names[codes[b]]) for a, b in e)
    made = lambda: local_graph.LocalGraph(vids, codes, names, np.bincount(e[:, 0], minlength=n).astype(np.int32), first, chunks, counts)
    shapes = [path("A", "B", "C", "A"), cycle("A", "B", "C"), path("A"), path("A", "X", "B"), PatternGraph(("A", "B", "X", "C"), ((1, 2), (2, 4))), PatternGraph(("A", "A", "B", "D", "B"), ((1, 2), (1, 3), (2, 3), (3, 4), (4, 5)))]
    plain, paired, none = made(), made(), made()
    for filters in ((), ("degree",), ("labels", "bipartite"), *(m.filters for m in dfs.METHODS.values())):
        for p in shapes:
            want = plain.domains(p, filters)
            monkeypatch.setattr(local_graph, "PAIR_BYTES", 0)
            none.index(p, filters)
            assert none.domains(p, filters) == want and not none._pairs
            monkeypatch.setattr(local_graph, "PAIR_BYTES", 15_000)
            paired.index(p, filters)
            if set(filters) & local_graph.BY_PAIR and "X" not in p.labels and p.edges:
                with monkeypatch.context() as m:
                    m.setattr(local_graph.LocalGraph, "_read", lambda *_: pytest.fail("whole lists are read"))
                    assert paired.domains(p, filters) == want
            assert paired.domains(p, filters) == want
            assert sum(x.nbytes for held in paired._pairs.values() for x in held) <= 15_000


def test_filters_end_with_the_budget(spark):
    """A budget that the filters use up leaves an unfinished query and not a longer one."""
    g = graph("gs", spark, DATA)
    stats = workloads.run_experiment(g, joins.query_set(spark, [path(A, B, C)]), ["profile_refine"], query_budget_s=1e-9).collect()
    assert [(r.dnf, r.search_calls, r.n_found) for r in stats] == [(True, 1, 0)]


def test_an_unfinished_search_is_no_agreement(spark, monkeypatch):
    """It has no embedding and a call, like one that failed, and was left out of what must hold."""
    g = graph("gs", spark, DATA)
    q = workloads.random_walk_patterns(g, [4], 3, induced=True).cache()
    stats = workloads.run_experiment(g, q, ["learned", "no_lookup", "profile_refine"], query_budget_s=1e-9)
    assert tuple(workloads.invariants(q, stats).first()) == (3, 9, 3, 3, 0)
    seen, run = [], workloads.run_experiment
    monkeypatch.setattr(workloads, "run_experiment", lambda g, q, methods, cap, budget: seen.append(budget) or run(g, q, methods, cap, budget))
    assert queries.QUERIES["w_invariants"](spark, DATA).count() == 2 and seen == [None, None]


def test_partners_are_looked_for_only_where_counts_leave_it_open(monkeypatch):
    """Same images as by looking for the partners of every vertex; neighbours of different labels need no looking."""
    rng, n = np.random.default_rng(5), 60
    e = np.unique(np.sort(rng.integers(0, n, (150, 2)), 1), axis=0)
    e = e[e[:, 0] != e[:, 1]]
    e = np.unique(np.concatenate([e, e[:, ::-1]]), axis=0)
    codes = rng.integers(0, 2, n).astype(np.int32)
    g = local_graph.LocalGraph(np.arange(n), codes, ["A", "B"], np.bincount(e[:, 0], minlength=n).astype(np.int32), [0], [e[:, 1].astype(np.int32)])
    shapes = [PatternGraph(("A", "B", "B", "B", "A"), ((1, 2), (1, 3), (1, 4), (2, 5))), PatternGraph(("A", "A", "A", "B", "B"), ((1, 2), (1, 3), (1, 4), (1, 5), (2, 4), (3, 5)))]
    looked, saturates = [], local_graph._saturates
    monkeypatch.setattr(local_graph, "_saturates", lambda *a: looked.append(1) or saturates(*a))
    for p in shapes:
        dom, size = {u: set(g.vids[codes == "AB".index(x)].tolist()) for u, x in enumerate(p.labels, 1)}, None
        while size != (size := sum(map(len, dom.values()))):
            dom = {u: {v for v in d if saturates(sorted(p.neighbors(u)), {w: sorted(g.adjacency[v] & dom[w]) for w in p.neighbors(u)})} for u, d in dom.items()}
        assert {u: set(d) for u, d in g.domains(p, ("bipartite",)).items()} == dom and 0 < size
    assert looked
    looked.clear()
    g.domains(path("A", "B"), ("bipartite",)), g.domains(PatternGraph(("A", "B", "A"), ((1, 2), (1, 3))), ("bipartite",))
    assert not looked


def test_a_set_with_all_labels_uses_the_chunks_of_its_walk(spark):
    g = graph("gs_type", spark, DATA)
    names = sorted(r.label for r in g.vertices.select("label").distinct().collect())
    _, walked = dfs.broadcast_graph(g)
    whole, chunks = dfs.broadcast_graph(g, names)
    assert [c.value for c in chunks] == [c.value for c in walked] and all(a is b for a, b in zip(chunks, walked))
    assert whole.value[5] == g.statistics(set(names))[1]
    some, few = dfs.broadcast_graph(g, names[:2])
    assert some.value[2] and set(some.value[2]) <= set(names[:2]) and not any(a is b for a in few for b in walked)
    again, last = dfs.broadcast_graph(graph("gd_type", spark, DATA), names[:2])
    assert not any(a is b for a in last for b in few) and sum(again.value[3]) > sum(some.value[3])


def test_hard_searches_only_by_the_methods_it_compares(spark, monkeypatch):
    seen, run = [], workloads.run_experiment
    monkeypatch.setattr(workloads, "run_experiment", lambda g, q, methods, *a, **k: seen.append(set(methods)) or run(g, q, methods, *a, **k))
    assert queries.QUERIES["w_hard"](spark, DATA).count() == 4 and queries.QUERIES["w_hard_found"](spark, DATA).count() == 4
    assert seen == [{"learned", "no_lookup"}, {"learned", "no_lookup", "plain"}]


def test_hard_searches_are_dealt_over_shares(spark, monkeypatch):
    want = sorted(map(tuple, queries.QUERIES["w_hard_found"](spark, DATA).collect()))
    monkeypatch.setattr(queries.experiments, "SHARE_ROOTS", 5)
    seen, run = [], workloads.run_experiment
    monkeypatch.setattr(workloads, "run_experiment", lambda *a, **k: (seen.append(k["shares"]), run(*a, **k))[1])
    assert sorted(map(tuple, queries.QUERIES["w_hard_found"](spark, DATA).collect())) == want and seen[0] > 1


def test_whole_searches_that_learn_nothing_go_side_by_side(spark, monkeypatch):
    g = graph("gd_type", spark, DATA)
    p, labels = queries.experiments.hard(2), sorted(set(queries.experiments.hard(2).labels))
    local = dfs.local_graph(dfs.broadcast_graph(g, labels))
    run = lambda mode, cap=None, budget=None, checks=(): [r | {"prep_ns": 0, "elapsed_ns": 0} for r in dfs.search_share(local, 1, p, mode, dfs.Method(mode), cap, budget, False, False, checks=checks)]
    want = [run(m, 10**9) for m in ("plain", "no_lookup")]
    with monkeypatch.context() as m:
        m.setattr(dfs, "search_rows", lambda *a, **k: pytest.fail("one assignment at a time"))
        assert [run(x) for x in ("plain", "no_lookup")] == want and want[0][0]["n_found"]
    monkeypatch.setattr(dfs, "search_wide", lambda *a, **k: pytest.fail("no bounds or checks"))
    run("learned"), run("plain", 5), run("plain", None, 10**12), run("plain", None, None, ((1, "<", 2),))


def test_experiment_measures(spark):
    g = graph("gs_type", spark, DATA)
    q = workloads.random_walk_patterns(g, [4, 6], 5, induced=True).cache()
    assert q.count() == 10
    stats = workloads.run_experiment(g, q, ["learned", "no_lookup", "structure_first", "rare_edge_order", "profile_refine"], cap=50).cache()
    assert stats.filter("n_found = 0").isEmpty()  # a pattern cut from the data is in the data
    assert stats.groupBy("query_id").agg(F.count_distinct("n_found").alias("n")).filter("n > 1").isEmpty()
    for r in workloads.compare(stats, "no_lookup", "learned").collect():
        assert r.differing == 0 and r.calls_other <= r.calls_base


def test_ratios_leave_out_unfinished_queries(spark):
    rows = [(1, 4, "a", 90, 900, 1, False), (1, 4, "b", 30, 100, 1, False), (2, 4, "a", 10, 10, 0, True), (2, 4, "b", 40, 50, 1, False), (3, 6, "a", 5, 5, 0, True), (3, 6, "b", 5, 5, 0, True)]
    stats = spark.createDataFrame(rows, "query_id int, n_vertices int, method string, search_calls bigint, elapsed_ns bigint, n_found bigint, dnf boolean").withColumn("prep_ns", F.lit(100))
    found = {r["size"]: r for r in workloads.compare(stats, "a", "b").collect()}
    assert (found[4].queries, found[4].finished, found[4].call_ratio, found[4].speedup, found[4].dnf_base, found[4].dnf_other) == (2, 1, 3.0, 9.0, 1, 0)
    assert (found[6].finished, found[6].call_ratio, found[6].speedup) == (0, None, None)
    assert (found[4].speedup_with_prep, found[4].best_speedup, found[4].overhead, found[4].more_calls) == (5.0, 5.0, None, 0)


def test_a_set_is_unfinished_by_the_time_of_all_its_queries(spark, monkeypatch):
    """A query may take longer than its share, as long as the set does not; a set that does has no mean time."""
    names = "n_vertices int, method string, elapsed_ns bigint, dnf boolean"
    stats = spark.createDataFrame([(4, "a", 15 * 10**9, False), (4, "a", 10**9, False), (6, "a", 19 * 10**9, False), (6, "a", 10**9, False), (8, "a", 10**9, True), (8, "a", 10**9, False)], names)
    zero = [c for c in ("search_calls", "n_found", "f_wipeout", "f_reuse", "f_known", "f_child", "f_check", "slot_writes", "slot_overwrites", "slot_hits", "slots_used", "prep_ns")]
    found = {r["size"]: (r.set_dnf, r.avg_ms) for r in workloads.summarise(stats.withColumns({c: F.lit(0) for c in zero}).withColumn("capped", F.lit(False)), 8.64).collect()}
    assert found == {4: (False, 8000.0), 6: (True, None), 8: (True, None)}
    seen, run = [], workloads.run_experiment
    monkeypatch.setattr(workloads, "run_experiment", lambda g, q, methods, cap, budget, set_budget: seen.append(budget) or run(g, q, ["learned"], cap, budget, set_budget))
    monkeypatch.setattr(workloads, "random_walk_patterns", lambda g, sizes, *a, f=workloads.random_walk_patterns: f(g, [4], *a))
    assert [r.set_dnf for r in queries.QUERIES["w_time_sparse"](spark, DATA).collect()] == [False] and seen == [pytest.approx(216)]


def test_wave_nogoods_are_sound(spark):
    assert queries.QUERIES["q_nogoods_sound"](spark, DATA).first()[0] == 0
    found, _, stats = waves.wave_match(inline(spark, *X1), X1_PATTERN, 2, 7)
    assert found.count() == 3
    assert stats.filter("cause = 'KNOWN'").agg(F.sum("rows")).first()[0] == 4


def test_sql_functions(spark):
    udtf.register(spark)
    g = inline(spark, *X1)
    g.edges.createOrReplaceTempView("x1_edges")
    rows = spark.sql("SELECT asg FROM match_pattern(TABLE(x1_edges) WITH SINGLE PARTITION, '(p:a)-(q:b)-(r:c)-(s:a)')").collect()
    assert sorted(r.asg for r in rows) == [[1, 2, 5, 8], [1, 3, 5, 8], [1, 4, 5, 8]]
    assert [r.pos for r in spark.sql("SELECT pos FROM pattern_reason_bits(5)").collect()] == [1, 3]


def test_stream_of_edges_adds_up_to_the_whole(spark, tmp_path):
    g = graph("gd", spark, DATA)
    pairs = g.edges.filter("src < dst").select(F.col("src").alias("a"), F.col("dst").alias("b"))
    for i in range(3):
        pairs.filter((F.col("a") + F.col("b")) % 3 == i).coalesce(1).write.mode("append").parquet(str(tmp_path / "in"))
    source = spark.readStream.schema("a bigint, b bigint").option("maxFilesPerTrigger", 1).parquet(str(tmp_path / "in"))
    p, got = path(A, B, C), []
    run = deltas.run_continuous(source, g.vertices, p, str(tmp_path / "edges"), lambda df, _: got.extend(map(tuple, df.collect())), str(tmp_path / "ck"))
    run.processAllAvailable()
    run.stop()
    assert sorted(got) == sorted(map(tuple, joins.join_match(g, p).collect()))


@pytest.mark.parametrize("engine", match.ENGINES)
def test_facade(spark, engine):
    g, p = graph("gd", spark, DATA), path(A, B, C, A)
    want = sorted(map(tuple, joins.join_match(g, p).collect()))
    assert sorted(map(tuple, match.match(g, p, engine).collect())) == want
    assert list(map(tuple, match.match(g, p, engine, limit=3).collect())) == want[:3]
    if engine in ("join", "dfs", "region"):
        assert sorted(map(tuple, match.match(g, p, engine, where={2: "vid % 2 = 0"}).collect())) == [r for r in want if r[1] % 2 == 0]
    else:
        with pytest.raises(ValueError):
            match.match(g, p, engine, where={2: "vid % 2 = 0"})


def test_conditions_on_attributes(spark):
    vertices = spark.createDataFrame([(1, "a", 5.0), (2, "b", 7.0), (3, "b", 9.0)], "vid bigint, label string, price double")
    g = LabeledGraph.from_edges(vertices, spark.createDataFrame([(1, 2), (1, 3)], "a bigint, b bigint")).settled()
    for engine in ("join", "dfs", "region"):
        assert [tuple(r) for r in match.match(g, path("a", "b"), engine, where={2: "price > 8"}).collect()] == [(1, 3)]


def test_the_empty_pattern_has_one_embedding(spark):
    g = inline(spark, *X1)
    assert joins.join_match(g, PatternGraph((), ())).count() == dfs.dfs_match(g, PatternGraph((), ()), shares=1).count() == 1


def test_the_facade_chooses(spark, monkeypatch):
    g = graph("gs", spark, DATA)
    assert match.choose_engine(g, path(A, B)) == "join" and match.choose_engine(g, path(*[A, B] * 4)) == "dfs"
    monkeypatch.setattr(dfs, "MAX_BYTES", 100)
    assert match.choose_engine(g, path(*[A, B] * 4)) == "region"


def test_heavy_roots_are_cut_into_units(spark):
    """Each unit of a hub has a share of its edges, and no unit the whole."""
    n = 60
    rows = [(0, "a"), *((i, "b") for i in range(1, n + 1)), *((100 + i, "c") for i in range(n))]
    pairs = [(0, i) for i in range(1, n + 1)] + [(i, 100 + i - 1) for i in range(1, n + 1)]
    g = LabeledGraph.from_edges(spark.createDataFrame(rows, "vid bigint, label string"), spark.createDataFrame(pairs, "a bigint, b bigint"))
    p = path("a", "b", "c")
    dom = regions.build_domains(g, p)
    edges = regions.candidate_edges(g, p, dom)
    units = regions.region_units(edges, dom, p, 20)
    assert [tuple(r) for r in units.collect()] == [(0, 6)]
    sizes = [r["count"] for r in regions.extract_regions(edges, dom, p, units).groupBy("root", "unit").count().collect()]
    assert sum(sizes) == 2 * n and len(sizes) == 6 and max(sizes) < n
    assert regions.region_match(g, p, unit_edges=20).count() == n


def test_labelled_edges_are_read_by_pair(spark):
    """The self join of the orders is not in the plan of a pattern; label pairs are filters of the scan."""
    plan = joins.join_match(graph("gd", spark, DATA), path(A, B, C, A))._jdf.queryExecution().executedPlan().toString()
    assert "lineitem" not in plan and plan.count("PushedFilters: [IsNotNull(src_label), IsNotNull(dst_label), EqualTo(src_label") == 3


def test_a_graph_is_made_again_when_its_table_changes(spark, tmp_path):
    for t in ("lineitem", "part"):
        spark.read.parquet(f"{DATA}/{t}.parquet").coalesce(1).write.parquet(f"{tmp_path}/{t}.parquet")
    first = graph("gs", spark, str(tmp_path))
    assert graph("gs", spark, str(tmp_path)) is first
    few = [r.p_partkey for r in spark.read.parquet(f"{DATA}/part.parquet").limit(50).collect()]
    spark.read.parquet(f"{DATA}/part.parquet").filter(F.col("p_partkey").isin(few)).coalesce(1).write.mode("overwrite").parquet(f"{tmp_path}/part.parquet")
    assert graph("gs", spark, str(tmp_path)).vertices.count() == 50


def test_sinks_and_pattern_files(spark, tmp_path):
    g = inline(spark, *X1)
    queries_path = tmp_path / "patterns.json"
    queries_path.write_text('{"labels": ["a", "b", "c", "a"], "edges": [[1, 2], [2, 3], [3, 4]]}\n{"labels": ["a", "b"], "edges": [[1, 2]]}\n')
    q = src.pattern_file(spark, str(queries_path))
    found = dfs.dfs_search(g, q, {"m": dfs.Method()}).filter("kind = 'embedding'").select("query_id", "n_vertices", "asg")
    match.write_embeddings(found, str(tmp_path / "found"), ("n_vertices",))
    back = spark.read.parquet(str(tmp_path / "found"))
    assert {(r.query_id, r.n_vertices): r["count"] for r in back.groupBy("query_id", "n_vertices").count().collect()} == {(0, 4): 3, (1, 2): 3}
    match.write_nogoods(g, q, str(tmp_path / "nogoods"))
    assert {(r.pos, r.vid, tuple(r.positions)) for r in spark.read.parquet(str(tmp_path / "nogoods")).filter("query_id = 0").collect()} == {(0, 8, (0,)), (2, 6, (0, 2)), (2, 7, (0, 2))}


def test_late_rows_are_counted(spark, tmp_path):
    rows = spark.createDataFrame([(1, "2024-01-01 10:00:00"), (2, "2024-01-01 10:30:00")], "user_id bigint, ts string").selectExpr("user_id", "'x' AS event_type", "cast(ts AS timestamp) AS ts")
    rows.coalesce(1).write.parquet(str(tmp_path / "in"))
    source = spark.readStream.schema(rows.schema).option("maxFilesPerTrigger", 1).parquet(str(tmp_path / "in"))
    run = deltas.edge_stream(source).writeStream.format("memory").queryName("edges").outputMode("append").option("checkpointLocation", str(tmp_path / "ck")).start()
    run.processAllAvailable()
    spark.createDataFrame([(3, "2024-01-01 09:00:00")], "user_id bigint, ts string").selectExpr("user_id", "'x' AS event_type", "cast(ts AS timestamp) AS ts").coalesce(1).write.mode("append").parquet(str(tmp_path / "in"))
    run.processAllAvailable()
    late = deltas.dropped_late(run)
    run.stop()
    assert late >= 1


def test_budgets(spark):
    """A set whose time is over reports its queries as unfinished, without a call."""
    g = graph("gs", spark, DATA)
    stats = workloads.run_experiment(g, joins.query_set(spark, [path(A, B, C)]), ["learned"], set_budget_s=-1).collect()
    assert [(r.dnf, r.search_calls) for r in stats] == [(True, 0)]


def test_edges_of_a_table_and_a_stream_are_the_same(spark, tmp_path):
    events = spark.read.parquet(f"{DATA}/events.parquet")
    want = {tuple(r) for r in deltas.edge_stream(events).distinct().collect()}
    users = events.select(F.window(F.col("ts").cast("timestamp"), "1 minute").alias("w"), "event_type", "user_id").distinct().collect()
    by = {}
    for r in users:
        by.setdefault((r.w, r.event_type), []).append(r.user_id)
    assert want == {(a, b) for x in by.values() for a in x for b in x if a < b}


def test_imports_without_the_llm_folders(tmp_path):
    """The library must not need the llm subpackage."""
    for d, _, files in os.walk(os.path.dirname(os.path.dirname(queries.__file__))):
        if not d.endswith("llm"):
            for f in files:
                if f.endswith(".py"):
                    assert "branchwise.llm" not in open(os.path.join(d, f)).read(), f
