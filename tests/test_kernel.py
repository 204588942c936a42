"""The worked examples with their call counts, and random graphs against plain search and brute force."""

import random
from itertools import permutations

import pytest

from branchwise.functions.reasons import fold_reason, prefix_length
from branchwise.operators import kernel, wide
from branchwise.operators.kernel import is_fruitless, search_unit
from branchwise.plans import ordering
from branchwise.plans.pattern import PatternError, PatternGraph

BIP = [(i, j) for i in (2, 3, 4) for j in (5, 6, 7)]
K4 = [(a, b) for a in range(1, 5) for b in range(a + 1, 5)]
STAR = ({"a": [1, 4], "b": [2, 3, 5], "c": [6]}, [(1, 2), (1, 3), (4, 5), (4, 6)])
#: name -> labels, pattern edges, data, calls (plain, no_lookup, learned), embeddings
CASES = {
    "X1": ("abca", ((1, 2), (2, 3), (3, 4)), ({"a": [1, 8], "b": [2, 3, 4], "c": [5, 6, 7]}, [(1, 2), (1, 3), (1, 4), *BIP, (5, 8), (6, 1), (7, 1)]), (18, 18, 14), [(1, 2, 5, 8), (1, 3, 5, 8), (1, 4, 5, 8)]),
    "X2": ("abca", ((1, 2), (1, 3), (2, 4)), ({"a": [1, 5], "b": [2, 3], "c": [4]}, [(1, 2), (1, 3), (1, 4), (3, 5)]), (9, 8, 8), [(1, 3, 4, 5)]),
    "X3": ("abc", ((1, 2), (1, 3)), STAR, (7, 5, 5), [(4, 5, 6)]),
    "X4": ("az", ((1, 2),), STAR, (3, 1, 1), []),
    "X5": ("abb", ((2, 3),), ({"a": [1, 3], "b": [2]}, []), (5, 5, 4), []),
    "X6": ("abcda", ((1, 2), (1, 3), (3, 4), (3, 5), (4, 5)), ({"a": [1, 7], "b": [2, 3], "c": [4], "d": [5, 6]}, [(1, 2), (1, 3), (1, 4), (4, 5), (5, 1), (4, 6), (4, 7), (6, 7)]), (13, 13, 13), [(1, 2, 4, 6, 7), (1, 3, 4, 6, 7)]),
    "X7": ("a", (), STAR, (3, 3, 3), [(1,), (4,)]),
    "X8": ("aaa", ((1, 2), (2, 3), (1, 3)), ({"a": [1, 2, 3, 4]}, K4), (41, 41, 41), None),
}


def run(name, **options):
    labels, edges, (vertices, pairs), _, _ = CASES[name]
    adjacency = {}
    for a, b in pairs:
        adjacency.setdefault(a, set()).add(b)
        adjacency.setdefault(b, set()).add(a)
    return search_unit(PatternGraph(tuple(labels), edges).nbr_mask(), [vertices.get(x, []) for x in labels], adjacency, **options)


@pytest.mark.parametrize("name", CASES)
def test_calls_and_embeddings(name):
    _, _, _, calls, rows = CASES[name]
    assert tuple(run(name, mode=m).stats["search_calls"] for m in ("plain", "no_lookup", "learned")) == calls
    for mode in ("plain", "no_lookup", "learned"):
        assert run(name, mode=mode).rows == rows if rows is not None else len(run(name, mode=mode).rows) == 24


def test_variants_of_the_small_graphs():
    assert run("X6", match="subset").stats["search_calls"] == 12
    assert run("X5", infeasible_stop=True).stats["search_calls"] == 3
    s = run("X1").stats
    assert (s["f_reuse"], s["f_known"], s["f_wipeout"], s["f_child"], s["slot_hits"]) == (2, 4, 1, 3, 4)
    assert run("X1").slots.export() == [(2, 6, 5, 1, 1, [1]), (2, 7, 5, 1, 1, [1]), (0, 8, 1, 0, 0, [])]


def test_a_reuse_reason_needs_both_positions():
    assert run("X2", drop_current=True).rows == []


def test_a_stop_by_time_records_nothing_above_it():
    r = run("X8", deadline_ns=-1)
    assert not r.stats["dnf"] or r.slots.export() == []


def test_reason_rules():
    assert fold_reason(0b1001, 3, 0b0010, 0b111) == 0b011
    assert fold_reason(0b0001, 3, 0b0010, 0b111) == 0b0001
    assert prefix_length(0, 0) == 0 and prefix_length(0b101, 2) == 1


def random_case(seed):
    rng = random.Random(seed)
    size, n = rng.randint(2, 12), rng.randint(1, 5)
    label = {i: rng.choice("ab") for i in range(size)}
    edges = {(i, j) for i in range(size) for j in range(i) if rng.random() < 0.4}
    p = PatternGraph(tuple(rng.choice("ab") for _ in range(n)), tuple((i + 1, j + 1) for i in range(n) for j in range(i) if rng.random() < 0.5))
    return p, label, edges


OPTIONS = [{"mode": "plain"}, {"mode": "no_lookup"}, {}, {"match": "subset"}, {"store": "set"}, {"policy": "smallest"}, {"backjump": True}, {"infeasible_stop": True}, {"wipeout_choice": "smallest"}, {"match": "subset", "store": "set"}]


@pytest.mark.parametrize("seed", range(60))
def test_random_graphs(seed):
    p, label, edges = random_case(seed)
    adjacency = {}
    for a, b in edges:
        adjacency.setdefault(a, set()).add(b)
        adjacency.setdefault(b, set()).add(a)
    want = [x for x in permutations(sorted(label), p.n) if all(label[v] == y for v, y in zip(x, p.labels)) and all(x[b - 1] in adjacency.get(x[a - 1], ()) for a, b in p.edges)]
    domains = [sorted(v for v, x in label.items() if x == y) for y in p.labels]
    for o in OPTIONS:
        r = search_unit(p.nbr_mask(), domains, adjacency, **o)
        assert r.rows == sorted(want), o
        for pos, vid, reason, _, _, vals in r.slots.export():
            part = dict(zip((i for i in range(pos) if reason >> i & 1), vals)) | ({pos: vid})
            assert is_fruitless(p.nbr_mask(), domains, adjacency, part), (o, part)
    calls = [search_unit(p.nbr_mask(), domains, adjacency, mode=m).stats["search_calls"] for m in ("learned", "no_lookup", "plain")]
    assert calls == sorted(calls)
    assert search_unit(p.nbr_mask(), domains, adjacency, cap=2).rows == sorted(want)[:2]


def test_patterns_and_orders():
    p = PatternGraph.from_text("(a:X)-(b:Y)-(c:X), (a)-(c)")
    assert p.labels == ("X", "Y", "X") and p.edges == ((1, 2), (1, 3), (2, 3)) and p.is_connected() and p.core2() == {1, 2, 3}
    assert len(p.automorphisms()) == 2
    assert PatternGraph.from_row({"vertices": [{"u": 2, "label": "b"}, {"u": 1, "label": "a"}], "edges": [{"a": 1, "b": 2}]}) == PatternGraph(("a", "b"), ((1, 2),))
    with pytest.raises(PatternError):
        PatternGraph(("a",), ((1, 2),))
    assert PatternGraph(("a",), ((1, 1),)) == PatternGraph(("a",), (), (1,))
    order = ordering.cheapest_joins(p, {"X": 100, "Y": 2}, {("X", "Y"): 3, ("Y", "X"): 3, ("X", "X"): 800})
    assert ordering.validate_order(p, order)[0] == 2  # the rare label first
    counts, pairs = {1: 5, 2: 1, 3: 9}, {("X", "Y"): 3, ("Y", "X"): 3, ("X", "X"): 8}
    for order in (ordering.given(p), ordering.smallest_domain_first(p, counts), ordering.join_size_greedy(p, counts, {k: v / 9 for k, v in pairs.items()}), ordering.tree_path_first(p, counts, pairs), ordering.dense_then_tree_then_leaf(p), ordering.rare_edge_spanning(p, pairs)):
        ordering.validate_order(p, order)


@pytest.mark.parametrize("seed", range(40))
def test_conditions_on_several_positions(seed):
    """A failed comparison is a reason of its own: nothing is lost, and what is learnt holds under the conditions."""
    p, label, edges = random_case(seed)
    if p.n < 2:
        return
    rng = random.Random(seed)
    a, b = rng.sample(range(p.n), 2)
    adjacency = {}
    for x, y in edges:
        adjacency.setdefault(x, set()).add(y)
        adjacency.setdefault(y, set()).add(x)
    domains = [sorted(v for v, x in label.items() if x == y) for y in p.labels]
    checks = ((1 << a | 1 << b, lambda asg: asg[a] < asg[b]),)
    want = [r for r in search_unit(p.nbr_mask(), domains, adjacency, mode="plain").rows if r[a] < r[b]]
    for o in OPTIONS:
        assert search_unit(p.nbr_mask(), domains, adjacency, checks=checks, **o).rows == want, o


def test_patterns_of_more_than_63_vertices():
    """A long path in a ring: reasons are sets of more positions than a 64-bit number has."""
    n = 70
    ring = {i: {(i + 1) % 80, (i - 1) % 80} for i in range(80)}
    p = PatternGraph(tuple("a" * n), tuple((i, i + 1) for i in range(1, n)))
    r = search_unit(p.nbr_mask(), [list(range(80))] * n, ring, cap=3)
    assert len(r.rows) == 3 and all(len(set(row)) == n for row in r.rows)


def test_rows_come_in_batches(monkeypatch):
    from branchwise.operators import kernel

    monkeypatch.setattr(kernel, "BATCH", 5)
    p = PatternGraph(tuple("aa"), ())
    sizes = [len(b) for b in kernel.search_rows(p.nbr_mask(), [list(range(6))] * 2, {})]
    assert sum(sizes) == 30 and max(sizes) == 5


def test_refinement_from_either_side():
    from branchwise.operators.kernel import _meet

    few, many = {3, 500, 77, 9_000}, list(range(0, 10_000, 3))
    assert _meet(many, few) == [3, 9_000] == [c for c in many if c in few]
    assert _meet([1, 2, 3], set(range(2, 1000))) == [2, 3]


@pytest.mark.parametrize("seed", range(60))
def test_side_by_side_visits_what_the_kernel_visits(seed, monkeypatch):
    """Same rows in the same order and same counts, in small parts, with lists dropped, with and without the embeddings."""
    p, label, edges = random_case(seed)
    adjacency = {}
    for a, b in edges:
        adjacency.setdefault(a, set()).add(b)
        adjacency.setdefault(b, set()).add(a)
    domains = [sorted(v for v, x in label.items() if x == y) for y in p.labels]
    for name, k in (("WIDE", 5), ("ROOTS", 2), ("HELD", 1 + seed % 2 * 1000)):
        monkeypatch.setattr(wide, name, k)
    for mode in ("plain", "no_lookup"):
        for injective in (True, False):
            want = search_unit(p.nbr_mask(), domains, adjacency, mode=mode, injective=injective)
            for rows in (True, False):
                found, search = [], wide.search_wide(p.nbr_mask(), domains, adjacency, every=mode != "plain", injective=injective, labels=p.labels, embeddings=rows)
                try:
                    while True:
                        found += next(search)
                except StopIteration as done:
                    got = done.value.stats
                assert found == (want.rows if rows else []) and got | {"elapsed_ns": 0} == want.stats | {"elapsed_ns": 0}


def test_lists_are_met_once(monkeypatch):
    """Four leaves of the root before a triangle that is not there: what the root leaves of the triangle is not found anew under each choice."""
    adjacency = {0: set(range(1, 40))} | {v: {0} for v in range(1, 40)}
    asked, meet = [], kernel._meet
    monkeypatch.setattr(kernel, "_meet", lambda *a: asked.append(1) or meet(*a))
    p = PatternGraph(tuple("abbcd"), ((1, 2), (1, 3), (1, 4), (1, 5), (4, 5)))
    domains = [[0], list(range(1, 20)), list(range(1, 20)), list(range(20, 30)), list(range(30, 40))]
    r = search_unit(p.nbr_mask(), domains, adjacency, mode="no_lookup")
    assert r.stats["search_calls"] == 1 + 1 + 19 + 19 * 18 + 19 * 18 * 10 and r.stats["f_wipeout"] == 19 * 18 * 10 and len(asked) < 30
