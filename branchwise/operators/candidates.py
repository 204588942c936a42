"""Candidate filters: per pattern vertex the data vertices that may be its image, (pos, vid).

Every filter may only drop a vertex that no embedding uses there.
"""

from __future__ import annotations

from collections import Counter
from itertools import combinations

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from branchwise.plans.pattern import PatternGraph

from .graph import LabeledGraph
from .storage import discard, settled


#: Up to this many neighbours of a pattern vertex, matchings are tested by the sizes of all their sets; beyond it by augmenting paths.
HALL = 5


def _rows(g: LabeledGraph, rows: list[tuple], schema: str) -> DataFrame:
    """A table of the pattern's own size, so it can always be broadcast."""
    return F.broadcast(g.vertices.sparkSession.createDataFrame(rows, schema))


def label_domains(g: LabeledGraph, p: PatternGraph, where: dict[int, str] | None = None) -> DataFrame:
    """where: by vertex of the pattern, an SQL condition on the columns of vertices (vid, label and attributes). It drops only
    vertices that are no image there, so every engine and what it learns stay exact."""
    labels = _rows(g, [(i, x) for i, x in enumerate(p.labels, 1)], "pos int, label string")
    met = g.vertices.join(labels, "label")
    for u, condition in (where or {}).items():
        met = met.filter((F.col("pos") != u) | F.expr(condition))
    dom = met.select("pos", "vid")
    return dom if not p.loops else _with_loops(g, p, dom)


def _with_loops(g: LabeledGraph, p: PatternGraph, dom: DataFrame) -> DataFrame:
    """Vertices of the pattern with an edge to themselves need an image with one."""
    looped = F.col("pos").isin(list(p.loops))
    kept = dom.filter(~looped)
    return kept if g.loops is None else kept.unionByName(dom.filter(looped).join(g.loops, "vid", "left_semi").select("pos", "vid"))


def degree_filter(g: LabeledGraph, p: PatternGraph, dom: DataFrame) -> DataFrame:
    need = _rows(g, [(u, len(p.neighbors(u))) for u in range(1, p.n + 1)], "pos int, need int")
    deg = dom.join(g.degrees(), "vid", "left").join(need, "pos")
    return deg.filter(F.coalesce("deg", F.lit(0)) >= F.col("need")).select("pos", "vid")


def neighbor_label_filter(g: LabeledGraph, p: PatternGraph, dom: DataFrame, counts: bool = True) -> DataFrame:
    """At least as many neighbours of each label (or some, with counts=False) as in the pattern."""
    need = [(u, x, n if counts else 1) for u in range(1, p.n + 1) for x, n in Counter(p.labels[w - 1] for w in p.neighbors(u)).items()]
    free = [u for u in range(1, p.n + 1) if not p.neighbors(u)]
    has = g.edges.join(_rows(g, [(x,) for x in sorted(set(p.labels))], "dst_label string"), "dst_label").groupBy(F.col("src").alias("vid"), F.col("dst_label").alias("label")).agg(F.count(F.lit(1)).alias("n"))
    wanted = _rows(g, need, "pos int, label string, need int")
    kinds = _rows(g, list(Counter(u for u, _, _ in need).items()), "pos int, kinds int")
    met = dom.join(wanted, "pos").join(has, ["vid", "label"]).filter("n >= need").groupBy("pos", "vid").agg(F.count(F.lit(1)).alias("met"))
    kept = met.join(kinds, "pos").filter("met = kinds").select("pos", "vid")
    return kept.unionByName(dom.filter(F.col("pos").isin(free)).select("pos", "vid")) if free else kept


def _semi(g: LabeledGraph, dom: DataFrame, pairs: list[tuple[int, int]]) -> DataFrame:
    """(pos, vid) that have, for each given (pos, other), a neighbour in other's domain."""
    links = _rows(g, pairs, "pos int, other int")
    need = _rows(g, list(Counter(a for a, _ in pairs).items()), "pos int, need int")
    reach = dom.join(links, "pos").join(g.edges.select(F.col("src").alias("vid"), "dst"), "vid")
    met = reach.join(dom.select(F.col("pos").alias("other"), F.col("vid").alias("dst")), ["other", "dst"], "left_semi").select("pos", "vid", "other").distinct().groupBy("pos", "vid").agg(F.count(F.lit(1)).alias("met"))
    kept = met.join(need, "pos").filter("met = need").select("pos", "vid")
    others = sorted({a for a, _ in pairs})
    return kept.unionByName(dom.filter(~F.col("pos").isin(others)).select("pos", "vid"))


def arc_consistency(g: LabeledGraph, p: PatternGraph, dom: DataFrame, rounds: int | None = None) -> DataFrame:
    """Rounds of neighbour tests over all pattern edges; without a number until nothing changes (one count a round)."""
    pairs = [(a, b) for x, y in p.edges for a, b in ((x, y), (y, x))]
    if not pairs:
        return dom
    if rounds is not None:
        for _ in range(rounds):
            dom = cut(_semi(g, dom, pairs))
        return dom
    return _fixpoint(lambda d: _semi(g, d, pairs), dom)


def _fixpoint(step, dom: DataFrame) -> DataFrame:
    """Rounds of a filter until one drops nothing."""
    dom = cut(dom)
    size = dom.count()
    while True:
        before, dom = dom, cut(step(dom))
        left = dom.count()
        discard(before)
        if left == size:
            return dom
        size = left


def cut(df: DataFrame) -> DataFrame:
    """Ends the lineage of a loop."""
    return settled(df, "step")


def tree_filter(g: LabeledGraph, p: PatternGraph, dom: DataFrame, root: int = 1) -> DataFrame:
    """A sweep up a breadth-first tree, then one down."""
    tree = p.bfs_tree(root)
    for a, c in reversed(tree):
        dom = cut(_semi(g, dom, [(a, c)]))
    for a, c in tree:
        dom = cut(_semi(g, dom, [(c, a)]))
    return dom


def bipartite_filter(g: LabeledGraph, p: PatternGraph, dom: DataFrame, rounds: int | None = None) -> DataFrame:
    """The pattern neighbours can be given different data neighbours, each from its domain; again until nothing drops, or
    for a number of rounds."""
    if rounds is None:
        return _fixpoint(lambda d: _bipartite_round(g, p, d), dom)
    for _ in range(rounds):
        dom = cut(_bipartite_round(g, p, dom))
    return dom


def _bipartite_round(g: LabeledGraph, p: PatternGraph, dom: DataFrame) -> DataFrame:
    links = [(a, b) for x, y in p.edges for a, b in ((x, y), (y, x))]
    need = {u: sorted(p.neighbors(u)) for u in range(1, p.n + 1)}
    free = [u for u, w in need.items() if not w]
    reach = dom.join(_rows(g, links, "pos int, other int"), "pos").join(g.edges.select(F.col("src").alias("vid"), "dst"), "vid").join(dom.select(F.col("pos").alias("other"), F.col("vid").alias("dst")), ["other", "dst"], "left_semi")
    if max(map(len, need.values()), default=0) <= HALL:
        # Every set of neighbours must reach as many vertices as it has members.
        sets = [(u, i, o) for u, w in need.items() for i, some in enumerate(s for k in range(1, len(w) + 1) for s in combinations(w, k)) for o in some]
        size = Counter((u, i) for u, i, _ in sets)
        reached = reach.join(_rows(g, sets, "pos int, part int, other int"), ["pos", "other"]).groupBy("pos", "vid", "part").agg(F.count_distinct("dst").alias("n"))
        met = reached.join(_rows(g, [(u, i, n) for (u, i), n in size.items()], "pos int, part int, need int"), ["pos", "part"]).filter("n >= need").groupBy("pos", "vid").agg(F.count(F.lit(1)).alias("met"))
        kept = met.join(_rows(g, list(Counter(u for u, _ in size).items()), "pos int, parts int"), "pos").filter("met = parts").select("pos", "vid")
    else:
        # A vertex needs at most n distinct partners per neighbour: the n least suffice for a matching.
        few = reach.groupBy("pos", "vid", "other").agg(F.slice(F.array_sort(F.collect_set("dst")), 1, p.n).alias("partners")).groupBy("pos", "vid").agg(F.map_from_entries(F.collect_list(F.struct("other", "partners"))).alias("m"))

        def matched(part: pd.Series, pos: pd.Series) -> pd.Series:
            return pd.Series([_saturates(need[int(u)], dict(m)) for m, u in zip(part, pos)])

        kept = few.filter(F.pandas_udf(matched, "boolean")("m", "pos")).select("pos", "vid")
    return kept.unionByName(dom.filter(F.col("pos").isin(free)).select("pos", "vid")) if free else kept


def _saturates(need: list[int], partners: dict[int, list[int]]) -> bool:
    held: dict[int, int] = {}

    def place(u: int, seen: set[int]) -> bool:
        for v in partners.get(u, ()):
            v = int(v)
            if v not in seen:
                seen.add(v)
                if v not in held or place(held[v], seen):
                    held[v] = u
                    return True
        return False

    return all(place(u, set()) for u in need)


def candidate_edges(g: LabeledGraph, p: PatternGraph, dom: DataFrame) -> DataFrame:
    """(a, b, src, dst): data edges with both ends in the domains of a pattern edge, in both directions."""
    links = _rows(g, [(a, b, p.labels[a - 1], p.labels[b - 1]) for x, y in p.edges for a, b in ((x, y), (y, x))], "a int, b int, src_label string, dst_label string")
    near = g.edges.join(links, ["src_label", "dst_label"]).select("a", "b", "src", "dst")
    near = near.join(dom.select(F.col("pos").alias("a"), F.col("vid").alias("src")), ["a", "src"], "left_semi")
    return near.join(dom.select(F.col("pos").alias("b"), F.col("vid").alias("dst")), ["b", "dst"], "left_semi").select("a", "b", "src", "dst")


FILTERS = {"degree": degree_filter, "labels": neighbor_label_filter, "arcs": lambda g, p, d: arc_consistency(g, p, d, 1), "tree": tree_filter, "bipartite": bipartite_filter}


def build_domains(g: LabeledGraph, p: PatternGraph, filters: tuple[str, ...] = (), where: dict[int, str] | None = None) -> DataFrame:
    dom = label_domains(g, p, where)
    for name in filters:
        dom = FILTERS[name](g, p, dom)
    return dom


def domain_sizes(dom: DataFrame) -> dict[int, int]:
    return {r.pos: r.n for r in dom.groupBy("pos").agg(F.count(F.lit(1)).alias("n")).collect()}
