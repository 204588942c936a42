"""Shared-nothing search: every root gets the candidate edges its pattern can reach, and is searched alone.

Nothing is broadcast but the pattern. Regions grow along a breadth-first tree by joins. The edges of each root are counted
first; a root with more than ``unit_edges`` of them is cut into units by its second vertex: a unit gets its share of
the images of the second vertex, and of the rest only what is reached from there (or from the root past it), so
that a hub is many tasks, none of them with the whole. What a unit learns holds only inside it.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from branchwise.plans.pattern import PatternGraph

from .candidates import build_domains, candidate_edges
from .graph import LabeledGraph
from .kernel import search_rows
from .storage import settled

UNIT_EDGES = 200_000


def extract_regions(edges: DataFrame, dom: DataFrame, p: PatternGraph, units: DataFrame | None = None) -> DataFrame:
    """(root, unit, a, b, src, dst): candidate edges between positions, as reached from each image of vertex 1. units: root and
    n_units of the roots that are cut."""
    roots = dom.filter("pos = 1").select(F.col("vid").alias("root"), F.col("vid").alias("vid"))
    if units is None:
        roots = roots.withColumns({"n_units": F.lit(1), "unit": F.lit(0)})
    else:
        roots = roots.join(units, "root", "left").withColumn("n_units", F.coalesce("n_units", F.lit(1)))
        roots = roots.withColumn("unit", F.explode(F.sequence(F.lit(0), F.col("n_units") - 1)))
    reach = {1: roots}
    for k, (a, c) in enumerate(p.bfs_tree(1)):
        step = edges.filter((F.col("a") == a) & (F.col("b") == c)).select(F.col("src").alias("vid"), "dst")
        met = reach[a].join(step, "vid")
        if not k:
            met = met.filter(F.pmod(F.xxhash64("dst"), F.col("n_units")) == F.col("unit"))
        reach[c] = met.select("root", "n_units", "unit", F.col("dst").alias("vid")).distinct()
    out = None
    for a, b in p.edges:
        own = edges.filter((F.col("a") == a) & (F.col("b") == b))
        ends = reach[b].select("root", "unit", F.col("vid").alias("dst"))
        part = reach[a].withColumnRenamed("vid", "src").join(own, "src").join(ends, ["root", "unit", "dst"], "left_semi").select("root", "unit", "a", "b", "src", "dst")
        out = part if out is None else out.unionByName(part)
    return out


def region_units(edges: DataFrame, dom: DataFrame, p: PatternGraph, unit_edges: int) -> DataFrame:
    """(root, n_units) of the roots with more than unit_edges candidate edges."""
    weight = extract_regions(edges, dom, p).groupBy("root").agg(F.count(F.lit(1)).alias("n"))
    return weight.filter(F.col("n") > unit_edges).select("root", F.ceil(F.col("n") / unit_edges).cast("int").alias("n_units"))


def region_match(g: LabeledGraph, p: PatternGraph, mode: str = "learned", filters: tuple[str, ...] = ("degree", "labels"), unit_edges: int = UNIT_EDGES, where: dict[int, str] | None = None) -> DataFrame:
    """m1..mn. The pattern must be connected and have an edge; positions are searched in breadth-first order from 1."""
    if not p.is_connected() or not p.edges:
        raise ValueError("regions need a connected pattern with an edge; use join_match")
    dom = settled(build_domains(g, p, filters, where), "domains")
    edges = settled(candidate_edges(g, p, dom), "candidate-edges")
    regions = extract_regions(edges, dom, p, settled(region_units(edges, dom, p, unit_edges), "units"))
    order = (1, *(c for _, c in p.bfs_tree(1)))
    masks, n = p.nbr_mask(order), p.n
    back = [order.index(u) for u in range(1, n + 1)]
    cols = [f"m{i}" for i in range(1, n + 1)]

    def found(root: int, parts: list[pa.RecordBatch]):
        adjacency: dict[int, set] = {}
        sets: dict[int, set] = {u: set() for u in order}
        for part in parts:
            for a, b, s, d in zip(*(part.column(i).to_pylist() for i in range(2, 6))):
                adjacency.setdefault(s, set()).add(d)
                adjacency.setdefault(d, set()).add(s)
                sets[a].add(s)
                sets[b].add(d)
        sets[1] &= {root}
        for rows in search_rows(masks, [sorted(sets[u]) for u in order], adjacency, mode=mode):
            at = np.array(rows, np.int64)
            yield pa.RecordBatch.from_arrays([pa.array(at[:, i]) for i in back], names=cols)

    def run(batches):
        held, current = [], None
        for b in batches:
            if not b.num_rows:
                continue
            keys = np.column_stack([b.column(i).to_numpy() for i in (0, 1)])
            edges = np.concatenate([[0], np.flatnonzero((keys[1:] != keys[:-1]).any(axis=1)) + 1, [len(keys)]]).tolist()
            for s, e in zip(edges, edges[1:]):
                key = tuple(keys[s].tolist())
                if key != current and held:
                    yield from found(current[0], held)
                    held = []
                current = key
                held.append(b.slice(s, e - s))
        if held:
            yield from found(current[0], held)

    dealt = regions.repartition("root", "unit").sortWithinPartitions("root", "unit")
    return dealt.select("root", "unit", "a", "b", "src", "dst").mapInArrow(run, ", ".join(f"{c} bigint" for c in cols))
