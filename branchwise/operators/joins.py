"""Matching as joins: one plan per pattern, or level by level for whole query sets."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from branchwise.plans.ordering import cheapest_joins, joined_by_pairs
from branchwise.plans.pattern import QUERY_SET, PatternGraph

from .candidates import cut
from .graph import LabeledGraph
from .storage import discard


def join_order(g: LabeledGraph, p: PatternGraph) -> tuple[int, ...]:
    """The order of least estimated rows, from counts of the pattern's labels and label pairs."""
    return cheapest_joins(p, *g.statistics(set(p.labels)))


def join_match(g: LabeledGraph, p: PatternGraph, order: tuple[int, ...] | None = None, injective: bool = True, limit: int | None = None, domains: DataFrame | None = None, checks: tuple = ()) -> DataFrame:
    """m1..mn, numbered as in the pattern whatever the order. Every step is an equi-join on an anchor edge
    with both labels pushed to the edge scan; further edges to what is mapped are semi-joins. Where an anchor has very many edges
    (a cycle through a hub), the pairs of edges to two mapped neighbours are made first and met by both. domains (pos, vid) narrow
    the images; checks are comparisons (u, operator, w) of two images."""
    if not p.n:
        return g.vertices.sparkSession.range(1).select()  # the empty pattern has one empty embedding
    order = order or join_order(g, p)
    paired = joined_by_pairs(p, order, *g.statistics(set(p.labels))) if any(len(p.neighbors(u) & set(order[:k])) > 1 for k, u in enumerate(order)) else set()
    out, done = None, []
    for u in order:
        own = g.vertices.filter(F.col("label") == p.labels[u - 1]).select(F.col("vid").alias(f"m{u}"))
        narrow = domains is not None or u in p.loops
        if domains is not None:
            own = own.join(domains.filter(F.col("pos") == u).select(F.col("vid").alias(f"m{u}")), f"m{u}", "left_semi")
        if u in p.loops:
            own = own.filter("false") if g.loops is None else own.join(g.loops.select(F.col("vid").alias(f"m{u}")), f"m{u}", "left_semi")
        back = [w for w in done if w in p.neighbors(u)]
        apart = [w for w in done if injective and p.labels[w - 1] == p.labels[u - 1] and w not in back]
        edge = lambda w: g.edges.filter((F.col("src_label") == p.labels[w - 1]) & (F.col("dst_label") == p.labels[u - 1])).select(F.col("src").alias(f"m{w}"), F.col("dst").alias(f"m{u}"))  # noqa: B023, E731
        if out is None:
            out = own
        elif u in paired:
            two = edge(back[0]).join(edge(back[1]), f"m{u}")
            if narrow:
                two = two.join(own, f"m{u}", "left_semi")
            out = out.join(two, [f"m{back[0]}", f"m{back[1]}"])
        elif back:
            out = out.join(edge(back[0]), f"m{back[0]}")
            if narrow:
                out = out.join(own, f"m{u}", "left_semi")
        else:
            out = out.crossJoin(own)  # a pattern in several parts asks for the product of their results
        for w in back[2 if u in paired else 1 :]:
            out = out.join(edge(w), [f"m{w}", f"m{u}"], "left_semi")
        for w in apart:
            out = out.filter(F.col(f"m{w}") != F.col(f"m{u}"))
        done.append(u)
        for a, op, b in checks:
            if u in (a, b) and {a, b} <= set(done):
                out = out.filter(f"m{a} {op} m{b}")
    out = out.select(*(f"m{i}" for i in range(1, p.n + 1)))
    return out if limit is None else out.orderBy(*out.columns).limit(limit)


def count_matches(g: LabeledGraph, p: PatternGraph, **options) -> DataFrame:
    return join_match(g, p, **options).agg(F.count(F.lit(1)).alias("n_found"))


def exists_match(g: LabeledGraph, p: PatternGraph) -> bool:
    return not join_match(g, p).limit(1).isEmpty()


def query_set(spark, patterns: list[PatternGraph], orders: list[tuple[int, ...]] | None = None) -> DataFrame:
    return spark.createDataFrame([p.to_row(i, orders[i] if orders else None) for i, p in enumerate(patterns)], QUERY_SET)


def compile_levels(queries: DataFrame) -> DataFrame:
    """One row per query and position of its order: label, the mapped neighbours' positions (back), positions of equal label."""
    flat = queries.select("query_id", "n_vertices", "vertices", "edges", "match_order", F.posexplode("match_order").alias("k", "u"))
    label = F.expr("filter(vertices, x -> x.u = u)[0].label")
    partner = F.expr("transform(filter(edges, x -> x.a = u OR x.b = u), x -> array_position(match_order, CASE WHEN x.a = u THEN x.b ELSE x.a END) - 1)")
    return flat.select("query_id", "n_vertices", F.col("k").cast("int").alias("k"), label.alias("label"), F.array_sort(F.filter(partner, lambda x: x < F.col("k"))).alias("back"))


def expand(g: LabeledGraph, frontier: DataFrame, steps: DataFrame) -> DataFrame:
    """One level for all queries: by the anchor edge where there is one, by the label domain otherwise; then the other edges."""
    ready = frontier.join(steps, "query_id")
    edges = g.edges.select(F.col("src").alias("anchor"), F.col("dst").alias("new"), F.col("dst_label").alias("label"))
    near = ready.filter("size(back) > 0").withColumn("anchor", F.element_at("asg", F.element_at("back", 1).cast("int") + 1)).join(edges, ["anchor", "label"]).drop("anchor")
    free = ready.filter("size(back) = 0").join(g.vertices.select(F.col("vid").alias("new"), "label"), "label")
    grown = near.unionByName(free, allowMissingColumns=True).filter(~F.array_contains("asg", F.col("new")))
    more = grown.filter("size(back) > 1").withColumn("rest", F.slice("back", F.lit(2), F.size("back") - 1)).withColumn("b", F.explode("rest")).withColumn("src", F.element_at("asg", F.col("b").cast("int") + 1))
    closed = more.join(g.edges.select("src", F.col("dst").alias("new")), ["src", "new"], "left_semi")
    closed = closed.groupBy("query_id", "asg", "new", "n_vertices").agg(F.count(F.lit(1)).alias("met"), F.first(F.size("rest")).alias("need")).filter("met = need")
    whole = grown.filter("size(back) < 2").select("query_id", "asg", "new", "n_vertices").unionByName(closed.select("query_id", "asg", "new", "n_vertices"))
    return whole.select("query_id", F.array_append("asg", F.col("new")).alias("asg"))


def level_frontiers(g: LabeledGraph, queries: DataFrame) -> list[DataFrame]:
    """The frontier after each level, all queries together; each is settled."""
    steps = cut(compile_levels(queries))
    deepest = steps.agg(F.max("k")).first()[0]
    frontier = queries.select("query_id", F.expr("cast(array() as array<bigint>)").alias("asg"))
    out = []
    for k in range(0 if deepest is None else deepest + 1):
        frontier = cut(expand(g, frontier, steps.filter(F.col("k") == k).drop("k")))
        out.append(frontier)
    return out


def shared_match(g: LabeledGraph, p: PatternGraph, order: tuple[int, ...] | None = None) -> tuple[DataFrame, DataFrame]:
    """(m1..mn, statistics): level by level, where the images of the next vertex are found once for all rows that agree on
    its mapped neighbours, and joined back. Statistics: level, rows, distinct projections, and how many of those have no
    image at all, which closes every row that shares them."""
    order = order or join_order(g, p)
    spark = g.vertices.sparkSession
    out, stats = None, []
    for k, u in enumerate(order):
        own = g.vertices.filter(F.col("label") == p.labels[u - 1]).select(F.col("vid").alias(f"m{u}"))
        if u in p.loops:
            own = own.filter("false") if g.loops is None else own.join(g.loops.select(F.col("vid").alias(f"m{u}")), f"m{u}", "left_semi")
        back = [w for w in order[:k] if w in p.neighbors(u)]
        apart = [w for w in order[:k] if p.labels[w - 1] == p.labels[u - 1] and w not in back]
        edge = lambda w: g.edges.filter((F.col("src_label") == p.labels[w - 1]) & (F.col("dst_label") == p.labels[u - 1])).select(F.col("src").alias(f"m{w}"), F.col("dst").alias(f"m{u}"))  # noqa: B023, E731
        keys = [f"m{w}" for w in back]
        projections = dead = 0
        if out is None:
            grown = own
        elif back:
            asked = cut(out.select(*keys).distinct())
            images = asked.join(edge(back[0]), keys[0])
            for w in back[1:]:
                images = images.join(edge(w), [f"m{w}", f"m{u}"], "left_semi")
            if u in p.loops:
                images = images.join(own, f"m{u}", "left_semi")
            images = cut(images.select(*keys, f"m{u}"))
            projections, dead = asked.count(), asked.join(images, keys, "left_anti").count()
            grown = out.join(images, keys)
        else:
            grown = out.crossJoin(own)  # a pattern in several parts asks for the product of their results
        for w in apart:
            grown = grown.filter(F.col(f"m{w}") != F.col(f"m{u}"))
        before, out = out, cut(grown)
        if before is not None:
            discard(before)
        stats.append((k + 1, out.count(), projections, dead))
    return out.select(*(f"m{i}" for i in range(1, p.n + 1))), spark.createDataFrame(stats, "level int, rows bigint, projections bigint, dead bigint")


def level_match(g: LabeledGraph, queries: DataFrame) -> DataFrame:
    """query_id and asg, numbered as in the pattern (position u - 1 of asg is the image of u)."""
    fronts = level_frontiers(g, queries)
    plan = queries.select("query_id", "n_vertices", "match_order")
    if not fronts:
        return plan.select("query_id", F.expr("cast(array() as array<bigint>)").alias("asg"))
    done = fronts[0]
    for f in fronts[1:]:
        done = done.unionByName(f)
    done = done.join(plan, "query_id").filter("size(asg) = n_vertices")
    return done.select("query_id", F.expr("transform(sequence(1, n_vertices), u -> asg[cast(array_position(match_order, u) - 1 as int)])").alias("asg"))


def level_sizes(g: LabeledGraph, queries: DataFrame) -> DataFrame:
    """query_id, level, rows: the visited assignments of plain search are these rows and the root."""
    fronts = level_frontiers(g, queries)
    parts = [f.groupBy("query_id").agg(F.count(F.lit(1)).alias("rows")).select("query_id", F.lit(i).alias("level"), "rows") for i, f in enumerate(fronts, 1)]
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out


def as_array(wide: DataFrame) -> DataFrame:
    return wide.select(F.array(*wide.columns).alias("asg"))


def as_map(wide: DataFrame) -> DataFrame:
    return wide.select(F.map_from_arrays(F.array(*(F.lit(i) for i in range(1, len(wide.columns) + 1))), F.array(*wide.columns)).alias("mapping"))


def as_wide(arrays: DataFrame, n: int) -> DataFrame:
    return arrays.select(*(F.col("asg")[i].alias(f"m{i + 1}") for i in range(n)))


def distinct_images(wide: DataFrame) -> DataFrame:
    """One row per set of images: automorphic embeddings fall together."""
    return wide.select(F.array_sort(F.array(*wide.columns)).alias("image")).distinct()
