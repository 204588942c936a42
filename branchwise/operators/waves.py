"""Set-oriented learning: the frontier at a split level is cut in waves, and what one wave shows to be
fruitless closes rows of the next ones.

Each wave keeps, level by level, every candidate: alive, or a leaf with its reason (REUSE, or KNOWN
from an earlier wave). Folding back from the last level gives the reasons of fruitless rows;
projected to the positions they name, they are nogoods by value, matched by equality of the
values themselves. A closed row stays as a leaf, since its parent's fold needs its reason.
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from branchwise.plans.pattern import PatternGraph

from .candidates import cut
from .graph import LabeledGraph

#: Sets of positions a row of a wave is probed with.
PROBES = 16
NOGOODS = "k int, reason bigint, vals array<bigint>"


def _values(reason, asg="asg"):
    """Values of an assignment at the positions of a reason."""
    return F.expr(f"filter(transform({asg}, (v, i) -> CASE WHEN shiftright({reason}, i) & 1 = 1 THEN v END), v -> v IS NOT NULL)")


def candidates(g: LabeledGraph, p: PatternGraph, order: tuple[int, ...], k: int, frontier: DataFrame) -> DataFrame:
    """(asg, new): all images of position k that its label and its mapped neighbours allow, used ones included."""
    u = order[k]
    back = [i for i, w in enumerate(order[:k]) if w in p.neighbors(u)]
    if not back:
        own = g.vertices.filter(F.col("label") == p.labels[u - 1]).select(F.col("vid").alias("new"))
        return frontier.crossJoin(own)  # only for a pattern in several parts, or for the first position
    edge = lambda i: g.edges.filter((F.col("src_label") == p.labels[order[i] - 1]) & (F.col("dst_label") == p.labels[u - 1])).select(F.col("src").alias(f"b{i}"), F.col("dst").alias("new"))
    out = frontier.select("asg", *(F.col("asg")[i].alias(f"b{i}") for i in back)).join(edge(back[0]), f"b{back[0]}")
    for i in back[1:]:
        out = out.join(edge(i), [f"b{i}", "new"], "left_semi")
    return out.select("asg", "new")


def traced_level(g, p, order, k, frontier, nogoods: DataFrame | None) -> DataFrame:
    """(asg, new, cause, reason) of every candidate of position k; alive ones have no cause."""
    rows = candidates(g, p, order, k, frontier)
    if k:
        holder = F.array_position("asg", F.col("new")) - 1
        reuse = F.when(holder >= 0, F.expr(f"shiftleft(1L, cast(array_position(asg, new) - 1 as int)) | shiftleft(1L, {k})"))
    else:
        reuse = F.lit(None).cast("bigint")
    rows = rows.withColumn("r_reuse", reuse)
    if nogoods is None:
        return rows.select("asg", "new", F.when(F.col("r_reuse").isNotNull(), F.lit("REUSE")).alias("cause"), F.col("r_reuse").alias("reason"))
    known = nogoods.filter(F.col("k") == k)
    # A row is probed once per set of positions: only with those that the most nogoods name. What is left out prunes nothing.
    masks = [r.reason for r in known.groupBy("reason").count().orderBy(F.desc("count"), "reason").limit(PROBES).collect()]
    if not masks:
        return rows.select("asg", "new", F.when(F.col("r_reuse").isNotNull(), F.lit("REUSE")).alias("cause"), F.col("r_reuse").alias("reason"))
    full = rows.withColumn("all", F.array_append("asg", F.col("new")))
    probes = full.withColumn("mask", F.explode(F.array(*map(F.lit, masks)))).select("asg", "new", "mask", _values("mask", "all").alias("vals"))
    hits = probes.join(known.select(F.col("reason").alias("mask"), "vals"), ["mask", "vals"], "left_semi").groupBy("asg", "new").agg(F.min_by("mask", F.struct(F.bit_count("mask"), F.col("mask"))).alias("r_known"))
    joined = rows.join(hits, ["asg", "new"], "left")
    cause = F.when(F.col("r_reuse").isNotNull(), F.lit("REUSE")).when(F.col("r_known").isNotNull(), F.lit("KNOWN"))
    return joined.select("asg", "new", cause.alias("cause"), F.coalesce("r_reuse", "r_known").alias("reason"))


def fold_up(p: PatternGraph, order, k: int, frontier: DataFrame, level: DataFrame, below: DataFrame | None) -> DataFrame:
    """(asg, found, reason, cause) of the frontier at k from its candidates and, for alive ones, from what was found below."""
    masks = p.nbr_mask(order)
    mapped = (1 << k) - 1
    if below is None:
        settled = level.select("asg", F.col("cause").isNull().alias("found"), F.coalesce("reason", F.lit(0)).alias("reason"))
    else:
        under = below.select(F.slice("asg", 1, k).alias("asg"), F.element_at("asg", -1).alias("new"), "found", F.col("reason").alias("r"))
        joined = level.join(under, ["asg", "new"], "left")
        settled = joined.select("asg", F.coalesce("found", F.lit(False)).alias("found"), F.coalesce("reason", "r", F.lit(0)).alias("reason"))
    union = settled.groupBy("asg").agg(F.bool_or("found").alias("found"), F.bit_or(F.when(~F.col("found"), F.col("reason")).otherwise(0)).alias("u"))
    wipe = masks[k] & mapped
    folded = F.when(F.col("u").isNull(), F.lit(wipe)).when(F.col("u").bitwiseAND(F.lit(1 << k)) != 0, F.col("u").bitwiseOR(F.lit(masks[k])).bitwiseAND(F.lit(mapped))).otherwise(F.col("u"))
    cause = F.when(F.col("u").isNull() & F.col("found").isNull(), F.lit("WIPEOUT")).otherwise(F.lit("CHILD"))
    return frontier.join(union, "asg", "left").select("asg", F.coalesce("found", F.lit(False)).alias("found"), folded.cast("bigint").alias("reason"), cause.alias("cause"))


def nogoods_of(k: int, folded: DataFrame) -> DataFrame:
    """Fruitless rows with k positions mapped, as (last position, reason, values): one per reason and values."""
    return folded.filter("NOT found").select(F.lit(k - 1).alias("k"), "reason", _values("reason").alias("vals")).distinct()


def wave_match(g: LabeledGraph, p: PatternGraph, split_level: int = 2, waves: int = 4, order: tuple[int, ...] | None = None) -> tuple[DataFrame, DataFrame, DataFrame]:
    """(embeddings m1..mn, nogoods, statistics by wave and level). Nogoods come from positions after the split level,
    where each wave has seen all candidates of its rows."""
    order = order or tuple(range(1, p.n + 1))
    spark = g.vertices.sparkSession
    split_level = max(1, min(split_level, p.n))
    frontier = spark.createDataFrame([([],)], "asg array<bigint>")
    for k in range(split_level):
        frontier = cut(candidates(g, p, order, k, frontier).filter(~F.array_contains("asg", F.col("new"))).select(F.array_append("asg", F.col("new")).alias("asg")))
    wave = F.pmod(F.xxhash64(F.element_at("asg", -1)), F.lit(waves))
    learnt = spark.createDataFrame([], NOGOODS)
    done, stats = None, []
    for w in range(waves):
        front = frontier.filter(wave == w)
        fronts, levels = [front], []
        for k in range(split_level, p.n):
            level = cut(traced_level(g, p, order, k, fronts[-1], learnt if w else None))
            counts = level.groupBy(F.coalesce("cause", F.lit("ALIVE")).alias("cause")).agg(F.count(F.lit(1)).alias("rows")).collect()
            stats += [(w, k + 1, c.cause, c.rows) for c in counts]
            levels.append(level)
            fronts.append(level.filter("cause IS NULL").select(F.array_append("asg", F.col("new")).alias("asg")))
        done = fronts[-1] if done is None else done.unionByName(fronts[-1])
        below = None
        for k in range(p.n - 1, split_level - 1, -1):
            below = cut(fold_up(p, order, k, fronts[k - split_level], levels[k - split_level], below))
            learnt = learnt.unionByName(nogoods_of(k, below)) if k else learnt
        learnt = cut(learnt.distinct())
    back = [order.index(u) for u in range(1, p.n + 1)]
    wide = done.select(*(F.col("asg")[i].alias(f"m{u}") for u, i in enumerate(back, 1)))
    return wide, learnt, spark.createDataFrame(stats, "wave int, level int, cause string, rows bigint")


def explain_empty(g: LabeledGraph, p: PatternGraph, order: tuple[int, ...] | None = None) -> DataFrame:
    """(level, cause, reason, rows): why assignments fail, over all of them (one wave, from the first position). A row at a
    level has so many positions mapped; WIPEOUT has no candidate for the next, CHILD has some and each of them fails,
    REUSE is a candidate that is held already."""
    order = order or tuple(range(1, p.n + 1))
    spark = g.vertices.sparkSession
    fronts, levels = [spark.createDataFrame([([],)], "asg array<bigint>")], []
    for k in range(p.n):
        levels.append(cut(traced_level(g, p, order, k, fronts[-1], None)))
        fronts.append(levels[-1].filter("cause IS NULL").select(F.array_append("asg", F.col("new")).alias("asg")))
    parts, below = [], None
    for k in range(p.n - 1, -1, -1):
        below = cut(fold_up(p, order, k, fronts[k], levels[k], below))
        parts.append(below.filter("NOT found").groupBy(F.lit(k).alias("level"), "cause", "reason").agg(F.count(F.lit(1)).alias("rows")))
        parts.append(levels[k].filter("cause = 'REUSE'").groupBy(F.lit(k + 1).alias("level"), "cause", "reason").agg(F.count(F.lit(1)).alias("rows")))
    return reduce(DataFrame.unionByName, parts) if parts else spark.createDataFrame([], "level int, cause string, reason bigint, rows bigint")
