"""Edges from an event stream, and matching of what new edges add.

A nogood only holds while the graph does not grow, so nothing learnt is carried over a delta.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from branchwise.operators.graph import LabeledGraph
from branchwise.plans.pattern import PatternGraph


def windowed_activity(events: DataFrame, kind: str = "tumbling", size: str = "10 minutes", slide: str = "5 minutes", late: str | None = None) -> DataFrame:
    """Events per type and window (tumbling, sliding or session); the same plan for a table and for a stream."""
    at = F.col("ts").cast("timestamp")
    rows = events.withColumn("at", at)
    if late is not None:
        rows = rows.withWatermark("at", late)
    w = {"tumbling": lambda: F.window("at", size), "sliding": lambda: F.window("at", size, slide), "session": lambda: F.session_window("at", size)}[kind]()
    return rows.groupBy(w.alias("w"), "event_type").agg(F.count(F.lit(1)).alias("n"), F.sum("value").alias("total"))


def edge_stream(events: DataFrame, size: str = "1 minute", late: str = "2 minutes", salts: int = 4) -> DataFrame:
    """(a, b) of users active with one event type in one window, from a stream or a table: a watermark bounds the state.
    Users are told apart once per window; of a pair of sides one is dealt over salts, so that a busy window is several tasks."""
    rows = events.withColumn("at", F.col("ts").cast("timestamp"))
    if events.isStreaming:
        rows = rows.withWatermark("at", late)
    seen = rows.select(F.window("at", size).alias("w"), "event_type", "user_id").select("w", "event_type", "user_id").dropDuplicates(["w", "event_type", "user_id"])
    a = seen.select("w", "event_type", F.col("user_id").alias("a")).withColumn("salt", F.pmod(F.xxhash64("a"), F.lit(salts)).cast("int"))
    b = seen.select("w", "event_type", F.col("user_id").alias("b")).withColumn("salt", F.explode(F.sequence(F.lit(0), F.lit(salts - 1))))
    return a.join(b, ["w", "event_type", "salt"]).filter("a < b").select("a", "b")


def dropped_late(query) -> int:
    """Rows that a streaming query has dropped as too late, by its own progress reports."""
    return sum(int(s.get("numRowsDroppedByWatermark") or 0) for p in query.recentProgress for s in p["stateOperators"])


def delta_match(old: LabeledGraph, delta: DataFrame, p: PatternGraph) -> DataFrame:
    """m1..mn of the embeddings in old and delta together that use a new edge, each once.

    delta: (a, b) of new undirected edges. The first pattern edge (in the pattern's order of edges) that
    lies on a new edge is the seed: edges before it must be old, edges after it may be either."""
    once = delta.select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).filter("a <> b").distinct()
    fresh = LabeledGraph.from_edges(old.vertices, once).edges.join(old.edges.select("src", "dst"), ["src", "dst"], "left_anti").select("src", "dst", "src_label", "dst_label")
    both = old.edges.unionByName(fresh)
    out = None
    for i in range(len(p.edges)):
        part = _seeded(old, fresh, both, p, i)
        out = part if out is None else out.unionByName(part)
    if out is None:
        return old.vertices.sparkSession.createDataFrame([], ", ".join(f"m{i} bigint" for i in range(1, p.n + 1)))
    return out


def _seeded(old: LabeledGraph, fresh: DataFrame, both: DataFrame, p: PatternGraph, seed: int) -> DataFrame:
    def edges(i: int, a: int, b: int) -> DataFrame:
        rows = fresh if i == seed else old.edges if i < seed else both
        return rows.filter((F.col("src_label") == p.labels[a - 1]) & (F.col("dst_label") == p.labels[b - 1])).select(F.col("src").alias(f"m{a}"), F.col("dst").alias(f"m{b}"))

    a, b = p.edges[seed]
    out, done, todo = edges(seed, a, b), [a, b], [i for i in range(len(p.edges)) if i != seed]
    while todo:
        i = next((i for i in todo if set(p.edges[i]) <= set(done)), None)
        if i is None:
            i = next((i for i in todo if set(p.edges[i]) & set(done)), None)
        if i is None:
            i = todo[0]
        x, y = p.edges[i]
        known = [u for u in (x, y) if u in done]
        if len(known) == 2:
            out = out.join(edges(i, x, y), [f"m{x}", f"m{y}"], "left_semi")
        else:
            new = [u for u in (x, y) if u not in done]
            out = out.join(edges(i, x, y), [f"m{u}" for u in known]) if known else out.crossJoin(edges(i, x, y))
            for u in new:
                for w in done:
                    if p.labels[w - 1] == p.labels[u - 1]:
                        out = out.filter(F.col(f"m{w}") != F.col(f"m{u}"))
                done.append(u)
        todo.remove(i)
    for u in range(1, p.n + 1):
        if u not in done:
            out = out.crossJoin(old.vertices.filter(F.col("label") == p.labels[u - 1]).select(F.col("vid").alias(f"m{u}")))
            for w in done:
                if p.labels[w - 1] == p.labels[u - 1]:
                    out = out.filter(F.col(f"m{w}") != F.col(f"m{u}"))
            done.append(u)
    return out.select(*(f"m{i}" for i in range(1, p.n + 1)))


def run_continuous(pairs: DataFrame, vertices: DataFrame, p: PatternGraph, edges_path: str, sink: Callable[[DataFrame, int], None], checkpoint: str):
    """A stream of (a, b): each micro-batch matches what its edges add to the stored graph, hands it to the sink, and then stores the edges under its own batch number."""

    def step(batch: DataFrame, number: int) -> None:
        spark = batch.sparkSession
        stored = spark.read.schema("a bigint, b bigint, batch bigint").parquet(edges_path).filter(F.col("batch") < number).select("a", "b")
        batch = batch.select(F.col("a").cast("bigint").alias("a"), F.col("b").cast("bigint").alias("b"))
        sink(delta_match(LabeledGraph.from_edges(vertices, stored), batch, p), number)
        batch.withColumn("batch", F.lit(number).cast("bigint")).write.mode("append").parquet(edges_path)

    spark = vertices.sparkSession
    spark.createDataFrame([], "a bigint, b bigint, batch bigint").write.mode("append").parquet(edges_path)
    return pairs.writeStream.foreachBatch(step).option("checkpointLocation", checkpoint).outputMode("append").start()
