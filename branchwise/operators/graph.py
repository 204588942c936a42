"""Labelled graphs as two DataFrames, and helpers over them."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .storage import settled


class GraphSchemaError(ValueError):
    pass


class LabeledGraph:
    """vertices (vid, label, and attributes if there are any); edges (src, dst, src_label, dst_label) in both directions,
    distinct, without loops; loops (vid), the vertices with an edge to themselves, or None where there are none."""

    def __init__(self, vertices: DataFrame, edges: DataFrame, loops: DataFrame | None = None):
        self.vertices, self.edges, self.loops = vertices, edges, loops

    @classmethod
    def from_edges(cls, vertices: DataFrame, pairs: DataFrame, validate: bool = False, loops: bool = False) -> LabeledGraph:
        """pairs (a, b): one row per undirected edge or more, in any direction. Further columns of vertices stay as
        attributes. loops: keep edges from a vertex to itself (in a table of their own); else they are dropped."""
        further = [c for c in vertices.columns if c not in ("vid", "label")]
        vertices = vertices.select(F.col("vid").cast("bigint").alias("vid"), F.col("label").cast("string").alias("label"), *further)
        # Dealt by one end before anything else: what is distinct and the first label need no further exchange, and both labels are
        # found while an edge is one row.
        once = pairs.filter("a <> b").select(F.least("a", "b").cast("bigint").alias("a"), F.greatest("a", "b").cast("bigint").alias("b")).repartition("a").distinct()
        named = lambda side: vertices.select(F.col("vid").alias(side), F.col("label").alias(f"{side}_label"))
        one = once.join(named("a"), "a").join(named("b"), "b")
        turned = lambda a, b: F.struct(F.col(a).alias("src"), F.col(b).alias("dst"), F.col(f"{a}_label").alias("src_label"), F.col(f"{b}_label").alias("dst_label"))
        both = one.select(F.explode(F.array(turned("a", "b"), turned("b", "a"))).alias("e")).select("e.*")
        if validate:
            cls._validate(vertices, pairs)
        selves = pairs.filter("a = b").select(F.col("a").cast("bigint").alias("vid")).distinct() if loops else None
        return cls(vertices, both, selves)

    def settled(self, name: str = "graph") -> LabeledGraph:
        """The same graph from storage: labelled edges in ranges of label pair and source, so that the scan of a pattern edge
        skips files and row groups by their statistics, and a frequent pair is several files."""
        keys = ("src_label", "dst_label", "src")
        edges = settled(self.edges.repartitionByRange(*keys).sortWithinPartitions(*keys, "dst"), f"{name}-edges")
        vertices = settled(self.vertices.repartitionByRange("label", "vid").sortWithinPartitions("label", "vid"), f"{name}-vertices")
        return LabeledGraph(vertices, edges, None if self.loops is None else settled(self.loops, f"{name}-loops"))

    def write_adjacency(self, table: str, buckets: int) -> None:
        """The edges as a table bucketed and sorted by source: joins on the source with another such table move nothing."""
        self.edges.write.bucketBy(buckets, "src").sortBy("src", "dst").mode("overwrite").saveAsTable(table)

    @staticmethod
    def _validate(vertices: DataFrame, pairs: DataFrame) -> None:
        nulls, rows, ids = vertices.agg(F.count_if(F.col("vid").isNull() | F.col("label").isNull()), F.count(F.lit(1)), F.count_distinct("vid")).first()
        if nulls or rows - nulls != ids:
            raise GraphSchemaError(f"vertices: {nulls} rows with nulls, {rows} rows for {ids} ids")
        ends = pairs.select(F.explode(F.array("a", "b")).alias("vid"))
        if not ends.filter("vid IS NULL").isEmpty() or not ends.join(vertices, "vid", "left_anti").isEmpty():
            raise GraphSchemaError("edges end in a null or in an unknown vertex")

    def degrees(self) -> DataFrame:
        return self.edges.groupBy(F.col("src").alias("vid")).agg(F.count(F.lit(1)).alias("deg"))

    def statistics(self, labels: set[str]) -> tuple[dict[str, int], dict[tuple[str, str], int]]:
        """Vertices by label and edges by label pair, for the given labels (those of a pattern, so the answer is small). Kept with the graph."""
        held = self.__dict__.setdefault("_statistics", {})
        new = sorted(labels - held.keys())
        if new:
            for x in new:
                held[x] = (0, {})
            for r in self.vertices.filter(F.col("label").isin(new)).groupBy("label").count().collect():
                held[r["label"]] = (r["count"], held[r["label"]][1])
            known = sorted(held)
            pairs = self.edges.filter((F.col("src_label").isin(new) & F.col("dst_label").isin(known)) | (F.col("src_label").isin(known) & F.col("dst_label").isin(new)))
            for r in pairs.groupBy("src_label", "dst_label").count().collect():
                held[r.src_label][1][r.dst_label] = r["count"]
        return {x: held[x][0] for x in labels}, {(x, y): held[x][1].get(y, 0) for x in labels for y in labels}

    def label_counts(self) -> DataFrame:
        return self.vertices.groupBy("label").agg(F.count(F.lit(1)).alias("n"))

    def label_pair_counts(self) -> DataFrame:
        return self.edges.groupBy("src_label", "dst_label").agg(F.count(F.lit(1)).alias("n"))

    def adjacency(self, max_list: int = 1 << 16) -> DataFrame:
        """Packed neighbours; a hub is several chunks, so that no row outgrows max_list."""
        chunks = self.degrees().select(F.col("vid").alias("src"), "deg", F.ceil(F.col("deg") / max_list).alias("chunks"))
        cut = self.edges.join(chunks, "src").withColumn("chunk", F.pmod(F.xxhash64("dst"), "chunks"))
        return cut.groupBy(F.col("src").alias("vid"), "chunk", "deg").agg(F.array_sort(F.collect_list("dst")).alias("nbrs"))

    def neighbors(self, vids: DataFrame) -> DataFrame:
        return self.edges.join(vids.select(F.col("vid").alias("src")), "src", "left_semi").select(F.col("dst").alias("vid")).distinct()

    def induced_subgraph(self, vids: DataFrame) -> LabeledGraph:
        keep = vids.select("vid").distinct()
        ends = lambda side: keep.select(F.col("vid").alias(side))
        loops = None if self.loops is None else self.loops.join(keep, "vid", "left_semi")
        return LabeledGraph(self.vertices.join(keep, "vid", "left_semi"), self.edges.join(ends("src"), "src", "left_semi").join(ends("dst"), "dst", "left_semi"), loops)

    def ego(self, vids: DataFrame, hops: int = 1) -> LabeledGraph:
        seen = vids.select("vid").distinct()
        for _ in range(hops):
            seen = seen.union(self.neighbors(seen)).distinct()
        return self.induced_subgraph(seen)

    def stats(self) -> DataFrame:
        v = self.vertices.agg(F.count(F.lit(1)).alias("n_vertices"), F.count_distinct("label").alias("n_labels"))
        e = self.degrees().agg(F.coalesce((F.sum("deg") / 2).cast("bigint"), F.lit(0)).alias("n_edges"), F.coalesce(F.max("deg"), F.lit(0)).alias("max_degree"))
        return v.join(e)  # one row beside one row
