"""SQL functions: match_pattern over edges that a query deals to it, and the bits of a reason."""

from __future__ import annotations

from pyspark.sql import SparkSession
from pyspark.sql.functions import udtf

from branchwise.plans.pattern import PatternGraph

from .kernel import search_unit


@udtf(returnType="asg array<bigint>")
class MatchPattern:
    """TABLE(edges) with src, dst, src_label, dst_label and a pattern text; matches inside each partition of the table."""

    def __init__(self):
        self.adjacency, self.label, self.pattern = {}, {}, None

    def eval(self, row, pattern: str):
        self.pattern = pattern
        for a, b, x in ((row["src"], row["dst"], row["src_label"]), (row["dst"], row["src"], row["dst_label"])):
            self.adjacency.setdefault(a, set()).add(b)
            self.label[a] = x

    def terminate(self):
        if self.pattern is not None:
            p = PatternGraph.from_text(self.pattern)
            domains = [sorted(v for v, x in self.label.items() if x == y) for y in p.labels]
            for found in search_unit(p.nbr_mask(), domains, self.adjacency).rows:
                yield (list(found),)


@udtf(returnType="pos int")
class PatternReasonBits:
    def eval(self, reason: int):
        for i in range(63):
            if reason >> i & 1:
                yield (i + 1,)


def register(spark: SparkSession) -> None:
    spark.udtf.register("match_pattern", MatchPattern)
    spark.udtf.register("pattern_reason_bits", PatternReasonBits)
