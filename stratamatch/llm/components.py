"""Connected components of an edge table by alternating large-star and small-star steps.

Both steps are joins and minimum aggregates over edges, so a vertex with very
many neighbours is a skewed join key (which adaptive execution splits) and never
a group in one task's memory. Each round is written to the shared folder.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .durable import stored


def connected_components(edges: DataFrame) -> DataFrame:
    """(a, b) long edges to (node, root): root is the smallest id of the component.
    Self loops, repeated and reversed edges are allowed; null ends are left out."""
    state = stored(
        edges.where("a is not null and b is not null and a != b").select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).distinct(), "edges"
    )
    seen = None
    while True:
        both = state.unionAll(state.select(F.col("b").alias("a"), F.col("a").alias("b")))
        lowest = both.groupBy("a").agg(F.least(F.min("b"), F.col("a")).alias("m"))
        large = both.where("b > a").join(lowest, "a").select(F.col("b").alias("a"), F.col("m").alias("b"))
        large = large.where("a != b").distinct()
        lowest = large.groupBy("a").agg(F.min("b").alias("m"))
        small = large.join(lowest, "a").select(F.col("b").alias("a"), F.col("m").alias("b")).unionAll(lowest.select("a", F.col("m").alias("b")))
        state = stored(small.where("a != b").distinct(), "edges")
        now = state.agg(F.count("*"), F.bit_xor(F.xxhash64("a", "b"))).first()
        if now == seen:
            return state.select(F.col("a").alias("node"), F.col("b").alias("root")).unionAll(state.select(F.col("b").alias("node"), F.col("b").alias("root")).distinct())
        seen = now
