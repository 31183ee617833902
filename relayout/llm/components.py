"""Connected components by large-star and small-star: each round is two aggregations and joins over the edges."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from relayout.llm.shared import materialise


def _toward_least(pairs: DataFrame) -> DataFrame:
    """(u, v), each u linked to all its v: every v and u itself to the least of them."""
    least = pairs.groupBy("u").agg(F.min("v").alias("m"))
    return pairs.join(least.select("u", F.least("u", "m").alias("m")), "u").select(F.col("v").alias("u"), F.col("m").alias("v"))


def components(edges: DataFrame) -> DataFrame:
    """(node, component): of each node that an edge (u, v) names, the least node that it reaches.

    Edges may be repeated, lie in either order, or be loops (a node alone). Nothing reaches the driver but two sums a
    round; the number of rounds grows with the logarithm of the longest chain."""
    ends = edges.select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v")).distinct()
    now = materialise(ends, "edges")
    before = None
    while True:
        state = now.agg(F.count(F.lit(1)), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first()
        if state == before:
            return now.select(F.col("u").alias("node"), F.col("v").alias("component")).union(now.select(F.col("v").alias("node"), F.col("v").alias("component"))).distinct()
        before = state
        both = now.union(now.select(F.col("v").alias("u"), F.col("u").alias("v")))
        large = _toward_least(both.filter("u <> v"))
        large = large.union(now.filter("u = v").select("u", "v"))
        large = large.select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v")).distinct()
        small = _toward_least(large)
        least = large.groupBy("u").agg(F.min("v").alias("v"))
        now = materialise(small.union(least).select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v")).distinct(), "edges")
