"""Connected components by alternating star contractions, as DataFrame joins and aggregates."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from incwalk.llm.common import discard, save


def connected_components(edges: DataFrame, a: str = "a", b: str = "b") -> DataFrame:
    """``(node, component)`` for every node with an edge; component is the smallest node reachable.

    Every round hangs each node's larger neighbours on its smallest neighbour, then each node and
    its smaller neighbours on the smallest of them, and stops when the edge set no longer changes.
    Rounds are logarithmic in practice. Partial minima keep a hub's edges from meeting in one task,
    and the joins back are plain shuffle joins that AQE can split. Edge sets go through the shared
    folder, so a lost executor costs one round at most. Nulls and self-loops are ignored; an empty
    input gives an empty result.
    """
    low, high = F.least(a, b), F.greatest(a, b)
    e = save(edges.where(F.col(a) != F.col(b)).select(high.alias("u"), low.alias("v")).distinct(), "cc")
    before = None
    while True:
        both = e.union(e.select(F.col("v").alias("u"), F.col("u").alias("v")))
        least = both.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m"))
        large = both.join(least, "u").where(F.col("v") > F.col("u")).select(F.col("v").alias("u"), F.col("m").alias("v")).distinct()
        floor = large.groupBy("u").agg(F.min("v").alias("m"))
        small = large.join(floor, "u").where(F.col("v") != F.col("m")).select(F.col("v").alias("u"), F.col("m").alias("v")).union(floor.select("u", F.col("m").alias("v"))).distinct()
        done, e = e, save(small, "cc")
        discard(done)
        now = e.agg(F.count("*"), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first()
        if now == before:
            break
        before = now
    return e.select(F.col("u").alias("node"), F.col("v").alias("component")).union(e.select(F.col("v").alias("node"), F.col("v").alias("component")).distinct())
