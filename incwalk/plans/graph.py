"""Slot tables: out-edge i of a node sits at slot i, so a random edge is an equi-join on ``(src, slot)`` and a hub's edges spread over partitions."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

SALTS = 64


def slots(edges: DataFrame) -> DataFrame:
    """``(src, slot, dst, ord)`` in the order of arrival, ties by target."""
    w = Window.partitionBy("src").orderBy("ord", "dst")
    return edges.select("src", (F.row_number().over(w) - 1).cast("long").alias("slot"), "dst", "ord")


def salted_slots(edges: DataFrame, salts: int = SALTS) -> DataFrame:
    """A valid numbering in which no task sorts a whole hub: numbers inside salts, offset by the salts before."""
    e = edges.withColumn("salt", F.pmod(F.xxhash64("dst"), F.lit(salts)))
    sizes = e.groupBy("src", "salt").count()
    before = Window.partitionBy("src").orderBy("salt").rowsBetween(Window.unboundedPreceding, -1)
    offset = sizes.withColumn("offset", F.coalesce(F.sum("count").over(before), F.lit(0))).drop("count")
    own = Window.partitionBy("src", "salt").orderBy("dst")
    return e.join(offset, ["src", "salt"]).select("src", (F.col("offset") + F.row_number().over(own) - 1).cast("long").alias("slot"), "dst", "ord")


def numbered_within(rows: DataFrame, keys: list[str], first: str, order: list[str], salt: str | None = None, salts: int = SALTS) -> DataFrame:
    """Adds ``slot``, from 0 within ``keys``: by ``first``, then by ``order``; or, with ``salt``, by that column's digest, so that no task sorts all rows of a hot key."""
    if salt is None:
        return rows.withColumn("slot", (F.row_number().over(Window.partitionBy(*keys).orderBy(first, *order)) - 1).cast("long"))
    x = rows.withColumn("__salt", F.pmod(F.xxhash64(salt), F.lit(salts)))
    before = Window.partitionBy(*keys).orderBy(first, "__salt").rowsBetween(Window.unboundedPreceding, -1)
    offset = x.groupBy(*keys, first, "__salt").count().withColumn("__offset", F.coalesce(F.sum("count").over(before), F.lit(0))).drop("count")
    inside = F.row_number().over(Window.partitionBy(*keys, first, "__salt").orderBy(*order)) - 1
    return x.join(offset, [*keys, first, "__salt"]).withColumn("slot", (F.col("__offset") + inside).cast("long")).drop("__salt", "__offset")


def reverse(edges: DataFrame) -> DataFrame:
    return edges.select(F.col("dst").alias("src"), F.col("src").alias("dst"), *(c for c in edges.columns if c not in ("src", "dst")))


def nodes(edges: DataFrame) -> DataFrame:
    return edges.select(F.col("src").alias("node")).union(edges.select("dst")).distinct()


def degrees(edges: DataFrame) -> DataFrame:
    """``(node, outdeg, indeg)``: one aggregate over both ends of every edge."""
    ends = edges.select(F.explode(F.array(F.struct(F.col("src").alias("node"), F.lit(1).alias("o")), F.struct(F.col("dst").alias("node"), F.lit(0).alias("o")))).alias("x")).select("x.node", "x.o")
    return ends.groupBy("node").agg(F.sum("o").alias("outdeg"), F.sum(1 - F.col("o")).alias("indeg"))


def outdegrees(edges: DataFrame) -> DataFrame:
    return edges.groupBy("src").agg(F.count("*").alias("deg"))
