"""Numbers over whole frames without sending the frame through one task."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from incwalk.store import save


def numbered(df: DataFrame, order: list[Column], name: str = "rank") -> DataFrame:
    """Adds ``name``, 1 upwards in ``order`` (a total one): rows are split by ranges of the order, numbered inside them, and offset by the sizes of the ranges before.

    Only the table of range sizes, a row per shuffle partition, passes through a single window.
    """
    parts = int(df.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    x = save(df.repartitionByRange(parts, *order).withColumn("__range", F.spark_partition_id()), "ranges")
    before = Window.orderBy("__range").rowsBetween(Window.unboundedPreceding, -1)
    offset = x.groupBy("__range").agg(F.count("*").alias("__n")).select("__range", F.coalesce(F.sum("__n").over(before), F.lit(0)).alias("__before"))
    inside = F.row_number().over(Window.partitionBy("__range").orderBy(*order))
    return x.join(F.broadcast(offset), "__range").select(*df.columns, (F.col("__before") + inside).alias(name))
