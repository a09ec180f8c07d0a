"""A table function over walks and a pandas aggregate over histograms."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F


class SegmentSteps:
    """The steps of a walk given as its path: position, node, and the node after it (null at the end). A null path has none."""

    def eval(self, path):
        for i, node in enumerate(path or []):
            yield i, node, path[i + 1] if i + 1 < len(path) else None


def register(spark: SparkSession) -> None:
    """``segment_steps(path)`` for use in ``LATERAL`` joins."""
    spark.udtf.register("segment_steps", F.udtf(SegmentSteps, returnType="pos int, node long, next long"))


def _gini(value: pd.Series, times: pd.Series) -> float:
    order = value.argsort(kind="stable")
    v, k = value.iloc[order].astype(float), times.iloc[order].astype(float)
    n, total = k.sum(), (v * k).sum()
    places = k * (k.cumsum() - k) + k * (k + 1) / 2  # of all that share a value, summed
    return float(2 * (v * places).sum() / (n * total) - (n + 1) / n) if n and total else 0.0


def gini():
    """The aggregate ``(value, how often)``: Gini coefficient of a histogram; a group is a row for each distinct value."""
    return F.pandas_udf(_gini, "double")
