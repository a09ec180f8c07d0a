"""Names of all graph queries and of the SQL that checks them."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from incwalk.operators import baseline_queries, measure_queries, snapshot_queries, stream_queries, surface_queries, table_queries, walk_queries
from incwalk.plans import exact
from incwalk.sources.graphs import edges

_MODULES = (walk_queries, measure_queries, baseline_queries, table_queries, stream_queries, snapshot_queries, surface_queries)


def queries() -> dict:
    return {k: f for m in _MODULES for k, f in m.R.queries.items()}


def oracle_sql() -> dict[str, str]:
    return {k: q for m in _MODULES for k, q in m.R.sql.items()}


def flagship(spark, sf_dir) -> DataFrame:
    counts = walk_queries.pagerank_counts(spark, sf_dir)
    truth = exact.power_iteration(edges(spark, sf_dir, "cobuy").select("src", "dst", "ord"), rounds=20)
    return counts.join(truth.select("node", F.col("score").alias("exact")), "node").orderBy(F.desc("score"), "node").limit(20)
