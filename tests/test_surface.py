"""The facade, its views, the data source, the aggregate, walks by scans, and plans that must stay as they are."""

import pytest
from pyspark.sql import functions as F

from incwalk.engine import Engine
from incwalk.functions.tables import _gini
from incwalk.operators import surface_queries, table_queries
from incwalk.plans import exact
from incwalk.plans.scans import scan_walks
from incwalk.plans.walks import Spec, segments

SMALL = "/root/testdata/sf0.001"
TRI = [(0, 1, 1), (1, 0, 2), (1, 2, 3), (2, 0, 4), (0, 2, 5)]


@pytest.fixture(scope="module")
def tri(spark):
    return spark.createDataFrame(TRI, "src long, dst long, ord long")


def _plan(df):
    return df._jdf.queryExecution().executedPlan().toString()


def test_engine_views_follow_updates(spark, tri):
    engine = Engine(spark)
    store = engine.edges("tri", tri).store(reps=300)
    assert {r["slot"] for r in spark.sql("SELECT slot FROM adj_tri WHERE src = 1").collect()} == {0, 1}
    assert {r["node"]: r["score"] for r in store.pagerank().collect()}[0] == pytest.approx(0.4286, abs=0.06)
    store.update(spark.createDataFrame([("+", 2, 3, 6)], "op string, src long, dst long, ord long"))
    assert spark.sql("SELECT count(*) AS n FROM edges_tri").first()["n"] == 6
    steps = spark.sql("SELECT s.node, s.next FROM segments_tri, LATERAL segment_steps(path) s WHERE s.next IS NOT NULL").distinct()
    assert {tuple(r) for r in steps.collect()} == {(a, b) for a, b, _ in TRI} | {(2, 3)}
    top = store.topk(spark.createDataFrame([(0,)], "seed long"), 2, alpha=0.75).collect()
    assert [r["rank"] for r in top] == [1, 2] and top[0]["node"] == 0
    with pytest.raises(ValueError):
        engine.edges("no name", tri)


def test_data_source_draws_the_same_in_any_partitions(spark):
    Engine(spark)
    read = lambda parts: sorted(map(tuple, spark.read.format("coin_edges").option("nodes", 50).option("edges", 700).option("partitions", parts).load().collect()))
    assert read(1) == read(5) and len(read(1)) == 700
    assert all(0 <= a < 50 and 0 <= b < 50 for a, b, _ in read(1))


def test_gini():
    import pandas as pd

    assert _gini(pd.Series([3]), pd.Series([10])) == pytest.approx(0)
    assert _gini(pd.Series([1, 0]), pd.Series([1, 3])) == pytest.approx(0.75)


def test_scans_keep_the_law(spark, tri):
    visits, ledger = scan_walks(tri, Spec(reps=600), short=3)
    share = {r["node"]: r["count"] * 0.2 / 1800 for r in visits.groupBy("node").count().collect()}
    truth = {r["node"]: r["score"] for r in exact.power_iteration(tri, rounds=40).collect()}
    assert all(share[k] == pytest.approx(truth[k], abs=0.03) for k in truth)
    paths = segments(visits.withColumn("role", F.lit("hub"))).collect()
    assert len(paths) == 1800 and all(r["ended"] == "reset" for r in paths)
    edges = {(a, b) for a, b, _ in TRI}
    assert all((a, b) in edges for r in paths for a, b in zip(r["path"], r["path"][1:], strict=False))
    row = ledger.first()
    assert row["single_scans"] > 0 and row["segments_used"] <= row["segments_made"] and row["hop_rounds"] < row["longest"]


def test_scan_pushes_filters_and_prunes_columns(spark):
    plan = _plan(table_queries.R.queries["scan_orders_cols"](spark, SMALL))
    assert "GreaterThan(o_totalprice" in plan
    assert plan.split("ReadSchema: ")[1].split(">")[0].count(":") == 3


def test_bucketed_join_moves_no_row(spark):
    plan = _plan(surface_queries.bucketed(spark, SMALL))
    assert "SortMergeJoin" in plan and "Exchange" not in plan


def test_faster_iterations_reach_the_scores(spark, tri):
    truth = {r["node"]: r["score"] for r in exact.power_iteration(tri, rounds=60).collect()}
    gap = lambda x: sum(abs(r["score"] - truth[r["node"]]) for r in x.collect())
    assert gap(exact.aitken(tri, rounds=8)) < gap(exact.power_iteration(tri, rounds=8)) + 1e-6
    old = exact.power_iteration(tri.where("ord < 5"), rounds=40).select("node", "score")
    new = exact.lumped_update(tri, old, spark.createDataFrame([(0,)], "node long"), hops=2, rounds=40)
    assert gap(new) < gap(old) and gap(new) < 1e-3
