"""Global numbering, low-rank factors, block starts and lagged values against small truths."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from incwalk.plans import exact
from incwalk.plans.factors import block_start, low_rank_scores
from incwalk.plans.ranking import numbered
from incwalk.plans.walks import Spec, build_store
from incwalk.sources.graphs import dedup, lag_over_time


def test_numbers_are_those_of_one_sort(spark):
    x = spark.range(1000).select("id", (F.col("id") % 7).alias("k"))
    got = [r["n"] for r in numbered(x, [F.desc("k"), F.asc("id")], "n").orderBy(F.desc("k"), "id").collect()]
    assert got == list(range(1, 1001))
    assert numbered(x.where("id < 0"), [F.asc("id")]).count() == 0


def test_lag_crosses_periods(spark):
    rows = [("a", 1, 10), ("a", 2, 20), ("a", 31, 30), ("a", 99, 40), ("b", 50, 50)]
    x = spark.createDataFrame(rows, "k string, t long, v long")
    got = {(r["k"], r["t"]): r["prev"] for r in lag_over_time(x, ["k"], "v", ["t"], F.floor(F.col("t") / 10)).collect()}
    assert got == {("a", 1): None, ("a", 2): 10, ("a", 31): 20, ("a", 99): 30, ("b", 50): None}


def test_low_rank_scores_reach_the_best_approximation(spark):
    a = np.zeros((6, 5))
    a[:3, :3], a[3:, 3:] = 1, 1
    a[0, 4] = 1
    e = spark.createDataFrame([(int(i), 100 + int(j)) for i, j in zip(*np.nonzero(a), strict=True)], "src long, dst long")
    seeds = spark.createDataFrame([(i,) for i in range(6)], "seed long")
    u, s, v = np.linalg.svd(a)
    want = (u[:, :2] * s[:2]) @ v[:2]
    for r in low_rank_scores(e, seeds, rank=2).collect():
        assert r["score"] == pytest.approx(want[r["seed"], r["node"] - 100], abs=0.02)


def test_block_start_helps_where_blocks_are_closed(spark):
    ring = lambda first, size: [(first + i, first + (i * i + 1) % size) for i in range(size)] + [(first + i, first) for i in range(1, size)]
    e = dedup(spark.createDataFrame([(a, b, 0) for a, b in [*ring(0, 9), *ring(100, 4), (3, 101), (102, 4)]], "src long, dst long, ord long"))
    blocks = spark.createDataFrame([(i, 1) for i in range(9)] + [(100 + i, 2) for i in range(4)], "node long, block long")
    truth = {r["node"]: r["score"] for r in exact.power_iteration(e, rounds=40).collect()}
    gap = lambda x: sum(abs(r["score"] - truth[r["node"]]) for r in x.collect())
    assert gap(exact.power_iteration(e, rounds=1, start=block_start(e, blocks))) < gap(exact.power_iteration(e, rounds=1))


def test_fast_coins_walk_over_salted_slots(spark):
    e = spark.createDataFrame([(0, 1, 1), (1, 0, 2), (1, 2, 3), (2, 0, 4), (0, 2, 5)], "src long, dst long, ord long")
    share = {r["node"]: r["count"] * 0.2 / 3000 for r in build_store(e, Spec(reps=1000, coin="fast")).groupBy("node").count().collect()}
    assert share[0] == pytest.approx(0.4286, abs=0.03) and share[1] == pytest.approx(0.2381, abs=0.03)
