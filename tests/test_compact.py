"""Graphs and stores that Spark sorts for a broadcast, and what tasks count by themselves, against the joins."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from incwalk.operators import measure_queries as M
from incwalk.plans import exact, personal, walks
from incwalk.plans.walks import Adjacency, Spec, build_store, dealt, on_broadcast

ROWS = [(0, 1, 1), (1, 0, 2), (1, 2, 3), (2, 0, 4), (0, 2, 5), (2, 7, 6), (8, 0, 7), (0, 7, 3), (7, 2, 1)]  # 8 has no edge in


@pytest.fixture(scope="module")
def e(spark):
    return spark.createDataFrame(ROWS, "src long, dst long, ord long")


def _rows(df):
    return sorted(map(tuple, df.collect()), key=repr)


def test_spark_sorts_as_the_driver_does(spark, e):
    one, other = Adjacency(e, True), Adjacency(e, True, count=walks.LOCAL_EDGES + 1)
    assert one.nodes.tolist() == other.nodes.tolist() == [0, 1, 2, 7, 8]
    for way in ("hub", "auth"):
        assert all(np.array_equal(a, b) for a, b in zip(one.ways[way], other.ways[way], strict=True))
    assert one.degree(0) == 3 and [one.target(0, i) for i in range(3)] == [1, 7, 2] and one.degree(99) == 0


def test_graphs_beyond_four_million_edges_are_broadcast(spark):
    assert on_broadcast(None, Spec(), 10_948_411) and not on_broadcast(None, Spec(), 40_000_001)
    assert not on_broadcast(None, Spec(engine="rounds"), 10)


def test_few_rows_of_much_work_are_many_tasks(spark):
    assert dealt(spark.range(100).toDF("seed"), "seed").mapInArrow(lambda x: x, "seed long").rdd.getNumPartitions() >= 12


@pytest.mark.parametrize(("policy", "kind"), [("lazy", "alternating"), ("once", "pagerank"), ("literal", "pagerank")])
def test_stored_segments_by_either_sort(spark, e, policy, kind, monkeypatch):
    spec = Spec(reps=3, kind=kind)
    visits, g = build_store(e, spec), Adjacency(e, kind == "alternating")
    one = personal.Stored(visits, spec, policy, g)
    monkeypatch.setattr(personal, "LOCAL_VISITS", 0)
    other = personal.Stored(visits, spec, policy, g)
    assert all(np.array_equal(getattr(one, c), getattr(other, c)) for c in ("flat", "place", "many", "first"))


@pytest.mark.parametrize("kind", ["pagerank", "alternating"])
def test_counts_and_ledgers_are_those_of_the_joins(spark, e, kind):
    seeds, got = spark.createDataFrame([(0,), (1,)], "seed long"), []
    for engine in ("local", "rounds"):
        spec = Spec(reps=2, eps=0.6, kind=kind, engine=engine)
        visits = build_store(e, spec)
        got.append((_rows(personal.visit_counts(visits, e, seeds, 12, spec)), _rows(personal.prefix_ledger(visits, e, seeds, (3, 9, 12), spec))))
    assert got[0] == got[1] and sum(r[3] for r in got[0][0]) == 24


def test_short_walks(spark, e):
    starts = spark.createDataFrame([(0, "0:0"), (0, "0:1"), (8, "8:0"), (7, "7:0")], "seed long, id string")
    count = lambda spec: _rows(M._short_walks(starts, e, 6, spec).groupBy("id", "seed", "node").count())
    assert count(Spec(seed=17)) == count(Spec(seed=17, engine="rounds"))


def test_best_rows_are_those_of_all(spark, e):
    seeds = spark.createDataFrame([(0,), (8,), (99,)], "seed long")
    for run, by in ((exact.power_iteration, "score"), (exact.alternating_iteration, "auth")):
        top = lambda x, by=by: [(r[0], r[1], pytest.approx(r[2])) for r in _rows(personal.top(x.where(F.col(by) > 0), 2, by).select("seed", "node", by))]
        assert top(run(e, rounds=3, seeds=seeds, best=2)) == top(run(e, rounds=3, seeds=seeds))


def test_a_query_sorts_its_graph_once(spark, e, monkeypatch):
    made, was, edges = [], walks.Adjacency.__init__, e.select("*")
    monkeypatch.setattr(walks.Adjacency, "__init__", lambda self, *a, **k: (made.append(1), was(self, *a, **k))[1])
    spec, seeds = Spec(reps=2, eps=0.6, kind="alternating"), spark.createDataFrame([(0,), (1,)], "seed long")
    exact.alternating_iteration(edges, rounds=2, seeds=seeds).count()
    assert personal.visit_counts(build_store(edges, spec), edges, seeds, 12, spec).agg(F.sum("visits")).first()[0] == 24
    assert len(made) == 1


def test_stores_beyond_forty_million_visits_are_broadcast(spark):
    assert personal._on_arrays(spark.range(44_410_886), spark.range(35_961_060), Spec(kind="alternating"))
