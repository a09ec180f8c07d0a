"""Errors by R are read off one store."""

from incwalk.operators import measure_queries as M
from incwalk.plans.walks import Spec, build_store


def test_one_store_for_all_r(spark, monkeypatch):
    e = spark.createDataFrame([(0, 1, 1), (1, 0, 2), (1, 2, 3), (2, 0, 4), (0, 2, 5), (2, 7, 6), (8, 0, 7)], "src long, dst long, ord long")
    built = []
    monkeypatch.setattr(M, "_e", lambda *_: e)
    monkeypatch.setattr(M, "build_store", lambda edges, spec: (built.append(spec.reps), build_store(edges, spec))[1])
    rows = {r["r"]: r for r in M.exp_w16(spark, "", reps=(1, 3)).collect()}
    assert built == [3]
    truth = {r["node"]: r["score"] for r in M.exact.power_iteration(e, rounds=25).collect()}
    for r in (1, 3):
        seen = {x["node"]: x["count"] for x in build_store(e, Spec(reps=r, seed=16)).groupBy("node").count().collect()}
        assert rows[r]["l1"] == round(sum(abs(seen.get(k, 0) * 0.2 / (5 * r) - t) for k, t in truth.items()), 9)
