"""Edges of buyers: one window by part, and the same rows by months where a part is hot."""

from incwalk.sources import graphs

SF = "/root/testdata/sf0.001"


def test_one_window_unless_a_part_is_hot(spark, monkeypatch):
    e = graphs.cobuy(spark, SF)
    plan = e._jdf.queryExecution().sparkPlan().toString()
    assert plan.count("Window [") == 1 and "trunc(" not in plan
    monkeypatch.setattr(graphs, "SORTED", 0)
    split = graphs.cobuy(spark, SF)
    assert split._jdf.queryExecution().sparkPlan().toString().count("Window [") > 1
    assert sorted(map(tuple, e.collect())) == sorted(map(tuple, split.collect()))
