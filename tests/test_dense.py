"""Exact iterations on broadcast arrays give the rows of the joins; tables of passed rounds go."""

import os

import pytest

from incwalk import store
from incwalk.plans import dense, exact

ROWS = [(0, 1, 1), (1, 0, 2), (1, 2, 3), (2, 0, 4), (0, 2, 5), (2, 7, 6), (8, 0, 7)]  # 7 has no edge out, 8 none in


@pytest.fixture(scope="module")
def e(spark):
    return spark.createDataFrame(ROWS, "src long, dst long, ord long")


def _rows(df, *what):
    return {(r["seed"], r["node"]): [r[c] for c in what] for r in df.collect()}


def _same(a, b):
    assert a.keys() == b.keys()
    assert all(x == pytest.approx(y, abs=1e-12) for k in a for x, y in zip(a[k], b[k], strict=True))


@pytest.mark.parametrize("dangling", ["leak", "seed"])
@pytest.mark.parametrize("seeded", [True, False])
def test_power(spark, e, dangling, seeded):
    seeds = spark.createDataFrame([(0,), (2,), (8,), (99,)], "seed long") if seeded else None  # 99 is in no edge
    both = [exact.power_iteration(e, rounds=4, seeds=seeds, dangling=dangling, engine=x) for x in ("auto", "joins")]
    _same(*(_rows(x, "score") for x in both))


def test_weighted_jumps(spark, e):
    seeds = spark.createDataFrame([(5, 0, 0.25), (5, 7, 0.75), (6, 1, 1.0)], "seed long, node long, weight double")
    _same(*(_rows(exact.power_iteration(e, rounds=4, seeds=seeds, engine=x), "score") for x in ("auto", "joins")))


@pytest.mark.parametrize("divide", [True, False])
def test_alternating(spark, e, divide):
    seeds = spark.createDataFrame([(0,), (2,), (8,), (99,)], "seed long")
    _same(*(_rows(exact.alternating_iteration(e, rounds=4, seeds=seeds, divide=divide, engine=x), "hub", "auth") for x in ("auto", "joins")))


def test_rounds_leave_one_table_of_scores(spark, e, tmp_path, monkeypatch):
    monkeypatch.setattr(store, "scratch_root", lambda spark: str(tmp_path))
    seeds = spark.createDataFrame([(0,), (2,)], "seed long")
    exact.power_iteration(e, rounds=6, seeds=seeds, engine="joins").count()
    assert sum(name.startswith("scores-") for name in os.listdir(tmp_path / "incwalk-graph")) == 1


def test_a_write_ends_with_its_shuffles(spark, tmp_path, monkeypatch):
    seen, writer = [], type(spark.range(1).write)
    was = writer.parquet
    monkeypatch.setattr(writer, "parquet", lambda self, path: (seen.append(spark.conf.get(store.CLEANUP)), was(self, path))[1])
    before = spark.conf.get(store.CLEANUP)
    store.save(spark.range(3), "three", str(tmp_path / "three"))
    assert seen == ["true"] and spark.conf.get(store.CLEANUP) == before


def test_a_way_of_a_hundred_million_edges_is_broadcast(spark):
    rows = spark.range(43_002_387)  # edges of words on check_l
    assert dense.fits(rows) and dense.fits(rows, ways=2) and not dense.fits(spark.range(60_000_000), ways=2)
