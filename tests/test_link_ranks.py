"""Ranks of later links: seeds that advance together as columns give those of the joins."""

import numpy as np
import pytest

from incwalk.operators import measure_queries as M
from incwalk.plans import dense, exact
from incwalk.plans.dense import Numbered, Part, connected

# two parts; 4 and 5 tie, 7 and 105 have no edge out, 8 none in
ROWS = [(0, 1), (1, 0), (1, 2), (2, 0), (0, 2), (2, 4), (2, 5), (4, 0), (5, 0), (2, 7), (8, 0), (4, 7), (1, 7), (100, 101), (101, 102), (102, 100), (100, 105), (102, 101)]


@pytest.fixture(scope="module")
def e(spark):
    return spark.createDataFrame([(a, b, i) for i, (a, b) in enumerate(ROWS)], "src long, dst long, ord long")


def test_parts(e):
    g = Numbered(e)
    part = g.nodes[connected(g)]
    assert dict(zip(g.nodes.tolist(), part.tolist(), strict=True)) == {n: 0 if n < 100 else 100 for n in (0, 1, 2, 4, 5, 7, 8, 100, 101, 102, 105)}


def test_sums_over_rows_of_any_length(spark, monkeypatch):
    rng = np.random.default_rng(1)
    pairs = {(int(a), int(b)) for a, b in zip(rng.integers(0, 40, 300), rng.integers(0, 60, 300), strict=True)} | {(3, b) for b in range(60)}
    g = Numbered(spark.createDataFrame([(a, b, 0) for a, b in pairs], "src long, dst long, ord long"))
    monkeypatch.setattr(dense, "LONG_ROW", 20)
    monkeypatch.setattr(dense, "ROWS", 8)
    part, x = Part(g, np.arange(len(g.nodes))), rng.random((len(g.nodes), 3))
    for many, one in ((part.forward, g.forward), (part.back, g.back)):
        assert np.allclose(many(x)[0], np.stack([one(x[:, j]) for j in range(3)], axis=1), atol=1e-12)
        few = np.where(np.arange(len(x))[:, None] == 3, x, 0)
        assert np.allclose(many(few, np.array([3]))[0].copy(), many(few)[0])


@pytest.mark.parametrize("most", [3])
def test_ranks_are_those_of_the_joins(spark, most, monkeypatch):
    rng = np.random.default_rng(4)
    pairs = {(a + part, b + part) for part in (0, 100) for a, b in rng.integers(0, (20, 26), (90, 2)).tolist() if a != b}  # 20 to 25 have no edge out
    e = spark.createDataFrame([(a, b, 0) for a, b in sorted(pairs)], "src long, dst long, ord long")
    monkeypatch.setattr(M, "LINKS", 2)
    monkeypatch.setattr(dense, "TOGETHER", 2)
    seeds = spark.createDataFrame([(0,), (1,), (8,), (100,), (101,)], "seed long")
    nodes = exact.G.nodes(e)
    later = seeds.crossJoin(nodes)
    popular = e.groupBy("dst").count().withColumnRenamed("count", "links").where("links >= 2")
    got = {k: {tuple(r) for r in x.select("seed", "node", "rank").collect()} for k, x in M._ranks_together(e, later, seeds, 2, most, popular).items()}
    monkeypatch.setattr(dense, "DENSE_EDGES", 0)
    asked = {k: {tuple(r) for r in x.select("seed", "node", "rank").collect()} for k, x in M._ranks_joined(e, later, seeds, 2, most, popular).items()}
    assert got == asked and all(asked.values())
