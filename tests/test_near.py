"""Nearest neighbours by blocks against brute force, with large groups of equal vectors."""

import numpy as np
import pyarrow as pa

from incwalk.sources import graphs


def test_blocks_give_the_nearest_with_ties(spark, tmp_path, monkeypatch):
    monkeypatch.setattr(graphs, "NEAR_BLOCK", 40)
    monkeypatch.setattr(graphs, "NEAR_QUERIES", 7)
    rng = np.random.default_rng(3)
    vectors = [rng.normal(size=6).astype("float32").tolist() for _ in range(90)] + [[1.0, 2.0, 0.0, 0.0, 1.0, 3.0]] * 60 + [[0.0] * 6, None]
    spark.createDataFrame(list(enumerate(vectors)), "vec_id long, embedding array<float>").write.parquet(str(tmp_path / "embeddings.parquet"))
    got = {}
    for r in graphs.near(spark, str(tmp_path), k=5).collect():
        got.setdefault(r["src"], {})[r["ord"] - 5 * r["src"]] = r["dst"]
    v = np.array(vectors[:150], float)
    norm = np.sqrt((v * v).sum(1))
    for i in range(150):
        sims = [(-round(float(v[i] @ v[j] / (norm[i] * norm[j])), 12), j) for j in range(150) if j != i]
        assert got[i] == {n: j for n, (_, j) in enumerate(sorted(sims)[:5])}
    assert len(got) == 150


def test_a_group_of_copies_sends_few_rows_on():
    one = pa.table({"id": pa.array(range(500)), "v": pa.array([[1.0, 2.0]] * 500), "norm": pa.array([5**0.5] * 500)})
    assert graphs._nearest_of_block(10)(one, one).num_rows == 500 * 10
