"""Known links are left out alike with the seeds given, and only the edges of seeds meet the scores then."""

from incwalk.plans import personal


def test_only_edges_of_seeds_are_shuffled(spark):
    e = spark.createDataFrame([(a, b, 0) for a in range(6) for b in range(8) if (a * b) % 3 and a != b], "src long, dst long, ord long")
    scores = spark.createDataFrame([(a, b, 1.0) for a in (1, 4) for b in range(9)], "seed long, node long, score double")
    seeds = spark.createDataFrame([(1,), (4,)], "seed long")
    few = personal.exclude_known(scores, e, seeds)
    assert sorted(map(tuple, few.collect())) == sorted(map(tuple, personal.exclude_known(scores, e).collect()))
    plan = few._jdf.queryExecution().optimizedPlan().toString()
    assert "LeftAnti" in plan and "LeftSemi" in plan and "strategy=broadcast" in plan
