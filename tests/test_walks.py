"""Graphs, walk engines, updates and exact scores against small truths."""

import pytest

from incwalk.functions import theory
from incwalk.plans import exact, personal, update
from incwalk.plans import graph as G
from incwalk.plans.walks import Spec, build_store, segments
from incwalk.streaming.maintain import Maintainer

TRI = [(0, 1, 1), (1, 0, 2), (1, 2, 3), (2, 0, 4), (0, 2, 5)]


@pytest.fixture(scope="module")
def tri(spark):
    return spark.createDataFrame(TRI, "src long, dst long, ord long")


def _rows(df):
    return sorted(map(tuple, df.select("src", "rep", "pos", "node", "role", "ended").collect()), key=repr)


@pytest.mark.parametrize("kind", ["pagerank", "alternating"])
def test_engines_take_the_same_walks(tri, kind):
    one = build_store(tri, Spec(reps=5, kind=kind, engine="local"))
    assert _rows(one) == _rows(build_store(tri, Spec(reps=5, kind=kind, engine="rounds")))
    assert segments(one).count() == 3 * 5 * (2 if kind == "alternating" else 1)


def test_estimate_and_exact(tri):
    got = {r["node"]: r["score"] for r in exact.power_iteration(tri, rounds=40).collect()}
    assert got[0] == pytest.approx(0.4286, abs=1e-4) and got[1] == pytest.approx(0.2381, abs=1e-4)
    v = build_store(tri, Spec(reps=4000)).groupBy("node").count().collect()
    for r in v:
        assert r["count"] * 0.2 / (3 * 4000) == pytest.approx(got[r["node"]], abs=0.012)


def test_arrival_keeps_the_law(spark, tri):
    before = tri.where("ord < 5")
    ch = spark.createDataFrame([("+", 0, 2, 5)], "op string, src long, dst long, ord long")
    spec = Spec(reps=4000)
    store = update.WalkStore.create(before, spec)
    ledger = store.apply(ch)
    v, e = store.visits(), store.edges()
    share = {r["node"]: r["count"] * 0.2 / 12000 for r in v.groupBy("node").count().collect()}
    assert share[0] == pytest.approx(0.4286, abs=0.012) and share[1] == pytest.approx(0.2381, abs=0.012)
    assert e.count() == 5 and ledger.first()["walks_rerouted"] > 0
    edges = {(a, b) for a, b, _ in TRI}
    paths = segments(v).collect()
    assert all((a, b) in edges for r in paths for a, b in zip(r["path"], r["path"][1:], strict=False))


def test_deletion_of_last_edge_sticks(spark):
    e = spark.createDataFrame([(0, 1, 1)], "src long, dst long, ord long")
    spec = Spec(reps=50)
    ch = spark.createDataFrame([("-", 0, 1, 9), ("-", 5, 6, 9)], "op string, src long, dst long, ord long")
    store = update.WalkStore.create(e, spec)
    store.apply(ch)
    assert store.edges().count() == 0 and all(len(r["path"]) == 1 for r in segments(store.visits()).collect())


def test_maintainer_skips_repeated_batches(spark, tri):
    spec = Spec(reps=3)
    m = Maintainer(update.WalkStore.create(tri, spec))
    ch = spark.createDataFrame([("+", 2, 1, 6)], "op string, src long, dst long, ord long")
    m.on_batch(ch, 0)
    m.on_batch(ch, 0)
    assert m.store.epoch == 1 and m.store.edges().count() == 6
    other = Maintainer(update.WalkStore.open(spark, m.store.folder))  # another driver goes on
    other.on_batch(ch, 0)
    other.on_batch(spark.createDataFrame([("-", 2, 1, 7)], "op string, src long, dst long, ord long"), 1)
    assert other.store.epoch == 2 and other.store.edges().count() == 5 and update.WalkStore.open(spark, m.store.folder).epoch == 2


@pytest.mark.parametrize("policy", ["lazy", "once", "literal"])
def test_stitched_walk(tri, spark, policy):
    spec = Spec(reps=5)
    seeds = spark.createDataFrame([(0,)], "seed long")
    w = personal.stitched_walk(build_store(tri, spec), tri, seeds, 4000, spec, policy)
    share = {r["node"]: r["score"] for r in personal.frequencies(w).collect()}
    assert share[0] == pytest.approx(0.5102, abs=0.05)
    assert w.agg({"fetches": "max"}).first()[0] <= 3


@pytest.mark.parametrize(("policy", "kind"), [("lazy", "alternating"), ("once", "pagerank"), ("literal", "pagerank")])
def test_wave_engines_take_the_same_walks(tri, spark, policy, kind):
    seeds = spark.createDataFrame([(0,), (1,)], "seed long")
    got = []
    for engine in ("local", "rounds"):
        spec = Spec(reps=4, eps=0.7, kind=kind, engine=engine)
        w = personal.fetched(personal.waves(build_store(tri, spec), tri, seeds, 12, spec, policy), "edge")
        got.append(sorted(map(tuple, w.collect())))
    assert got[0] == got[1] and len(got[0]) == 24


def test_waves_agree_in_law(tri, spark):
    seeds = spark.createDataFrame([(0,)], "seed long")
    spec = Spec(reps=20)
    share = {r["node"]: r["score"] for r in personal.frequencies(personal.waves(build_store(tri, spec), tri, seeds, 3000, spec)).collect()}
    assert share[0] == pytest.approx(0.5102, abs=0.04) and share[1] == pytest.approx(0.2041, abs=0.04)


def test_closed_forms():
    assert theory.walk_length(1e8, 100, 5, 0.75) == pytest.approx(63245.55, abs=0.01)
    assert theory.topk_fetch_bound(100, 10, 5, 0.75) == pytest.approx(2001, abs=1)
    assert theory.fetch_bound(1e8, 10, 1.2, 100) is None


def test_salted_slots_are_gapless(tri):
    rows = G.salted_slots(tri).collect()
    assert sorted((r["src"], r["slot"]) for r in rows) == sorted((r["src"], r["slot"]) for r in G.slots(tri).collect())


def test_replay_applies_every_arrival(spark):
    import __spark_entry__
    from incwalk.sources.graphs import edges

    sf = "/root/testdata/sf0.001"
    m = edges(spark, sf, "handoff").count()
    rows = sorted(__spark_entry__.queries()["replay_ledger"](spark, sf).collect(), key=lambda r: r["epoch"])
    assert rows[0]["from_t"] == 0 and rows[-1]["to_t"] == m
    assert all(a["to_t"] == b["from_t"] for a, b in zip(rows, rows[1:], strict=False))
    assert sum(r["steps_redone"] for r in rows) > 0 and all(r["walks_rerouted"] >= 0 for r in rows)


@pytest.mark.parametrize("kind", ["pagerank", "alternating"])
def test_whole_history_starts_at_the_empty_graph(spark, tri, kind):
    spec = Spec(reps=2, kind=kind)
    assert update.whole_history(5) == [0, 1, 2, 3, 5] and update.whole_history(5000)[-1] == 5000 and len(update.whole_history(10**9)) == 7
    rows = update.replay(tri, spec, update.whole_history(5)).collect()
    assert [(r["from_t"], r["to_t"]) for r in sorted(rows, key=lambda r: r["epoch"])] == [(0, 1), (1, 2), (2, 3), (3, 5)]


def test_waves_reach_their_length_beside_dangling_nodes(spark):
    star = spark.createDataFrame([(0, 1, 1), (0, 2, 2), (3, 0, 3)], "src long, dst long, ord long")
    seeds = spark.createDataFrame([(0,), (1,), (3,)], "seed long")
    spec = Spec(reps=5)
    w = personal.waves(build_store(star, spec), star, seeds, 400, spec).collect()
    for s in (0, 1, 3):
        own = sorted((r["pos"], r["node"]) for r in w if r["seed"] == s)
        assert [p for p, _ in own] == list(range(400)) and own[0][1] == s
        if s == 0:
            assert sum(n == 0 for _, n in own) / 400 == pytest.approx(1 / 1.8, abs=0.06)


def test_topk_walks_grow_with_the_graph(spark):
    import __spark_entry__

    sf = "/root/testdata/sf0.001"
    rows = __spark_entry__.queries()["ppr_topk"](spark, sf).collect()
    assert len({r["seed"] for r in rows}) == 50 and len(rows) == 500
    small = spark.createDataFrame([(i, (i * j * j + j) % 60, j) for i in range(60) for j in range(1, 26) if (i * j * j + j) % 60 != i], "src long, dst long, ord long").dropDuplicates(["src", "dst"])
    more = small.unionByName(spark.range(60, 1060).selectExpr("id AS src", "id + 1 AS dst", "id AS ord"))
    seeds = spark.createDataFrame([(1, 20)], "seed long, friends long")
    assert personal.topk_length(more, seeds, 10, Spec()) > personal.topk_length(small, seeds, 10, Spec()) > 10
