"""Further baselines, arrival models and cost ledgers as queries."""

from __future__ import annotations

from pyspark.sql import functions as F

from incwalk.operators import measure_queries as M
from incwalk.operators import walk_queries as W
from incwalk.operators.registry_of import Registry
from incwalk.plans import exact, personal, update
from incwalk.plans import graph as G
from incwalk.plans.factors import block_start, low_rank_scores
from incwalk.plans.walks import Spec, build_store, walks_sql
from incwalk.sources.graphs import edges, edges_sql
from incwalk.store import save, table

R = Registry()
COBUY, LINKS = edges_sql("cobuy"), edges_sql("links")
_W = "WITH RECURSIVE " + walks_sql(COBUY, W.SPEC)


def _rounds(body, n):
    return ", ".join(body(i) for i in range(1, n + 1))


# dangling mass spread uniformly
_WL = f"e AS ({LINKS}), w AS (SELECT src, dst, 1 / count(*) OVER (PARTITION BY src) AS ow FROM e), n AS (SELECT src AS node FROM e UNION SELECT dst FROM e), k AS (SELECT count(*) AS k FROM n)"
_UNI = f"WITH {_WL}, x0 AS (SELECT node, 1 / (SELECT k FROM k) AS s FROM n), " + _rounds(lambda i: f"x{i} AS (SELECT node, sum(s) AS s FROM (SELECT dst AS node, s * ow * 0.8 AS s FROM x{i - 1} JOIN w ON src = node UNION ALL SELECT node, 0.2 * s FROM x0 UNION ALL SELECT node, (SELECT sum(s) * 0.8 FROM x{i - 1} ANTI JOIN (SELECT src AS node FROM e) USING (node)) / (SELECT k FROM k) FROM n) GROUP BY node)", 6)
R.add("power_iteration_uniform", lambda s, d: exact.power_iteration(W._e(s, d, "links"), rounds=6, dangling="uniform").select("node", F.round("score", 10).alias("score")), f"{_UNI} SELECT node, round(s, 10) AS score FROM x6")


# topics: nations of customers
def _topics(spark, sf_dir):
    return table(spark, sf_dir, "customer").select(F.col("c_custkey").alias("node"), F.col("c_nationkey").cast("long").alias("seed"))


def topic_power(spark, sf_dir):
    e = W._e(spark, sf_dir)
    t = _topics(spark, sf_dir).join(G.nodes(e), "node", "left_semi")
    sizes = t.groupBy("seed").agg((1 / F.count("*")).alias("weight"))
    return exact.power_iteration(e, rounds=6, seeds=save(t.join(sizes, "seed"), "topics")).select(F.col("seed").alias("topic"), "node", F.round("score", 10).alias("score"))


_TP = f"WITH e AS ({COBUY}), w AS (SELECT src, dst, 1 / count(*) OVER (PARTITION BY src) AS ow FROM e), n AS (SELECT src AS node FROM e UNION SELECT dst FROM e), x0 AS (SELECT c_nationkey AS topic, c_custkey AS node, 1 / count(*) OVER (PARTITION BY c_nationkey) AS s FROM customer SEMI JOIN n ON node = c_custkey), "
R.add("topic_power", topic_power, _TP + _rounds(lambda i: f"x{i} AS (SELECT topic, node, sum(s) AS s FROM (SELECT topic, dst AS node, s * ow * 0.8 AS s FROM x{i - 1} JOIN w ON src = node UNION ALL SELECT topic, node, 0.2 * s FROM x0) GROUP BY 1, 2)", 6) + " SELECT topic::BIGINT AS topic, node, round(s, 10) AS score FROM x6")


def topic_walk(spark, sf_dir):
    """Scores with jumps to a topic's nodes alike: visits of the walks stored at those nodes."""
    _, v = W._store(spark, sf_dir)
    x = v.join(_topics(spark, sf_dir).withColumnRenamed("node", "src"), "src")
    total = x.where("pos = 0").groupBy("seed").agg(F.count("*").alias("walks"))
    return x.groupBy("seed", "node").agg(F.count("*").alias("visits")).join(total, "seed").select(F.col("seed").alias("topic"), "node", "visits", F.round(F.col("visits") * 0.2 / F.col("walks"), 10).alias("score"))


R.add("topic_walk", topic_walk, f"{_W}, x AS (SELECT c_nationkey AS topic, node, pos FROM w0 JOIN customer ON c_custkey = src), t AS (SELECT topic, count(*) AS k FROM x WHERE pos = 0 GROUP BY 1) SELECT topic::BIGINT AS topic, node, count(*) AS visits, round(count(*) * 0.2 / max(k), 10) AS score FROM x JOIN t USING (topic) GROUP BY 1, 2")


def block_start_gain(spark, sf_dir):
    """Distance to the scores after two rounds: from block-structured and from uniform start. Blocks are the customers' nations."""
    e = W._e(spark, sf_dir)
    start = save(block_start(e, _topics(spark, sf_dir).withColumnRenamed("seed", "block")), "start")
    truth = save(exact.power_iteration(e, rounds=25).select("node", F.col("score").alias("t")), "truth")
    gap = lambda x, how: x.join(truth, "node").agg(F.sum(F.abs(F.col("score") - F.col("t"))).alias("l1")).select(F.lit(how).alias("start"), "l1")
    return gap(exact.power_iteration(e, rounds=2, start=start), "blocks").unionByName(gap(exact.power_iteration(e, rounds=2), "uniform"))


R.add("block_start", block_start_gain)
R.add("svd_recommend", lambda s, d: (lambda e: personal.top(personal.exclude_known(low_rank_scores(e, save(personal.pick_seeds(e), "seeds")), e), 20))(W._e(s, d, "buys")))

# costs of starting again
R.add("pass_count", lambda s, d: W._store(s, d)[1].groupBy("pos").agg(F.count("*").alias("live_walks")).crossJoin(W._e(s, d).agg(F.count("*").alias("edges_scanned"))).select(F.col("pos").cast("long").alias("pass"), "live_walks", "edges_scanned"), f"{_W} SELECT pos AS pass, count(*) AS live_walks, (SELECT count(*) FROM e0) AS edges_scanned FROM w0 GROUP BY pos")


def mc_scratch(spark, sf_dir):
    """Steps of building the store anew before and after a batch, which repair avoids."""
    base, _ = W._scenario(spark, sf_dir)
    row = lambda e, what: build_store(e, W.SPEC).agg(F.count("*").alias("steps")).select(F.lit(what).alias("edges"), "steps")
    return row(base, "before").unionByName(row(W._e(spark, sf_dir), "after"))


R.add("mc_scratch", mc_scratch, f"SELECT 'before' AS edges, (WITH RECURSIVE {walks_sql(f'SELECT src, dst, ord FROM ({COBUY}) WHERE {W._TAG} <> $$00$$', W.SPEC)} SELECT count(*) FROM w0) AS steps UNION ALL SELECT 'after', ({_W} SELECT count(*) FROM w0)")


def prop2_bound(spark, sf_dir):
    """Expected walks to repair over the arrivals after the cut: n R / eps times score over out-degree of each source."""
    old, new = M._snapshots(M._e(spark, sf_dir, "cobuy"))
    n = G.nodes(old).agg(F.count("*").alias("n"))
    d = old.groupBy(F.col("src").alias("node")).agg(F.count("*").alias("d"))
    x = new.select(F.col("src").alias("node")).join(exact.power_iteration(old, rounds=10).join(d, "node"), "node")
    return x.agg(F.count("*").alias("arrivals"), F.sum(F.col("score") / F.col("d")).alias("t")).crossJoin(n).select("arrivals", F.round(F.col("n") * 2 / 0.2 * F.col("t"), 5).alias("walks"))


R.add("prop2_bound", prop2_bound, f"WITH {M._PRC}, d AS (SELECT src, count(*) AS d FROM e GROUP BY 1) SELECT count(*) AS arrivals, round((SELECT count(*) FROM n) * 2 / 0.2::DOUBLE * sum(s / d), 5) AS walks FROM ({COBUY}) a JOIN x10 ON node = src JOIN d ON d.src = a.src WHERE a.ord >= {M.CUT}")


# single arrivals, new nodes, and what is read off a repaired store
def arrive_one(spark, sf_dir):
    e = W._e(spark, sf_dir)
    last = e.agg(F.max(F.struct("ord", "src", "dst")).alias("x")).select(F.lit("+").alias("op"), "x.src", "x.dst", "x.ord")
    last = save(last, "last")
    base = save(e.join(last.select("src", "dst"), ["src", "dst"], "left_anti").select("src", "dst", "ord"), "base")
    store = update.WalkStore.create(base, W.SPEC)
    store.apply(last)
    return store.visits().select("src", "rep", "pos", "node", "ended")


_LAST = f"SELECT src, dst, ord FROM ({COBUY}) ORDER BY ord DESC, src DESC, dst DESC LIMIT 1"
_ONE = update.update_sql(f"SELECT src, dst, ord FROM ({COBUY}) ANTI JOIN ({_LAST}) l USING (src, dst)", f"SELECT '+' AS op, src, dst, ord FROM ({_LAST})", W.SPEC)
R.add("arrive_one", arrive_one, f"WITH RECURSIVE {_ONE} SELECT src, rep, pos, node, ended FROM w1")
_MIXED = W._update_sql(("00",), ("01",))
R.add("store_after_update", lambda s, d: W._applied(s, d, ("00",), ("01",))[0].visits().groupBy("node").agg(F.count("*").alias("visits"), F.count_if(F.col("epoch") == 1).alias("redone")).drop("redone"), f"{_MIXED} SELECT node, count(*) AS visits FROM w1 GROUP BY node")


def _link_changes(spark, sf_dir):
    e = W._e(spark, sf_dir, "links")
    fresh = F.substring(F.md5(F.concat(F.lit("page|"), F.col("src").cast("string"))), 1, 1) < "4"
    return save(e.where(~fresh).select("src", "dst", "ord"), "base"), save(e.where(fresh).select(F.lit("+").alias("op"), "src", "dst", "ord"), "changes")


def new_node_walks(spark, sf_dir):
    """Walks of nodes that a batch brought: pages and targets first seen in it start as many walks as the others have."""
    base, ch = _link_changes(spark, sf_dir)
    store = update.WalkStore.create(base, W.SPEC)
    store.apply(ch)
    return store.visits().join(G.nodes(base).select(F.col("node").alias("src")), "src", "left_anti").select("src", "rep", "pos", "node", "ended")


_PAGE = "substr(md5('page|' || src), 1, 1)"
_NEW = update.update_sql(f"SELECT src, dst, ord FROM ({LINKS}) WHERE {_PAGE} >= '4'", f"SELECT '+' AS op, src, dst, ord FROM ({LINKS}) WHERE {_PAGE} < '4'", W.SPEC)
R.add("new_node_walks", new_node_walks, f"WITH RECURSIVE {_NEW} SELECT src, rep, pos, node, ended FROM w1 ANTI JOIN (SELECT node AS src FROM n0) USING (src)")


def exp_w11(spark, sf_dir):
    """Arrivals whose source has weight degree + 1: repair work by batch, summed, against the closed form for that model."""
    from incwalk.functions import theory

    e = W._e(spark, sf_dir, "dirichlet")
    m, n = e.count(), G.nodes(e).count()
    spec = Spec(reps=2, seed=11)
    ledger = update.replay(e, spec, [m // 2, m // 2 + m // 4, m])
    bound = theory.update_bound(n, 2, 0.2, m, "dirichlet") - theory.update_bound(n, 2, 0.2, m // 2, "dirichlet")
    return ledger.agg(F.sum("walks_rerouted").alias("walks_rerouted"), F.sum("steps_redone").alias("steps_redone")).withColumn("bound_steps", F.lit(round(bound, 3)))


R.add("exp_w11", exp_w11)
R.add("friends_excluded", lambda s, d: (lambda e, sd: e.select(F.col("src").alias("seed"), F.col("dst").alias("mid")).join(F.broadcast(sd.select("seed")), "seed", "left_semi").join(e.select(F.col("src").alias("mid"), F.col("dst").alias("node")), "mid").groupBy("seed", "node").agg(F.count("*").alias("paths")).where("seed <> node").join(e.select(F.col("src").alias("seed"), F.col("dst").alias("node")), ["seed", "node"], "left_anti"))(W._e(s, d), personal.pick_seeds(edges(s, d, "cobuy"))), f"WITH e AS ({COBUY}), sd AS (SELECT src AS seed FROM (SELECT src, count(*) AS f FROM e GROUP BY src) WHERE f BETWEEN 20 AND 30 ORDER BY md5('seed|' || src), src LIMIT 100) SELECT * FROM (SELECT a.src AS seed, b.dst AS node, count(*) AS paths FROM e a JOIN e b ON a.dst = b.src WHERE a.src IN (SELECT seed FROM sd) AND b.dst <> a.src GROUP BY 1, 2) ANTI JOIN (SELECT src AS seed, dst AS node FROM e) USING (seed, node)")
