"""Graphs, walk stores, estimates and updates as queries."""

from __future__ import annotations

from pyspark.sql import functions as F

from incwalk.functions import theory
from incwalk.operators.registry_of import Registry
from incwalk.plans import exact, personal, update
from incwalk.plans import graph as G
from incwalk.plans.walks import Spec, build_store, segments, walks_sql
from incwalk.sources.graphs import GRAPHS, edges, edges_sql
from incwalk.store import save

R = Registry()
SPEC = Spec(reps=2, eps=0.2, seed=1)
ALT = Spec(reps=1, eps=0.2, seed=2, kind="alternating")
COBUY = edges_sql("cobuy")


def _e(spark, sf_dir, name="cobuy"):
    return save(edges(spark, sf_dir, name).select("src", "dst", "ord"), f"edges-{name}")


def _store(spark, sf_dir, spec=SPEC, name="cobuy"):
    e = _e(spark, sf_dir, name)
    return e, build_store(e, spec)


for _name in GRAPHS:
    R.add(f"edges_{_name}", lambda spark, sf_dir, n=_name: edges(spark, sf_dir, n), edges_sql(_name))

R.add("adjacency_slots", lambda s, d: G.slots(edges(s, d, "cobuy")).select("src", "slot", "dst"), f"SELECT src, row_number() OVER (PARTITION BY src ORDER BY ord, dst) - 1 AS slot, dst FROM ({COBUY})")
R.add("degrees", lambda s, d: G.degrees(edges(s, d, "buys")), f"WITH e AS ({edges_sql('buys')}) SELECT node, sum(o)::BIGINT AS outdeg, sum(1 - o)::BIGINT AS indeg FROM (SELECT src AS node, 1 AS o FROM e UNION ALL SELECT dst, 0 FROM e) GROUP BY node")
R.add("dangling_nodes", lambda s, d: (lambda e: G.nodes(e).join(e.select(F.col("src").alias("node")), "node", "left_anti"))(_e(s, d, "words")), f"WITH e AS ({edges_sql('words')}) SELECT DISTINCT dst AS node FROM e ANTI JOIN (SELECT src AS dst FROM e) USING (dst)")

_W = "WITH RECURSIVE " + walks_sql(COBUY, SPEC)
R.add("walk_visits", lambda s, d: _store(s, d)[1].select("src", "rep", "pos", "node", "ended"), f"{_W} SELECT src, rep, pos, node, ended FROM w0")
R.add("walk_lengths", lambda s, d: segments(_store(s, d)[1]).groupBy("length", "ended").count(), f"{_W} SELECT length, ended, count(*) AS count FROM (SELECT count(*) AS length, max(ended) AS ended FROM w0 GROUP BY src, rep) GROUP BY 1, 2")


def pagerank_counts(spark, sf_dir):
    e, v = _store(spark, sf_dir)
    n = G.nodes(e).agg(F.count("*").alias("n"))
    return v.groupBy("node").agg(F.count("*").alias("visits")).crossJoin(n).select("node", "visits", F.round(F.col("visits") * SPEC.eps / (F.col("n") * SPEC.reps), 12).alias("score"))


R.add("pagerank_counts", pagerank_counts, f"{_W} SELECT node, count(*) AS visits, round(count(*) * 0.2 / ((SELECT count(*) FROM n0) * 2), 12) AS score FROM w0 GROUP BY node")


def pagerank_normalised(spark, sf_dir):
    _, v = _store(spark, sf_dir, name="links")
    return v.groupBy("node").agg(F.count("*").alias("visits")).crossJoin(v.agg(F.count("*").alias("n"))).select("node", F.round(F.col("visits") / F.col("n"), 12).alias("score"))


R.add("pagerank_normalised", pagerank_normalised, f"WITH RECURSIVE {walks_sql(edges_sql('links'), SPEC)} SELECT node, round(count(*) / (SELECT count(*) FROM w0), 12) AS score FROM w0 GROUP BY node")
R.add("walks_through_node", lambda s, d: _store(s, d)[1].groupBy("node").agg(F.count_distinct("src", "rep").alias("walks")), f"{_W} SELECT node, count(DISTINCT (src, rep)) AS walks FROM w0 GROUP BY node")
_A = "WITH RECURSIVE " + walks_sql(COBUY, ALT)
R.add("alt_visits", lambda s, d: _store(s, d, ALT)[1].select("src", "rep", "pos", "node", "role", "ended"), f"{_A} SELECT src, rep, pos, node, role, ended FROM w0")


def alt_scores(spark, sf_dir):
    e, v = _store(spark, sf_dir, ALT)
    n = G.nodes(e).agg(F.count("*").alias("n"))
    c = v.where(F.col("rep") < ALT.reps).groupBy("node").agg(F.count_if(F.col("role") == "hub").alias("h"), F.count_if(F.col("role") == "auth").alias("a")).crossJoin(n)
    return c.select("node", F.round(F.col("h") * 0.2 / F.col("n"), 12).alias("hub"), F.round(F.col("a") * 0.2 / (0.8 * F.col("n")), 12).alias("auth"))


R.add("alt_scores", alt_scores, f"{_A} SELECT node, round(count(*) FILTER (role = 'hub') * 0.2 / (SELECT count(*) FROM n0), 12) AS hub, round(count(*) FILTER (role = 'auth') * 0.2 / (0.8 * (SELECT count(*) FROM n0)), 12) AS auth FROM w0 WHERE rep < 1 GROUP BY node")
R.add("authority_limit", lambda s, d: (lambda e: e.groupBy(F.col("dst").alias("node")).agg(F.count("*").alias("k")).crossJoin(e.agg(F.count("*").alias("m"))).select("node", F.round(F.col("k") / F.col("m"), 12).alias("auth")))(_e(s, d)), f"WITH e AS ({COBUY}) SELECT dst AS node, round(count(*) / (SELECT count(*) FROM e), 12) AS auth FROM e GROUP BY dst")

# updates: a keyed sample of the edges arrives last, another leaves
_TAG = "substr(md5('cut|' || src || '|' || dst), 1, 2)"


def _tag():
    return F.substring(F.md5(F.concat(F.lit("cut|"), F.col("src").cast("string"), F.lit("|"), F.col("dst").cast("string"))), 1, 2)


def _scenario(spark, sf_dir, plus=("00",), minus=()):
    e = _e(spark, sf_dir).withColumn("tag", _tag())
    base = save(e.where(~F.col("tag").isin(*plus)) if plus else e, "base").drop("tag")
    ch = e.where(F.col("tag").isin(*plus, *minus)).select(F.when(F.col("tag").isin(*plus), "+").otherwise("-").alias("op"), "src", "dst", "ord") if plus else e.where(F.col("tag").isin(*minus)).select(F.lit("-").alias("op"), "src", "dst", "ord")
    return base, save(ch, "changes")


def _applied(spark, sf_dir, plus=("00",), minus=(), reroute="suffix", spec=SPEC, gate=None, counted=False):
    base, ch = _scenario(spark, sf_dir, plus, minus)
    store = update.WalkStore.create(base, spec)
    if counted:
        store.counters()
    return store, store.apply(ch, reroute, gate)


def _update_sql(plus=("00",), minus=(), restart=False):
    tags = lambda t: ", ".join(f"'{x}'" for x in t)
    e = f"SELECT src, dst, ord FROM ({COBUY})"
    base = f"{e} WHERE {_TAG} NOT IN ({tags(plus)})" if plus else e
    parts = [f"SELECT '{op}' AS op, src, dst, ord FROM ({COBUY}) WHERE {_TAG} IN ({tags(t)})" for op, t in (("+", plus), ("-", minus)) if t]
    return "WITH RECURSIVE " + update.update_sql(base, " UNION ALL ".join(parts), SPEC, 1, restart)


_VISITS = " SELECT src, rep, pos, node, ended FROM w1"
for _n, _p, _m, _re in (("arrive_batch", ("00",), (), "suffix"), ("arrive_restart", ("00",), (), "restart"), ("delete_batch", (), ("01",), "suffix"), ("mixed_batch", ("00",), ("01",), "suffix")):
    R.add(_n, lambda s, d, p=_p, m=_m, re=_re: _applied(s, d, p, m, re)[0].visits().select("src", "rep", "pos", "node", "ended"), _update_sql(_p, _m, _re == "restart") + _VISITS)
R.add("arrive_ledger", lambda s, d: _applied(s, d)[1].select("walks_rerouted", "edges_added"), _update_sql() + " SELECT (SELECT count(*) FROM c1) AS walks_rerouted, (SELECT count(*) FROM added) AS edges_added")
R.add("delete_ledger", lambda s, d: _applied(s, d, (), ("01",))[1].select("walks_rerouted", "edges_gone"), _update_sql((), ("01",)) + " SELECT (SELECT count(*) FROM c1) AS walks_rerouted, (SELECT count(*) FROM gone) AS edges_gone")
R.add("counters_after", lambda s, d: _applied(s, d, ("00",), ("01",), counted=True)[0].counters().select("node", "w_segments", "visits", "continuing", "outdeg"), _update_sql(("00",), ("01",)) + " SELECT node, w_segments, visits, continuing, coalesce(o, 0) AS outdeg FROM (SELECT node, count(DISTINCT (src, rep)) AS w_segments, count(*) AS visits, count(*) FILTER (ended IS NULL) AS continuing FROM w1 GROUP BY node) LEFT JOIN (SELECT src AS node, count(*) AS o FROM e1 GROUP BY 1) USING (node)")
R.add("gate_probabilities", lambda s, d: (lambda r: update.gate(update.counters(r[1], r[0])))(_store(s, d)), f"{_W}, c AS (SELECT node, count(DISTINCT (src, rep)) AS w, count(*) FILTER (ended IS NULL) AS v FROM w0 GROUP BY node), o AS (SELECT src AS node, count(*) AS d FROM e0 GROUP BY 1) SELECT node, round(1 - pow(1 - 1 / (coalesce(d, 0) + 1), w), 9) AS p_segments, round(1 - pow(1 - 1 / (coalesce(d, 0) + 1), v), 9) AS p_visits FROM c LEFT JOIN o USING (node)")
R.add("alt_arrive_batch", lambda s, d: _applied(s, d, spec=ALT)[0].visits().groupBy("role", "ended").count())


def replay_ledger(spark, sf_dir):
    e = _e(spark, sf_dir, "handoff")
    return update.replay(e, Spec(reps=2, seed=3), update.whole_history(e.count()))


R.add("replay_ledger", replay_ledger)


# personalised walks
TOP = 10


def _personal(spark, sf_dir, policy="lazy", length: int | None = 400, reps=5, how_many=100, kind="pagerank", name="cobuy", counts=False):
    spec = Spec(reps=reps or 1, seed=4, kind=kind)
    e = _e(spark, sf_dir, name)
    seeds = save(personal.pick_seeds(e, how_many), "seeds")
    length = personal.topk_length(e, seeds, TOP, spec) if length is None else length
    visits = build_store(e, spec) if reps else None
    return e, seeds, save((personal.visit_counts if counts else personal.waves)(visits, e, seeds, length, spec, policy), "walk")


def _personal_sql(policy="lazy", length: int | None = 400, reps=5, how_many=100, kind="pagerank", name="cobuy"):
    spec = Spec(reps=reps or 1, seed=4, kind=kind)
    seeds = f"SELECT src AS seed, friends FROM (SELECT src, count(*) AS friends FROM e0 GROUP BY src) WHERE friends BETWEEN 20 AND 30 ORDER BY md5('seed|' || src), src LIMIT {how_many}"
    text = personal.waves_sql(f"SELECT src, dst, ord FROM ({edges_sql(name)})", spec, seeds, str(length) if length else personal.topk_length_sql(TOP, spec), policy, bool(reps))
    return "WITH RECURSIVE " + text


_COUNTS = " SELECT seed, node, count(*) AS visits FROM pw GROUP BY 1, 2"
for _p in ("lazy", "once", "literal"):
    R.add(f"stitched_counts_{_p}", lambda s, d, p=_p: personal.frequencies(_personal(s, d, p, counts=True)[2]).select("seed", "node", "visits"), _personal_sql(_p) + _COUNTS)
_LEDGER = "SELECT seed, max(fetches)::BIGINT AS fetches, count(*) FILTER (how = 'segment') AS segment_steps, count(*) FILTER (how = 'step') AS hand_steps, count(*) FILTER (how = 'reset') AS resets FROM pf GROUP BY seed"
for _f in ("full", "edge"):
    R.add(f"fetch_ledger_{_f}", lambda s, d, f=_f: personal.fetched(_personal(s, d)[2], f).groupBy("seed").agg(F.max("fetches").alias("fetches"), F.count_if(F.col("how") == "segment").alias("segment_steps"), F.count_if(F.col("how") == "step").alias("hand_steps"), F.count_if(F.col("how") == "reset").alias("resets")), f"{_personal_sql()}, {personal.fetched_sql(_f)} {_LEDGER}")


def _top(scores):
    return personal.top(scores, TOP).select("seed", "node", "visits", F.col("rank").cast("long").alias("rank"))


def _top_sql(role="", known=False):
    friends = " ANTI JOIN (SELECT src AS seed, dst AS node FROM e0) USING (seed, node)" if known else ""
    keep = "WHERE seed <> node" if known else ""
    return f" SELECT * FROM (SELECT seed, node, visits, row_number() OVER (PARTITION BY seed ORDER BY visits DESC, node) AS rank FROM (SELECT seed, node, count(*) AS visits FROM pw {role} GROUP BY 1, 2){friends} {keep}) WHERE rank <= {TOP}"


_ALT4 = {"length": None, "kind": "alternating", "reps": 2}
_AUTH = "WHERE role = 'auth'"
R.add("ppr_topk", lambda s, d: _top(personal.frequencies(_personal(s, d, length=None, counts=True)[2])), _personal_sql(length=None) + _top_sql())
R.add("ppr_topk_no_friends", lambda s, d: (lambda x: _top(personal.exclude_known(personal.frequencies(x[2]), x[0], x[1])))(_personal(s, d, length=None, counts=True)), _personal_sql(length=None) + _top_sql(known=True))
R.add("alt_ppr_topk", lambda s, d: _top(personal.frequencies(_personal(s, d, **_ALT4, counts=True)[2].where("role = 'auth'"))), _personal_sql(**_ALT4) + _top_sql(_AUTH))
R.add("recommend_alt", lambda s, d: (lambda x: _top(personal.exclude_known(personal.frequencies(x[2].where("role = 'auth'")), x[0], x[1])))(_personal(s, d, **_ALT4, name="buys", counts=True)), _personal_sql(**_ALT4, name="buys") + _top_sql(_AUTH, known=True))
R.add("waves_counts", lambda s, d: personal.frequencies(_personal(s, d, length=None, counts=True)[2]).select("seed", "node", "visits"), _personal_sql(length=None) + _COUNTS)
R.add("crude_walk_queries", lambda s, d: personal.fetched(_personal(s, d, reps=0)[2], "edge").groupBy("seed").agg(F.count_if("hand").alias("queries"), F.count_if(F.col("how") == "reset").alias("resets")), _personal_sql(reps=0) + " SELECT seed, count(*) FILTER (hand) AS queries, count(*) FILTER (how = 'reset') AS resets FROM pw GROUP BY seed")


def topk_fetches(spark, sf_dir):
    """Mean fetches of the walks that give the top k, beside the bound for that length and the bound of the top-k rule."""
    spec = Spec(reps=5, seed=4)
    e = _e(spark, sf_dir)
    seeds = save(personal.pick_seeds(e, 100), "seeds")
    n, alpha = G.nodes(e).count(), personal.usable_alpha(e, seeds, spec)
    length = personal.topk_length(e, seeds, TOP, spec)
    walk = personal.fetched(personal.waves(build_store(e, spec), e, seeds, length, spec))
    seen = walk.groupBy("seed").agg(F.max("fetches").alias("f")).agg(F.round(F.avg("f"), 6).alias("fetches"))
    return seen.select(F.lit(length).cast("long").alias("steps"), F.lit(round(alpha, 5)).alias("alpha"), "fetches", F.lit(round(theory.fetch_bound(n, spec.reps, alpha, length), 3)).alias("bound_of_length"), F.lit(round(theory.topk_fetch_bound(TOP, spec.reps, 5, alpha), 3)).alias("bound_of_k"))


_FB = "SELECT (SELECT len FROM lg) AS steps, round((SELECT alpha FROM fa), 5) AS alpha, (SELECT round(avg(f), 6) FROM (SELECT max(fetches) AS f FROM pf GROUP BY seed)) AS fetches, round(1 + pow(2 * (1 - (SELECT alpha FROM fa)) / ((SELECT count(*) FROM n0)::DOUBLE * 5), 1 / (SELECT alpha FROM fa) - 1) * pow((SELECT len FROM lg)::DOUBLE, 1 / (SELECT alpha FROM fa)), 3) AS bound_of_length, round(1 + pow(5::DOUBLE, 1 / (SELECT alpha FROM fa)) * 10 / ((1 - (SELECT alpha FROM fa)) * pow(2.5::DOUBLE, 1 / (SELECT alpha FROM fa) - 1)), 3) AS bound_of_k"
R.add("topk_fetches", topk_fetches, f"{_personal_sql(length=None)}, fa AS ({personal.alpha_sql(Spec())}), {personal.fetched_sql()} {_FB}")
_SEEDS = "SELECT src AS seed, friends FROM (SELECT src, count(*) AS friends FROM e0 GROUP BY src) WHERE friends BETWEEN 20 AND 30 ORDER BY md5('seed|' || src), src LIMIT 100"
R.add("seeds", lambda s, d: personal.pick_seeds(edges(s, d, "cobuy")), f"WITH e0 AS ({COBUY}) {_SEEDS}")
R.add("segment_frequency", lambda s, d: (lambda r: personal.segment_frequency(r[1], personal.pick_seeds(r[0])))(_store(s, d)), f"{_W} SELECT src AS seed, node, count(*) AS visits FROM w0 WHERE src IN (SELECT seed FROM ({_SEEDS})) GROUP BY 1, 2")
R.add("segment_endpoints", lambda s, d: (lambda r: personal.segment_endpoints(r[1], personal.pick_seeds(r[0])))(_store(s, d)), f"{_W} SELECT src AS seed, node, count(*) AS visits FROM w0 WHERE ended IS NOT NULL AND src IN (SELECT seed FROM ({_SEEDS})) GROUP BY 1, 2")


# exact iterations, unrolled for SQL
def _rounds(body, n):
    return ", ".join(body(i) for i in range(1, n + 1))


_WE = f"e AS ({COBUY}), w AS (SELECT src, dst, 1 / count(*) OVER (PARTITION BY src) AS ow, 1 / count(*) OVER (PARTITION BY dst) AS iw FROM e), n AS (SELECT DISTINCT node FROM (SELECT src AS node FROM e UNION ALL SELECT dst FROM e))"
_PR = f"WITH {_WE}, x0 AS (SELECT node, 1 / (SELECT count(*) FROM n) AS s FROM n), " + _rounds(lambda i: f"x{i} AS (SELECT node, sum(s) AS s FROM (SELECT dst AS node, s * ow * 0.8 AS s FROM x{i - 1} JOIN w ON src = node UNION ALL SELECT node, 0.2 * s FROM x0) GROUP BY node)", 10)
R.add("power_iteration", lambda s, d: exact.power_iteration(_e(s, d)).select("node", F.round("score", 10).alias("score")), f"{_PR} SELECT node, round(s, 10) AS score FROM x10")
_P0 = f"WITH {_WE}, sd AS (SELECT src AS seed FROM (SELECT src, count(*) AS f FROM e GROUP BY src) WHERE f BETWEEN 20 AND 30 ORDER BY md5('seed|' || src), src LIMIT 100), x0 AS (SELECT seed, seed AS node, 1.0::DOUBLE AS s FROM sd), "
R.add("ppr_power", lambda s, d: (lambda e: exact.power_iteration(e, rounds=6, seeds=save(personal.pick_seeds(e), "seeds")).select("seed", "node", F.round("score", 10).alias("score")))(_e(s, d)), _P0 + _rounds(lambda i: f"x{i} AS (SELECT seed, node, sum(s) AS s FROM (SELECT seed, dst AS node, s * ow * 0.8 AS s FROM x{i - 1} JOIN w ON src = node UNION ALL SELECT seed, node, 0.2 * s FROM x0) GROUP BY 1, 2)", 6) + " SELECT seed, node, round(s, 10) AS score FROM x6")
_AL = lambda n, ow, iw: _rounds(lambda i: f"a{i} AS (SELECT seed, dst AS node, sum(s * {ow}) AS s FROM x{i - 1} JOIN w ON src = node GROUP BY 1, 2), x{i} AS (SELECT seed, node, sum(s) AS s FROM (SELECT seed, src AS node, s * {iw} * 0.8 AS s FROM a{i} JOIN w ON dst = node UNION ALL SELECT seed, node, 0.2 * s FROM x0) GROUP BY 1, 2)", n) + f", af AS (SELECT seed, dst AS node, sum(s * {ow}) AS s FROM x{n} JOIN w ON src = node GROUP BY 1, 2)"
_AF = " SELECT coalesce(x.seed, a.seed) AS seed, coalesce(x.node, a.node) AS node, round(coalesce(x.s, 0), 10) AS hub, round(coalesce(a.s, 0), 10) AS auth FROM x{n} x FULL JOIN af a ON a.seed = x.seed AND a.node = x.node"
R.add("alt_ppr_power", lambda s, d: (lambda e: exact.alternating_iteration(e, rounds=4, seeds=save(personal.pick_seeds(e), "seeds")).select("seed", "node", F.round("hub", 10).alias("hub"), F.round("auth", 10).alias("auth")))(_e(s, d)), _P0 + _AL(4, "ow", "iw") + _AF.format(n=4))
R.add("alt_power", lambda s, d: exact.alternating_iteration(_e(s, d), rounds=6).select("node", F.round("hub", 10).alias("hub"), F.round("auth", 10).alias("auth")), f"WITH {_WE}, x0 AS (SELECT -1 AS seed, node, 1 / (SELECT count(*) FROM n) AS s FROM n), " + _AL(6, "ow", "iw") + _AF.format(n=6).replace("coalesce(x.seed, a.seed) AS seed, ", ""))
R.add("hits_ppr", lambda s, d: (lambda e: personal.top(exact.alternating_iteration(e, rounds=4, seeds=save(personal.pick_seeds(e), "seeds"), divide=False), 10, "auth").select("seed", "node", "rank"))(_e(s, d)), _P0 + _AL(4, "1", "1") + ", rk AS (SELECT seed, node, row_number() OVER (PARTITION BY seed ORDER BY s DESC, node) AS rank FROM af) SELECT * FROM rk WHERE rank <= 10")
_CO = _P0 + "d AS (SELECT src, count(*) AS d FROM e GROUP BY 1), h AS (SELECT a.src AS seed, b.src AS node, count(*) AS k FROM e a JOIN e b ON a.dst = b.dst WHERE a.src IN (SELECT seed FROM sd) GROUP BY 1, 2), hub AS (SELECT seed, node, k / sqrt(x.d * y.d) AS hub FROM h JOIN d x ON x.src = seed JOIN d y ON y.src = node)"
R.add("cosine_scores", lambda s, d: (lambda e: exact.cosine_hubs(e, personal.pick_seeds(e)).select("seed", "node", F.round("hub", 10).alias("hub")))(_e(s, d)), _CO + " SELECT seed, node, round(hub, 10) AS hub FROM hub")
R.add("cosine_authority", lambda s, d: (lambda e: exact.cosine_authorities(e, exact.cosine_hubs(e, personal.pick_seeds(e))).select("seed", "node", F.round("auth", 8).alias("auth")))(_e(s, d)), _CO + " SELECT seed, dst AS node, round(sum(hub), 8) AS auth FROM hub JOIN e ON src = node GROUP BY 1, 2")
R.add("popularity", lambda s, d: edges(s, d, "buys").groupBy(F.col("dst").alias("node")).agg(F.count("*").alias("links")), f"SELECT dst AS node, count(*) AS links FROM ({edges_sql('buys')}) GROUP BY 1")
_DP = f"WITH {_WE}, b AS (SELECT node, node AS target, 0.2::DOUBLE AS s FROM (SELECT src AS node FROM (SELECT src, count(*) AS f FROM e GROUP BY src) WHERE f BETWEEN 20 AND 30 ORDER BY md5('seed|' || src), src LIMIT 100)), x0 AS (SELECT * FROM b), " + _rounds(lambda i: f"x{i} AS (SELECT * FROM (SELECT node, target, sum(s) AS s FROM (SELECT src AS node, target, s * ow * 0.8 AS s FROM x{i - 1} JOIN w ON dst = node UNION ALL SELECT * FROM b) GROUP BY 1, 2) WHERE s >= {{keep}})", 3) + " SELECT node, target, round(s, 10) AS score FROM x3"
R.add("neighbour_dp", lambda s, d: (lambda e: exact.neighbour_mean(e, personal.pick_seeds(e).select(F.col("seed").alias("node")), depth=3).select("node", "target", F.round("score", 10).alias("score")))(_e(s, d)), _DP.format(keep="0"))
R.add("rounded_dp", lambda s, d: (lambda e: exact.neighbour_mean(e, personal.pick_seeds(e).select(F.col("seed").alias("node")), depth=3, keep=0.0005).select("node", "target", F.round("score", 10).alias("score")))(_e(s, d)), _DP.format(keep="0.0005"))
R.add("aitken_power", lambda s, d: exact.aitken(_e(s, d)).select("node", F.round("score", 9).alias("score")))


def warm_start_gain(spark, sf_dir):
    """Distance to the new scores after two rounds: from the old scores and from the uniform start."""
    base, ch = _scenario(spark, sf_dir)
    new, _, _ = update.changed_edges(base, ch)
    new = save(new, "edges")
    truth = exact.power_iteration(new, rounds=20)
    old = save(exact.power_iteration(base, rounds=20), "old")
    gap = lambda x: x.join(truth.select("node", F.col("score").alias("t")), "node").agg(F.sum(F.abs(F.col("score") - F.col("t"))).alias("l1"))
    warm, cold = gap(exact.power_iteration(new, rounds=2, start=old)), gap(exact.power_iteration(new, rounds=2))
    return warm.select(F.lit("warm").alias("start"), "l1").union(cold.select(F.lit("cold"), "l1"))


def lumped_update(spark, sf_dir):
    base, ch = _scenario(spark, sf_dir)
    new, _, _ = update.changed_edges(base, ch)
    old = save(exact.power_iteration(base, rounds=15).select("node", "score"), "old")
    return exact.lumped_update(save(new, "edges"), old, ch.select(F.col("src").alias("node")).distinct())


R.add("warm_start_gain", warm_start_gain)
R.add("lumped_update", lumped_update)
