"""Costs, bounds, accuracy measures and the experiments as queries."""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
from pyspark.sql import Window
from pyspark.sql import functions as F

from incwalk.functions import theory
from incwalk.operators.registry_of import Registry
from incwalk.plans import dense, exact, personal, update
from incwalk.plans import graph as G
from incwalk.plans.ranking import numbered
from incwalk.plans.walks import Adjacency, Spec, advance, build_store, dealt, on_broadcast
from incwalk.sources.graphs import edges, edges_sql, trap
from incwalk.store import save

R = Registry()
CUT = 915_148_800  # 1999-01-01


def _e(spark, sf_dir, name):
    return save(edges(spark, sf_dir, name).select("src", "dst", "ord"), f"edges-{name}")


_CB = edges_sql("cobuy")
_SZ = f"e AS ({_CB}), sz AS (SELECT count(DISTINCT node) AS n, (SELECT count(*) FROM e) AS m FROM (SELECT src AS node FROM e UNION ALL SELECT dst FROM e))"


# closed forms: over grids of parameters and the sizes of a graph, by the SQL functions of the engine
def _sizes(e):
    """``(n, m)``: nodes and edges, a row."""
    return G.nodes(e).agg(F.count("*").alias("n")).crossJoin(e.agg(F.count("*").alias("m")))


def _grid(spark, sf_dir, values, *columns):
    theory.register(spark)
    return _sizes(_e(spark, sf_dir, "cobuy")).crossJoin(spark.sql(f"SELECT * FROM {values}")).selectExpr(*columns)


R.add("rem2_numbers", lambda s, d: _grid(s, d, "(VALUES (100)) AS x(k)", "n", "round(walk_length(n, k, 5, 0.75), 4) AS steps", "round(topk_fetch_bound(k, 10, 5, 0.75), 6) AS fetches", "round(fetch_bound(n, 10, 0.75, walk_length(n, k, 5, 0.75)), 6) AS fetches_of_length"), f"WITH {_SZ}, s AS (SELECT n, 5 / 0.25::DOUBLE * 100 * pow(n::DOUBLE / 100, 0.25) AS s FROM sz) SELECT n, round(s, 4) AS steps, round(1 + pow(5::DOUBLE, 1 / 0.75::DOUBLE) * 100 / (0.25 * pow(5::DOUBLE, 1 / 0.75::DOUBLE - 1)), 6) AS fetches, round(1 + pow(2 * 0.25::DOUBLE / (n::DOUBLE * 10), 1 / 0.75::DOUBLE - 1) * pow(s, 1 / 0.75::DOUBLE), 6) AS fetches_of_length FROM s")
_BY = ("CAST(s AS BIGINT) AS s", "CAST(r AS INT) AS r", "CAST(a AS DOUBLE) AS alpha")
_FB = "(VALUES (100), (200), (500), (1000), (2000), (5000), (10000), (20000), (50000)) AS x(s), (VALUES (5), (10), (20)) AS y(r), (VALUES (0.6), (0.77), (0.9), (1.1)) AS z(a)"
_TAU = "(VALUES (100), (1000), (10000), (50000)) AS x(s), (VALUES (5), (10), (20)) AS y(r), (VALUES (0.6), (0.77), (0.9)) AS z(a)"
R.add("fetch_bound_grid", lambda s, d: _grid(s, d, _FB, *_BY, "round(fetch_bound(n, r, a, s), 6) AS bound"), f"WITH {_SZ} SELECT {', '.join(_BY)}, round(CASE WHEN a < 1 THEN 1 + pow(2 * (1 - a::DOUBLE) / (n::DOUBLE * r), 1 / a::DOUBLE - 1) * pow(s::DOUBLE, 1 / a::DOUBLE) END, 6) AS bound FROM sz, {_FB}")


def topk_bound_grid(spark, sf_dir):
    """The bound of the top-k rule for as many results as some node has links."""
    theory.register(spark)
    k = _e(spark, sf_dir, "cobuy").groupBy("src").agg(F.count("*").alias("k")).select("k").distinct()
    grid = k.crossJoin(spark.sql("SELECT * FROM (VALUES (5), (10), (20)) AS y(r), (VALUES (0.5), (0.75), (0.9)) AS z(a)"))
    return grid.selectExpr("k", *_BY[1:], "round(topk_fetch_bound(k, r, 5, a), 6) AS bound")


R.add("topk_bound_grid", topk_bound_grid, f"SELECT k, {', '.join(_BY[1:])}, round(1 + pow(5::DOUBLE, 1 / a::DOUBLE) * k / ((1 - a::DOUBLE) * pow(r::DOUBLE / 2, 1 / a::DOUBLE - 1)), 6) AS bound FROM (SELECT DISTINCT count(*) AS k FROM ({_CB}) GROUP BY src), (VALUES (5), (10), (20)) AS y(r), (VALUES (0.5), (0.75), (0.9)) AS z(a)")


def model_scores(spark, sf_dir):
    """The model's score of each node that has links, by its place among them."""
    theory.register(spark)
    x = save(ranked(_e(spark, sf_dir, "cobuy").groupBy(F.col("dst").alias("node")).agg(F.count("*").alias("links")), "links"), "ranked")
    return x.crossJoin(x.agg(F.count("*").alias("n"))).selectExpr("node", "links", "rank", "round(model_score(rank, n, 0.75), 12) AS score")


R.add("model_scores", model_scores, f"SELECT node, links, row_number() OVER (ORDER BY links DESC, node) AS rank, round(0.25 * pow((row_number() OVER (ORDER BY links DESC, node))::DOUBLE, -0.75) / pow((count(*) OVER ())::DOUBLE, 0.25), 12) AS score FROM (SELECT dst AS node, count(*) AS links FROM ({_CB}) GROUP BY 1)")


def arrivals(spark, sf_dir, name):
    """``(src, dst, t)``: arrivals numbered from 1."""
    return numbered(_e(spark, sf_dir, name), [F.asc("ord"), F.asc("src"), F.asc("dst")], "t")


def thm4_bounds(spark, sf_dir):
    """Per arrival and running total, by partial sums inside blocks of arrivals and offsets of blocks."""
    e = save(arrivals(spark, sf_dir, "cobuy"), "arrivals")
    t = e.crossJoin(_sizes(e)).select("t", F.floor((F.col("t") - 1) / 500).alias("block"), (F.col("n") * 2 / 0.2 / F.col("t")).alias("walks"))
    inside = Window.partitionBy("block").orderBy("t").rowsBetween(Window.unboundedPreceding, 0)
    blocks = t.groupBy("block").agg(F.sum("walks").alias("w"))
    offset = blocks.withColumn("before", F.coalesce(F.sum("w").over(Window.orderBy("block").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0.0))).drop("w")
    x = t.join(offset, "block").withColumn("total", F.col("before") + F.sum("walks").over(inside))
    return x.select("t", F.round("walks", 6).alias("walks"), F.round(F.col("walks") / 0.2, 6).alias("steps"), F.round(F.col("total") / 0.2, 2).alias("total_steps"))


R.add("thm4_bounds", thm4_bounds, f"WITH {_SZ} SELECT t, round(w, 6) AS walks, round(w / 0.2, 6) AS steps, round(sum(w) OVER (ORDER BY t) / 0.2, 2) AS total_steps FROM (SELECT t, n * 2 / 0.2::DOUBLE / t AS w FROM (SELECT row_number() OVER (ORDER BY ord, src, dst) AS t FROM e), sz)")


def cost_table(spark, sf_dir):
    """Total work of keeping scores right over all arrivals, per method, for the sizes of the graphs."""
    out = None
    for name in ("cobuy", "buys", "handoff"):
        e = edges(spark, sf_dir, name)
        row = e.agg(F.count("*").alias("m")).crossJoin(G.nodes(e).agg(F.count("*").alias("n"))).select(F.lit(name).alias("graph"), "n", "m")
        out = row if out is None else out.unionByName(row)
    m, n, q = F.col("m").cast("double"), F.col("n").cast("double"), 1 / math.log(1 / 0.8)
    return out.select("graph", "n", "m", F.round(m * m / 2 * q, 2).alias("power"), F.round(m * n / 0.2, 2).alias("monte_carlo"), F.round(n / 0.04 * (F.log(m) + 1), 2).alias("incremental"), F.round(m * m / math.sqrt(0.2), 2).alias("scan_stitching"))


_Q = 1 / math.log(1 / 0.8)
R.add("cost_table", cost_table, "WITH g AS (" + " UNION ALL ".join(f"SELECT '{g}' AS graph, count(DISTINCT node) AS n, (SELECT count(*) FROM ({edges_sql(g)})) AS m FROM (SELECT src AS node FROM ({edges_sql(g)}) UNION ALL SELECT dst FROM ({edges_sql(g)}))" for g in ("cobuy", "buys", "handoff")) + f") SELECT graph, n, m, round(m::DOUBLE * m / 2 * {_Q!r}::DOUBLE, 2) AS power, round(m::DOUBLE * n / 0.2, 2) AS monte_carlo, round(n::DOUBLE / 0.04 * (ln(m) + 1), 2) AS incremental, round(m::DOUBLE * m / {math.sqrt(0.2)!r}::DOUBLE, 2) AS scan_stitching FROM g")
_SIZED = ("cobuy", "buys", "handoff")


def choose_r_table(spark, sf_dir):
    """R by each rule for the nodes of each graph; the level rule asks for the score of an average node."""
    n, log = F.col("n"), F.log(F.col("n").cast("double"))
    rules = {"one": F.lit(1), "log": F.ceil(F.log(n / 0.2)), "fetch": F.floor(log) + 1, "level": F.ceil(log)}
    out = None
    for name in _SIZED:
        row = G.nodes(edges(spark, sf_dir, name)).agg(F.count("*").alias("n")).select(F.lit(name).alias("graph"), "n", F.explode(F.array(*(F.struct(F.lit(k).alias("rule"), v.cast("long").alias("r")) for k, v in rules.items()))).alias("x"))
        out = row if out is None else out.unionByName(row)
    return out.select("graph", "x.rule", "n", "x.r")


R.add("choose_r_table", choose_r_table, "WITH g AS (" + " UNION ALL ".join(f"SELECT '{g}' AS graph, count(DISTINCT node) AS n FROM (SELECT src AS node FROM ({edges_sql(g)}) UNION ALL SELECT dst FROM ({edges_sql(g)}))" for g in _SIZED) + ") SELECT graph, rule, n, CASE rule WHEN 'one' THEN 1 WHEN 'log' THEN ceil(ln(n / 0.2)) WHEN 'fetch' THEN floor(ln(n)) + 1 ELSE ceil(ln(n)) END::BIGINT AS r FROM g, (VALUES ('one'), ('log'), ('fetch'), ('level')) a(rule)")
R.add("update_bounds", lambda s, d: s.createDataFrame([(m, round(theory.update_bound(1500, 2, 0.2, 50_000, m), 3)) for m in ("random", "alternating", "dirichlet", "deletion", "initial", "paid_gate")], "model string, steps double"), "WITH h AS (SELECT sum(1 / t::DOUBLE) AS h FROM range(1, 50001) x(t)) SELECT m AS model, round(CASE m WHEN 'random' THEN 75000 * h WHEN 'alternating' THEN 1200000 * h WHEN 'dirichlet' THEN 75000 * ln(51500 / 1500::DOUBLE) WHEN 'deletion' THEN 75000 / 50000::DOUBLE WHEN 'initial' THEN 1500 * 2 / 0.2::DOUBLE ELSE 50000 + 75000 * h END, 3) AS steps FROM h, (VALUES ('random'), ('alternating'), ('dirichlet'), ('deletion'), ('initial'), ('paid_gate')) v(m)")


def initial_share(spark, sf_dir):
    """Work of the first walks as a share of the work over all arrivals, for the arrivals of each graph."""
    out = None
    for name in _SIZED:
        row = arrivals(spark, sf_dir, name).agg(F.count("*").alias("m"), F.round(0.2 / F.sum(1 / F.col("t")), 9).alias("share")).select(F.lit(name).alias("graph"), "m", "share")
        out = row if out is None else out.unionByName(row)
    return out


R.add("initial_share", initial_share, " UNION ALL ".join(f"SELECT '{g}' AS graph, count(*) AS m, round(0.2 / sum(1 / t::DOUBLE), 9) AS share FROM (SELECT row_number() OVER (ORDER BY ord, src, dst) AS t FROM ({edges_sql(g)}))" for g in _SIZED))
R.add("fetch_ranks", lambda s, d: _grid(s, d, _TAU, *_BY, "round(fetch_rank(n, r, a, s), 6) AS tau"), f"WITH {_SZ} SELECT {', '.join(_BY)}, round(pow(1 - a::DOUBLE, 1 / a::DOUBLE) / pow(n::DOUBLE, 1 / a::DOUBLE - 1) * pow(2 * s::DOUBLE / r, 1 / a::DOUBLE), 6) AS tau FROM sz, {_TAU}")


def tail_bounds(spark, sf_dir):
    """Exponents of either tail by deviation, and their powers, with R of 2, at nodes of each number of links, whose scores are near their shares of all links."""
    rows = [(x, round(theory.tail_constant(x, 0.2), 9), round(theory.lower_tail_constant(x, 0.2), 9) if x < 1 else None) for x in (0.1, 0.25, 0.5, 1.0, 2.0)]
    e = _e(spark, sf_dir, "cobuy")
    links = e.groupBy("dst").agg(F.count("*").alias("links")).select("links").distinct().crossJoin(_sizes(e))
    power = lambda c: F.round(F.col("n") * 2 * F.col("links") / F.col("m") * F.col(c), 6)
    x = links.crossJoin(F.broadcast(spark.createDataFrame(rows, "delta double, exponent double, lower_exponent double")))
    return x.select("links", "delta", "exponent", "lower_exponent", power("exponent").alias("upper_power"), power("lower_exponent").alias("lower_power"))


_TAIL = "SELECT delta, round(greatest(0, max(t * (1 + delta) + 1 - 0.2::DOUBLE * exp(t * 0.2::DOUBLE) / (1 - 0.8::DOUBLE * exp(t * 0.2::DOUBLE)))), 9) AS exponent, CASE WHEN delta < 1 THEN round(greatest(0, max(1 - 0.2::DOUBLE * exp(-u * 0.2::DOUBLE) / (1 - 0.8::DOUBLE * exp(-u * 0.2::DOUBLE)) - u * (1 - delta))), 9) END AS lower_exponent FROM (SELECT -ln(0.8::DOUBLE) / 0.2::DOUBLE * i / 2000 AS t, 20 * i / 2000::DOUBLE AS u FROM range(1, 2000) r(i)), (SELECT unnest([0.1, 0.25, 0.5, 1.0, 2.0])::DOUBLE AS delta) GROUP BY delta"
R.add("tail_bounds", tail_bounds, f"WITH {_SZ} SELECT links, delta, exponent, lower_exponent, round(n * 2 * links / m * exponent, 6) AS upper_power, round(n * 2 * links / m * lower_exponent, 6) AS lower_power FROM sz, (SELECT DISTINCT count(*) AS links FROM e GROUP BY dst), ({_TAIL})")


# statistics of arrivals
def arrival_statistic(old, new, scores):
    """m times the mean of score over out-degree at the sources of new edges; sources not in the old graph drop."""
    m = old.agg(F.count("*").alias("m"))
    d = old.groupBy(F.col("src").alias("node")).agg(F.count("*").alias("d"))
    x = new.select(F.col("src").alias("node")).join(scores.join(d, "node"), "node")
    return x.agg(F.avg(F.col("score") / F.col("d")).alias("mean"), F.count("*").alias("arrivals")).crossJoin(m).select("arrivals", (F.col("m") * F.col("mean")).alias("mx"))


def _snapshots(e, cut=CUT):
    return save(e.where(F.col("ord") < cut), "old"), save(e.where(F.col("ord") >= cut), "new")


def exp_w01(spark, sf_dir):
    old, new = _snapshots(_e(spark, sf_dir, "cobuy"))
    return arrival_statistic(old, new, exact.power_iteration(old, rounds=10)).select("arrivals", F.round("mx", 6).alias("mx"))


_PRC = f"e AS (SELECT * FROM ({_CB}) WHERE ord < {CUT}), w AS (SELECT src, dst, 1 / count(*) OVER (PARTITION BY src) AS ow FROM e), n AS (SELECT src AS node FROM e UNION SELECT dst FROM e), x0 AS (SELECT node, 1 / (SELECT count(*) FROM n) AS s FROM n), " + ", ".join(f"x{i} AS (SELECT node, sum(s) AS s FROM (SELECT dst AS node, s * ow * 0.8 AS s FROM x{i - 1} JOIN w ON src = node UNION ALL SELECT node, 0.2 * s FROM x0) GROUP BY node)" for i in range(1, 11))
R.add("exp_w01", exp_w01, f"WITH {_PRC}, d AS (SELECT src, count(*) AS d FROM e GROUP BY 1) SELECT count(*) AS arrivals, round((SELECT count(*) FROM e) * avg(s / d), 6) AS mx FROM ({_CB}) a JOIN x10 ON node = src JOIN d ON d.src = a.src WHERE a.ord >= {CUT}")
R.add("arrival_statistic", lambda s, d: exp_w01(s, d), R.sql["exp_w01"])


def degree_cdfs(spark, sf_dir):
    """Shares of new and of existing edges whose source has at most d edges; both step functions at all degrees, missing ones carried forward."""
    old, new = _snapshots(_e(spark, sf_dir, "cobuy"))
    d = old.groupBy("src").agg(F.count("*").alias("d"))
    e = d.groupBy("d").agg(F.sum("d").alias("ends"))
    a = new.join(d, "src").groupBy("d").agg(F.count("*").alias("arrivals"))
    x = e.join(a, "d", "left").na.fill(0)
    run = Window.orderBy("d").rowsBetween(Window.unboundedPreceding, 0)  # as many rows as there are degrees
    every = Window.orderBy(F.lit(1)).rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    return x.select("d", F.round(F.sum("arrivals").over(run) / F.sum("arrivals").over(every), 9).alias("arriving"), F.round(F.sum("ends").over(run) / F.sum("ends").over(every), 9).alias("existing"))


_CDF = f"WITH o AS (SELECT * FROM ({_CB}) WHERE ord < {CUT}), g AS (SELECT src, count(*) AS d FROM o GROUP BY 1), e AS (SELECT d, sum(d) AS k FROM g GROUP BY 1), a AS (SELECT d, count(*) AS k FROM ({_CB}) x JOIN g ON g.src = x.src WHERE x.ord >= {CUT} GROUP BY 1), c AS (SELECT e.d, round(sum(coalesce(a.k, 0)) OVER (ORDER BY e.d) / sum(coalesce(a.k, 0)) OVER (), 9) AS arriving, round(sum(e.k) OVER (ORDER BY e.d) / sum(e.k) OVER (), 9) AS existing FROM e LEFT JOIN a ON a.d = e.d)"
R.add("degree_cdfs", degree_cdfs, f"{_CDF} SELECT * FROM c")
R.add("exp_w02", degree_cdfs, f"{_CDF} SELECT * FROM c")
R.add("cdf_gap", lambda s, d: degree_cdfs(s, d).agg(F.round(F.max(F.abs(F.col("arriving") - F.col("existing"))), 8).alias("gap")), f"{_CDF} SELECT round(max(abs(arriving - existing)), 8) AS gap FROM c")


# power laws
def ranked(scores, by="score"):
    return numbered(scores, [F.desc(by), F.asc("node")])


def powerlaw(scores, low, high, keys=()):
    """Least squares of ln score on ln rank between two ranks: exponent, intercept and fit."""
    x = scores.where((F.col("rank") >= low) & (F.col("rank") <= high) & (F.col("score") > 0)).select(*keys, F.log(F.col("rank").cast("double")).alias("x"), F.log(F.col("score").cast("double")).alias("y"))
    return (x.groupBy(*keys) if keys else x).agg(F.round(-F.regr_slope("y", "x"), 6).alias("alpha"), F.round(F.regr_r2("y", "x"), 6).alias("r2"), F.count("*").alias("points"))


R.add("exponent_indegree", lambda s, d: powerlaw(ranked(edges(s, d, "words").groupBy(F.col("dst").alias("node")).agg(F.count("*").alias("score"))), 1, 10**9), f"WITH r AS (SELECT score, row_number() OVER (ORDER BY score DESC, node) AS rank FROM (SELECT dst AS node, count(*) AS score FROM ({edges_sql('words')}) GROUP BY 1)) SELECT round(-regr_slope(ln(score), ln(rank)), 6) AS alpha, round(regr_r2(ln(score), ln(rank)), 6) AS r2, count(*) AS points FROM r")


def exp_w03(spark, sf_dir):
    e = _e(spark, sf_dir, "words")
    indeg = ranked(e.groupBy(F.col("dst").alias("node")).agg(F.count("*").alias("score")))
    pr = save(ranked(exact.power_iteration(e, rounds=10)), "ranked")
    part = lambda x, what, a, b: powerlaw(x, a, b).select(F.lit(what).alias("vector"), F.lit(a).alias("low"), F.lit(b).alias("high"), "alpha", "r2", "points")
    return part(indeg, "in-degree", 10, 1000).union(part(pr, "pagerank", 10, 1000)).union(part(pr, "pagerank", 10, 10000))


_WO = edges_sql("words")
_WW = f"e AS ({_WO}), w AS (SELECT src, dst, 1 / count(*) OVER (PARTITION BY src) AS ow FROM e)"
_FIT = "round(-regr_slope(ln(score), ln(rank)), 6) AS alpha, round(regr_r2(ln(score), ln(rank)), 6) AS r2, count(*) AS points"
_W03 = f"WITH {_WW}, n AS (SELECT src AS node FROM e UNION SELECT dst FROM e), x0 AS (SELECT node, 1 / (SELECT count(*) FROM n) AS s FROM n), " + ", ".join(f"x{i} AS (SELECT node, sum(s) AS s FROM (SELECT dst AS node, s * ow * 0.8 AS s FROM x{i - 1} JOIN w ON src = node UNION ALL SELECT node, 0.2 * s FROM x0) GROUP BY node)" for i in range(1, 11)) + ", r AS (SELECT 'in-degree' AS vector, score, row_number() OVER (ORDER BY score DESC) AS rank FROM (SELECT count(*) AS score FROM e GROUP BY dst) UNION ALL SELECT 'pagerank', s, row_number() OVER (ORDER BY s DESC) FROM x10), o AS (SELECT * FROM (VALUES ('in-degree', 10, 1000), ('pagerank', 10, 1000), ('pagerank', 10, 10000)) v(vector, low, high))"
_W03 += f" SELECT vector, low, high, {_FIT} FROM r JOIN o USING (vector) WHERE rank BETWEEN low AND high{{}} GROUP BY 1, 2, 3"
R.add("exp_w03", exp_w03, _W03.format(""))
R.add("exponent_pagerank", lambda s, d: exp_w03(s, d).where("vector = 'pagerank'"), _W03.format(" AND vector = 'pagerank'"))


def exponents_by_seed(spark, sf_dir, how_many=100):
    e = _e(spark, sf_dir, "words")
    seeds = save(personal.pick_seeds(e, how_many), "seeds")
    most = 20 * (seeds.agg(F.max("friends")).first()[0] or 0) + 1  # the ranks that count, and the seed itself
    x = exact.power_iteration(e, rounds=5, seeds=seeds, best=most).where("node <> seed")
    x = x.withColumn("rank", F.row_number().over(Window.partitionBy("seed").orderBy(F.desc("score"), "node"))).join(seeds, "seed")
    x = x.where((F.col("rank") >= 2 * F.col("friends")) & (F.col("rank") <= 20 * F.col("friends")))
    return powerlaw(x, 1, 10**9, ("seed", "friends"))


def _exponents_sql(how_many=100):
    x = ", ".join(f"x{i} AS (SELECT seed, node, sum(s) AS s FROM (SELECT seed, dst AS node, s * ow * 0.8 AS s FROM x{i - 1} JOIN w ON src = node UNION ALL SELECT seed, node, 0.2 * s FROM x0) GROUP BY 1, 2)" for i in range(1, 6))
    return f"WITH {_WW}, sd AS (SELECT src AS seed, friends FROM (SELECT src, count(*) AS friends FROM e GROUP BY src) WHERE friends BETWEEN 20 AND 30 ORDER BY md5('seed|' || src), src LIMIT {how_many}), x0 AS (SELECT seed, seed AS node, 1.0::DOUBLE AS s FROM sd), {x}, r AS (SELECT seed, s AS score, row_number() OVER (PARTITION BY seed ORDER BY s DESC) AS rank FROM x5 WHERE node <> seed), f AS (SELECT seed, friends, {_FIT} FROM r JOIN sd USING (seed) WHERE rank BETWEEN 2 * friends AND 20 * friends GROUP BY 1, 2)"


R.add("exponents_by_seed", exponents_by_seed, _exponents_sql() + " SELECT * FROM f")
R.add("exp_w04", lambda s, d: exponents_by_seed(s, d, 6), _exponents_sql(6) + " SELECT * FROM f")
R.add("exponent_summary", lambda s, d: exponents_by_seed(s, d).agg(F.round(F.avg("alpha"), 5).alias("mean"), F.round(F.stddev_pop("alpha"), 5).alias("sd"), F.round(F.avg((F.col("alpha") > 1).cast("double")), 6).alias("above_one"), F.count("*").alias("seeds")), _exponents_sql() + " SELECT round(avg(alpha), 5) AS mean, round(stddev_pop(alpha), 5) AS sd, round(avg((alpha > 1)::INT), 6) AS above_one, count(*) AS seeds FROM f")
# one row a seed, whose number is stated
R.add("exp_w05", lambda s, d: exponents_by_seed(s, d).withColumn("place", F.row_number().over(Window.orderBy("alpha", "seed"))), _exponents_sql() + " SELECT *, row_number() OVER (ORDER BY alpha, seed) AS place FROM f")


# short walks against long ones; fetches against bounds
def interpolated_precision(found, truth, retrieved, relevant):
    """Eleven-point curve, mean over seeds: at each recall level the best precision at any rank that has reached it."""
    t = personal.top(truth, relevant).select("seed", "node", F.lit(1).alias("hit"))
    f = personal.top(found, retrieved).join(t, ["seed", "node"], "left").na.fill({"hit": 0})
    upto = Window.partitionBy("seed").orderBy("rank").rowsBetween(Window.unboundedPreceding, 0)
    f = f.withColumn("hits", F.sum("hit").over(upto)).select("seed", (F.col("hits") / relevant).alias("recall"), (F.col("hits") / F.col("rank")).alias("precision"))
    levels = F.explode(F.array(*(F.lit(i / 10) for i in range(11)))).alias("level")
    best = f.select("*", levels).where(F.col("recall") >= F.col("level") - 1e-9).groupBy("seed", "level").agg(F.max("precision").alias("p"))
    every = t.select("seed").distinct().select("seed", levels)
    return every.join(best, ["seed", "level"], "left").groupBy("level").agg(F.avg(F.coalesce("p", F.lit(0.0))).alias("precision"))


def exp_w06(spark, sf_dir, short=5000, long=50_000, how_many=100, retrieved=1000, relevant=100):
    spec = Spec(reps=5, seed=6)
    e = _e(spark, sf_dir, "cobuy")
    v, seeds = save(build_store(e, spec), "visits"), save(personal.pick_seeds(e, how_many), "seeds")
    few = personal.exclude_known(personal.frequencies(save(personal.visit_counts(v, e, seeds, short, spec), "walk")), e)
    many = personal.exclude_known(personal.frequencies(save(personal.visit_counts(v, e, seeds, long, Spec(reps=5, seed=7)), "walk")), e)
    return interpolated_precision(few, many, retrieved, relevant)


R.add("exp_w06", exp_w06)
R.add("iap_curve", exp_w06)
LENGTHS = (100, 200, 500, 1000, 2000, 5000, 10_000, 20_000, 50_000)


def exp_w07(spark, sf_dir, how_many=100):
    """Mean fetches at growing lengths, prefixes of one walk a seed, for R of 5, 10 and 20; beside them the raw charge (visits beyond R, summed over nodes), the summed bound and the closed one, which is null where the fitted exponent is none of the model's."""
    e = _e(spark, sf_dir, "cobuy")
    seeds, out = save(personal.pick_seeds(e, how_many), "seeds"), None
    pi = save(exact.power_iteration(e, rounds=10, seeds=seeds), "pi")
    n, alpha = G.nodes(e).count(), personal.fitted_alpha(e, seeds)
    for r in (5, 10, 20):
        spec = Spec(reps=r, seed=8)
        seen = save(personal.prefix_ledger(build_store(e, spec), e, seeds, LENGTHS, spec), "prefixes")
        seen = seen.groupBy("s").agg(F.avg("f").alias("fetches"), F.avg("raw").alias("raw_charge"))
        large = lambda s: 1 + F.sum(F.when(F.col("score") * s > r / 2, F.col("score") * s).otherwise(0.0))
        sums = pi.groupBy("seed").agg(F.array(*(F.struct(F.lit(s).alias("s"), large(s).alias("b")) for s in LENGTHS)).alias("x")).select(F.explode("x").alias("x")).groupBy("x.s").agg(F.avg("x.b").alias("summed_bound"))
        closed = F.expr(f"CASE WHEN {alpha!r} > 0 AND {alpha!r} < 1 THEN fetch_bound({n}, {r}, {alpha!r}, s) END") if alpha is not None else F.lit(None).cast("double")
        theory.register(spark)
        row = seen.join(sums, "s").select(F.lit(r).alias("r"), "s", "fetches", "raw_charge", "summed_bound", closed.alias("closed_bound"))
        out = row if out is None else out.unionByName(row)
    return out


R.add("exp_w07", exp_w07)
_FBS = f"WITH e AS ({_CB}), w AS (SELECT src, dst, 1 / count(*) OVER (PARTITION BY src) AS ow FROM e), x0 AS (SELECT src AS seed, src AS node, 1.0::DOUBLE AS s FROM (SELECT src, count(*) AS f FROM e GROUP BY src) WHERE f BETWEEN 20 AND 30 ORDER BY md5('seed|' || src), src LIMIT 100), " + ", ".join(f"x{i} AS (SELECT seed, node, sum(s) AS s FROM (SELECT seed, dst AS node, s * ow * 0.8 AS s FROM x{i - 1} JOIN w ON src = node UNION ALL SELECT seed, node, 0.2 * s FROM x0) GROUP BY 1, 2)" for i in range(1, 7)) + " SELECT seed, round(1 + sum(CASE WHEN s * 1000 > 2.5 THEN s * 1000 ELSE 0 END), 6) AS bound FROM x6 GROUP BY seed"
R.add("fetch_bound_summed", lambda s, d: (lambda e: exact.power_iteration(e, rounds=6, seeds=save(personal.pick_seeds(e), "seeds")).groupBy("seed").agg(F.round(1 + F.sum(F.when(F.col("score") * 1000 > 2.5, F.col("score") * 1000).otherwise(0.0)), 6).alias("bound")))(_e(s, d, "cobuy")), _FBS)


# link prediction
LINKS = 10


def _ranks_together(old, later, seeds, rounds, most, popular):
    """Ranks of the later links among the ``most`` best of each method, taken by the tasks that have the seeds' scores."""
    ranks = save(dense.link_ranks(old, later.groupBy("seed").agg(F.collect_list("node").alias("wanted")), 0.2, rounds, most, LINKS), "ranks")
    return {method: ranks.where(F.col("method") == method) for method in dense.METHODS}


def _ranks_joined(old, later, seeds, rounds, most, popular):
    """The same by joins, for graphs that are too large to broadcast."""
    links = personal.top(popular.select(F.lit(0).alias("seed"), F.col("dst").alias("node"), F.col("links").alias("score")), most + 31)
    scores = {
        "pagerank": exact.power_iteration(old, rounds=rounds, seeds=seeds, dangling="seed").select("seed", "node", "score"),
        "alternating": exact.alternating_iteration(old, rounds=rounds, seeds=seeds).select("seed", "node", F.col("auth").alias("score")),
        "hits": exact.alternating_iteration(old, rounds=rounds, seeds=seeds, divide=False).select("seed", "node", F.col("auth").alias("score")),
        "cosine": exact.cosine_authorities(old, exact.cosine_hubs(old, seeds)).select("seed", "node", F.col("auth").alias("score")),
        # the most popular once, as many as a list, a user and their known links together: the rest can't come up
        "popularity": seeds.crossJoin(F.broadcast(links.select("node", F.col("score").cast("double").alias("score")))),
    }
    return {method: save(personal.top(personal.exclude_known(x.where("score > 0"), old), most), method).join(later, ["seed", "node"], "left_semi") for method, x in scores.items()}


def link_prediction(spark, sf_dir, name="buys", rounds=10, tops=(100, 1000)):
    """Mean number of a user's later links among the top of each method's list, over all users who qualify; hub side predicts, known links are left out. ``random`` is the expectation of a list drawn at random."""
    old, new = _snapshots(_e(spark, sf_dir, name))
    popular = old.groupBy("dst").agg(F.count("*").alias("links")).where(F.col("links") >= LINKS)
    later = new.join(popular, "dst", "left_semi").select(F.col("src").alias("seed"), F.col("dst").alias("node"))
    grown = later.groupBy("seed").agg(F.count("*").alias("more"))
    seeds = old.groupBy(F.col("src").alias("seed")).agg(F.count("*").alias("friends")).join(grown, "seed")
    seeds = seeds.where((F.col("friends").between(20, 30)) & (F.col("more") >= 0.5 * F.col("friends")) & (F.col("more") <= F.col("friends")))
    seeds = save(seeds.select("seed", "friends", "more"), "users")
    known, targets = seeds, popular.count()
    seeds = save(seeds.select("seed"), "seeds")
    lists = _ranks_together if dense.fits(old, ways=2) else _ranks_joined
    lists, out = lists(old, later.join(seeds, "seed", "left_semi"), seeds, rounds, max(tops), popular), None
    for method, best in lists.items():
        row = seeds.join(best, "seed", "left").agg(*((F.sum(F.when(F.col("rank") <= k, 1).otherwise(0)) / F.count_distinct("seed")).alias(f"top_{k}") for k in tops)).withColumn("method", F.lit(method))
        out = row if out is None else out.unionByName(row)
    chance = known.agg(*(F.avg(F.col("more") * F.least(F.lit(1.0), k / (targets - F.col("friends")))).alias(f"top_{k}") for k in tops)).withColumn("method", F.lit("random"))
    return out.unionByName(chance)


R.add("exp_w08", link_prediction)
R.add("captured_links", lambda s, d: link_prediction(s, d, "cobuy", tops=(20, 100)))


# maintenance
def exp_w09(spark, sf_dir):
    e = _e(spark, sf_dir, "handoff").withColumn("ord", F.conv(F.substring(F.md5(F.concat_ws("|", "src", "dst")), 1, 12), 16, 10).cast("long"))
    m = e.count()
    return update.replay(e, Spec(reps=2, seed=9), [m // 2, m // 2 + m // 8, m])


R.add("exp_w09", exp_w09)


def exp_w10(spark, sf_dir):
    """Removal of a random sample of edges: walks and steps against the expectation's bound."""
    spec = Spec(reps=2, seed=10)
    e = _e(spark, sf_dir, "cobuy")
    gone = e.where(F.substring(F.md5(F.concat_ws("|", "src", "dst")), 1, 2) == "7f").select(F.lit("-").alias("op"), "src", "dst", "ord")
    ledger = update.WalkStore.create(e, spec).apply(gone)
    n, m = G.nodes(e).count(), e.count()
    return ledger.select("edges_gone", "walks_rerouted", "steps_redone", F.round(F.col("edges_gone") * (n * spec.reps / (m * spec.eps**2)), 6).alias("bound_steps"))


_W10 = "WITH RECURSIVE " + update.update_sql(f"SELECT src, dst, ord FROM ({_CB})", f"SELECT '-' AS op, src, dst, ord FROM ({_CB}) WHERE substr(md5(src || '|' || dst), 1, 2) = '7f'", Spec(reps=2, seed=10)) + " SELECT (SELECT count(*) FROM gone) AS edges_gone, (SELECT count(*) FROM c1) AS walks_rerouted, (SELECT count(*) FROM r1) AS steps_redone, round((SELECT count(*) FROM gone) * ((SELECT count(*) FROM n0) * 2 / ((SELECT count(*) FROM e0) * 0.04::DOUBLE)), 6) AS bound_steps"
R.add("exp_w10", exp_w10, _W10)
R.add("deletion_bound", exp_w10, _W10)


def exp_w12(spark, sf_dir):
    """One adversarial edge from the centre into the cycle: rerouted walks grow with the graph."""
    out = None
    for size in (10, 100, 1000):
        spec = Spec(reps=2, seed=12)
        e = save(trap(spark, sf_dir, size).select("src", "dst", "ord"), "trap")
        ch = spark.createDataFrame([("+", 0, 1, 10**9)], "op string, src long, dst long, ord long")
        ledger = update.WalkStore.create(e, spec).apply(ch)
        row = ledger.select(F.lit(size).alias("size"), F.lit(3 * size + 1).alias("n"), "walks_rerouted", "steps_redone")
        out = row if out is None else out.unionByName(row)
    return out


R.add("exp_w12", exp_w12)
R.add("exp_w13", R.queries["rem2_numbers"], R.sql["rem2_numbers"])
R.add("exp_w14", R.queries["cost_table"], R.sql["cost_table"])


def exp_w15(spark, sf_dir):
    """Maintenance of alternating walks over the whole history of two graphs."""
    out = None
    for name in ("cobuy", "buys"):
        e = _e(spark, sf_dir, name)
        row = update.replay(e, Spec(reps=1, seed=15, kind="alternating"), update.whole_history(e.count())).select(F.lit(name).alias("graph"), "*")
        out = row if out is None else out.unionByName(row)
    return out


R.add("exp_w15", exp_w15)


def exp_w16(spark, sf_dir, name="cobuy", reps=(1, 2, 5, 10, 20)):
    """Error of the walk-store estimate against exact scores, by R."""
    e = _e(spark, sf_dir, name)
    truth, n, out = save(exact.power_iteration(e, rounds=25).select("node", F.col("score").alias("t")), "truth"), G.nodes(e).count(), None
    # the walks of a smaller R are the first ones of the largest
    seen = build_store(e, Spec(reps=max(reps), seed=16)).groupBy("node").agg(*(F.count_if(F.col("rep") < r).alias(f"r{r}") for r in reps))
    seen = save(seen, "counts")
    for r in reps:
        c = seen.select("node", (F.col(f"r{r}") * 0.2 / (n * r)).alias("score"))
        x = truth.join(c, "node", "left").na.fill(0.0)
        row = x.agg(F.round(F.sum(F.abs(F.col("score") - F.col("t"))), 9).alias("l1"), F.round(F.max(F.abs(F.col("score") - F.col("t"))), 10).alias("linf"), F.round(F.corr("score", "t"), 9).alias("corr"), F.round(F.avg((F.abs(F.col("score") / F.col("t") - 1) > 0.5).cast("double")), 9).alias("share_off_by_half")).withColumn("r", F.lit(r))
        out = row if out is None else out.unionByName(row)
    return out


def _w16_sql(name="cobuy", reps=(1, 2, 5, 10, 20)):
    from incwalk.plans.walks import walks_sql

    e = f"SELECT src, dst, ord FROM ({edges_sql(name)})"
    truth = f"e AS ({e}), w AS (SELECT src, dst, 1 / count(*) OVER (PARTITION BY src) AS ow FROM e), n AS (SELECT src AS node FROM e UNION SELECT dst FROM e), x0 AS (SELECT node, 1 / (SELECT count(*) FROM n) AS s FROM n), " + ", ".join(f"x{i} AS (SELECT node, sum(s) AS s FROM (SELECT dst AS node, s * ow * 0.8 AS s FROM x{i - 1} JOIN w ON src = node UNION ALL SELECT node, 0.2 * s FROM x0) GROUP BY node)" for i in range(1, 26))
    counts = " UNION ALL ".join(f"SELECT {r} AS r, * FROM (WITH RECURSIVE {walks_sql(e, Spec(reps=r, seed=16))} SELECT node, count(*) AS k FROM w0 GROUP BY node)" for r in reps)
    return f"WITH {truth}, c AS ({counts}), j AS (SELECT r, s AS t, coalesce(k, 0) * 0.2 / ((SELECT count(*) FROM n) * r) AS score FROM (SELECT node, s, unnest({list(reps)}) AS r FROM x25) LEFT JOIN c USING (node, r)) SELECT r, round(sum(abs(score - t)), 9) AS l1, round(max(abs(score - t)), 10) AS linf, round(corr(score, t), 9) AS corr, round(avg((abs(score / t - 1) > 0.5)::INT), 9) AS share_off_by_half FROM j GROUP BY r"


R.add("exp_w16", exp_w16, _w16_sql())
R.add("score_errors", exp_w16, _w16_sql())
R.add("tail_share", lambda s, d: exp_w16(s, d).select("r", "share_off_by_half"), f"SELECT r, share_off_by_half FROM ({_w16_sql()})")


LEMMA7, L7_WALKS, L7_STEPS = Spec(reps=5, seed=17), 300, 20


def lemma7_distance(spark, sf_dir):
    """Of each seed: summed distance between mean visits of walks of length s and s times the exact scores; the bound is two over eps."""
    e = _e(spark, sf_dir, "cobuy")
    seeds = save(personal.pick_seeds(e), "seeds")
    many = seeds.select("seed", F.explode(F.sequence(F.lit(0), F.lit(L7_WALKS - 1))).alias("walk")).select("seed", F.concat_ws(":", "seed", "walk").alias("id"))
    pi = exact.power_iteration(e, rounds=25, seeds=seeds).select("seed", "node", "score")
    mean = _short_walks(many, e, L7_STEPS, LEMMA7).groupBy("seed", "node").agg((F.count("*") / L7_WALKS).alias("visits"))
    gap = F.sum(F.abs(F.col("visits") - L7_STEPS * F.col("score")))
    return pi.join(mean, ["seed", "node"], "full").na.fill(0.0).groupBy("seed").agg(F.round(gap, 8).alias("distance")).withColumn("bound", F.lit(2 / LEMMA7.eps))


def _short_walks(starts, e, length, spec):
    """Visits (id, seed, node) of walks of ``length`` visits: all advance together, on a broadcast adjacency where that may be."""
    from incwalk.functions import coins

    if on_broadcast(e, spec):
        return _short_walks_local(starts, e, length, spec)
    adj, deg = G.slots(e), G.outdegrees(e)
    x = starts.select("id", "seed", F.col("seed").alias("node"))
    out = x
    for t in range(1, length):
        a, b = coins.coin(spec.seed, "short", F.col("id"), F.lit(0), F.lit(t))
        x = x.join(deg, x.node == deg.src, "left").select("id", "seed", "node", (a < coins.threshold(spec.eps)).alias("reset"), coins.slot(b, F.coalesce("deg", F.lit(1))).alias("slot"))
        x = x.join(adj.select(F.col("src").alias("node"), "slot", "dst"), ["node", "slot"], "left").select("id", "seed", F.when(F.col("reset") | F.col("dst").isNull(), F.col("seed")).otherwise(F.col("dst")).alias("node"))
        if t % 4 == 0:
            x = save(x, "short")
        out = out.unionByName(x)
    return out


def _short_walks_local(starts, e, length, spec):
    from incwalk.functions import coins

    held, stop = e.sparkSession.sparkContext.broadcast(Adjacency(e, False)), coins.threshold(spec.eps)

    def run(batches):
        g = held.value
        for batch in batches:
            ids, seed = batch.column("id"), batch.column("seed").to_numpy()
            names, node = ids.to_pylist(), seed
            for t in range(length):
                if t:
                    a, b = coins.python_coins(spec.seed, "short", names, 0, np.full(len(seed), t))
                    place = g.find(node)
                    deg, to = advance(g, place, np.zeros(len(seed), np.int8), b, False)
                    goes = (a >= stop) & (deg > 0)
                    node = seed.copy()
                    node[goes] = g.nodes[to[goes]]
                yield pa.RecordBatch.from_arrays([ids, pa.array(seed), pa.array(node)], names=["id", "seed", "node"])

    return dealt(starts.select("id", "seed"), "id").mapInArrow(run, "id string, seed long, node long")


def _lemma7_sql():
    """The same short walks by the same coins, all advancing together."""
    from incwalk.functions import coins

    h = coins.sql_digest(LEMMA7.seed, "short", "id", "0", "(t + 1)")
    scores = ", ".join(f"p{i} AS (SELECT seed, node, sum(s) AS s FROM (SELECT seed, dst AS node, s * ow * 0.8 AS s FROM p{i - 1} JOIN w ON src = node UNION ALL SELECT seed, node, 0.2 * s FROM p0) GROUP BY 1, 2)" for i in range(1, 26))
    return f"""WITH RECURSIVE e AS ({_CB}), w AS (SELECT src, dst, 1 / count(*) OVER (PARTITION BY src) AS ow FROM e), d AS (SELECT src, count(*) AS deg FROM e GROUP BY 1),
a AS (SELECT src, dst, row_number() OVER (PARTITION BY src ORDER BY ord, dst) - 1 AS slot FROM e),
sd AS (SELECT src AS seed FROM d WHERE deg BETWEEN 20 AND 30 ORDER BY md5('seed|' || src), src LIMIT 100),
p0 AS (SELECT seed, seed AS node, 1.0::DOUBLE AS s FROM sd), {scores},
x AS (SELECT seed, seed || ':' || k AS id, seed AS node, 0 AS t FROM sd, range({L7_WALKS}) r(k) UNION ALL
  SELECT seed, id, CASE WHEN {coins.sql_a("h")} < {coins.threshold(LEMMA7.eps)} OR a.dst IS NULL THEN seed ELSE a.dst END, t + 1
  FROM (SELECT *, {h} AS h FROM x WHERE t < {L7_STEPS - 1}) y LEFT JOIN d ON d.src = y.node LEFT JOIN a ON a.src = y.node AND a.slot = ({coins.sql_b("y.h")} * d.deg) >> 32)
SELECT seed, round(sum(abs(coalesce(v, 0) - {L7_STEPS} * coalesce(s, 0))), 8) AS distance, {2 / LEMMA7.eps}::DOUBLE AS bound
FROM p25 FULL JOIN (SELECT seed, node, count(*) / {L7_WALKS} AS v FROM x GROUP BY 1, 2) USING (seed, node) GROUP BY seed"""


R.add("lemma7_distance", lemma7_distance, _lemma7_sql())
