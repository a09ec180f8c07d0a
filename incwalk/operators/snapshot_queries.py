"""Snapshots of several graphs side by side: the arrival, degree and power-law experiments, updates in real and permuted order, a sliding window, agreement of rankings and the size of a store."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from incwalk.functions.theory import harmonic
from incwalk.operators import measure_queries as M
from incwalk.operators.registry_of import Registry
from incwalk.plans import dense, exact, update
from incwalk.plans import graph as G
from incwalk.plans.ranking import numbered
from incwalk.plans.walks import Spec, build_store, walks_sql
from incwalk.sources.graphs import edges, edges_sql
from incwalk.store import discard, save

R = Registry()
#: Graph, whether its arrivals come in permuted order, and the percentages of arrivals at which it is cut.
CUTS = (("words", False, (50, 80)), ("handoff", False, (25, 50, 75)), ("cobuy", False, (50,)), ("cobuy", True, (50,)), ("words", True, (50,)))
FITTED = ("words", "pref", "near", "cobuy")


def _digest():
    return F.md5(F.concat_ws("|", "src", "dst"))


def in_order(spark, sf_dir, name: str, permuted: bool = False) -> DataFrame:
    """``(src, dst, ord, t)``: arrivals numbered from 1, by time or by a digest of the edge."""
    return numbered(edges(spark, sf_dir, name).select("src", "dst", "ord"), _order(permuted), "t")


def _order(permuted: bool):
    return [*([_digest()] if permuted else [F.asc("ord")]), F.asc("src"), F.asc("dst")]


def _label(name: str, permuted: bool) -> str:
    return f"{name} {'permuted ' if permuted else ''}"


def _in_order_sql(name: str, permuted: bool = False) -> str:
    first = "md5(src || '|' || dst)" if permuted else "ord"
    return f"SELECT src, dst, ord, row_number() OVER (ORDER BY {first}, src, dst) AS t FROM ({edges_sql(name)})"


def before_cut(cut, m: int, t="t"):
    """Whether arrival ``t`` of ``m`` is among the first ``cut`` hundredths; the product is a long, which 32 bits would not hold from 27 million arrivals on."""
    return F.col(t) <= F.expr(f"{cut} * {m}L div 100")


def snapshots(spark, sf_dir, of=CUTS) -> DataFrame:
    """``(g, src, dst, old)``: every arrival of every graph once for each of its cuts."""
    out = None
    for name, permuted, cuts in of:
        x = save(in_order(spark, sf_dir, name, permuted), "arrivals")
        label = F.concat(F.lit(_label(name, permuted)), F.col("cut").cast("string"))
        m = x.count()
        x = x.select("src", "dst", "t", F.explode(F.array(*map(F.lit, cuts))).alias("cut"))
        x = x.select(label.alias("g"), "src", "dst", before_cut("cut", m).alias("old"))
        out = x if out is None else out.unionByName(x)
    return save(out, "snapshots")


def scores_by_graph(e: DataFrame, rounds: int = 10, eps: float = 0.2) -> DataFrame:
    """``(g, node, score)``: power iteration on all graphs ``g`` of ``e`` in the same jobs."""
    w = save(e.select("g", "src", "dst").join(e.groupBy("g", "src").agg((1 / F.count("*")).alias("w")), ["g", "src"]), "weighted")
    n = e.select("g", F.col("src").alias("node")).union(e.select("g", "dst")).distinct()
    tele = save(n.join(n.groupBy("g").agg((1 / F.count("*")).alias("tele")), "g"), "teleport")
    x = tele.select("g", "node", F.col("tele").alias("score"))
    for i in range(1, rounds + 1):
        moved = x.withColumnRenamed("node", "src").join(w, ["g", "src"]).select("g", F.col("dst").alias("node"), (F.col("score") * F.col("w") * (1 - eps)).alias("score"))
        x = moved.unionByName(tele.select("g", "node", (F.col("tele") * eps).alias("score"))).groupBy("g", "node").agg(F.sum("score").alias("score"))
        if i % exact.CUT == 0:
            x = save(x, "scores")
    return x


def _rounds_sql(rounds: int = 10) -> str:
    """CTEs ``w``, ``n`` and ``x0`` to the last round, over edges ``o`` (g, src, dst)."""
    steps = ", ".join(f"x{i} AS (SELECT g, node, sum(s) AS s FROM (SELECT w.g, dst AS node, s * ow * 0.8 AS s FROM x{i - 1} x JOIN w ON w.src = x.node AND w.g = x.g UNION ALL SELECT g, node, 0.2 * s FROM x0) GROUP BY 1, 2)" for i in range(1, rounds + 1))
    return f"w AS (SELECT g, src, dst, 1 / count(*) OVER (PARTITION BY g, src) AS ow FROM o), n AS (SELECT g, src AS node FROM o UNION SELECT g, dst FROM o), x0 AS (SELECT g, node, 1 / count(*) OVER (PARTITION BY g) AS s FROM n), {steps}"


def _snapshots_sql() -> str:
    parts = [f"SELECT '{name} {'permuted ' if permuted else ''}{cut}' AS g, src, dst, t <= ({cut} * (count(*) OVER ())) // 100 AS old FROM ({_in_order_sql(name, permuted)})" for name, permuted, cuts in CUTS for cut in cuts]
    return "z AS (" + " UNION ALL ".join(parts) + "), o AS (SELECT g, src, dst FROM z WHERE old), d AS (SELECT g, src, count(*) AS d FROM o GROUP BY 1, 2)"


def _arrivals_joined(z: DataFrame) -> DataFrame:
    old, new = z.where("old"), z.where("NOT old")
    d = old.groupBy("g", F.col("src").alias("node")).agg(F.count("*").alias("d"))
    x = new.select("g", F.col("src").alias("node")).join(scores_by_graph(old).join(d, ["g", "node"]), ["g", "node"])
    x = x.groupBy("g").agg(F.avg(F.col("score") / F.col("d")).alias("mean"), F.count("*").alias("arrivals"))
    return x.join(old.groupBy("g").agg(F.count("*").alias("m")), "g").select("g", "m", "arrivals", (F.col("m") * F.col("mean")).alias("mx"))


def _first_by_digest(e: DataFrame, k: int):
    """Whether an edge is among the ``k`` first by digest, source and target: the last of them is looked up among the edges whose digests begin as its own does."""
    head, seen = F.substring(_digest(), 1, 4), 0
    for h, n in sorted(map(tuple, e.groupBy(head).count().collect())):
        if seen + n >= k > 0:
            d, src, dst = sorted(map(tuple, e.where(head == h).select(_digest(), "src", "dst").collect()))[k - seen - 1]
            return (_digest() < d) | (_digest() == d) & ((F.col("src") < src) | (F.col("src") == src) & (F.col("dst") <= dst))
        seen += n
    return F.lit(False)


def _arrivals_on_arrays(e: DataFrame, of) -> DataFrame:
    """The cuts of one graph, whose edges are made once, in either order; a bit of ``old`` for each cut."""
    m, names, old = e.count(), [], F.lit(0)
    for name, permuted, cuts in of:
        for cut in cuts:
            first = _first_by_digest(e, cut * m // 100) if permuted else before_cut(cut, m)
            old = old + first.cast("int") * (1 << len(names))
            names.append(f"{_label(name, permuted)}{cut}")
    x = numbered(e, _order(False), "t")
    x = save(x.select("src", "dst", old.cast("byte").alias("old")), "arrivals")
    out = dense.arrival_means(x, names)
    discard(x)  # read by now
    return out


def arrivals_by_graph(spark, sf_dir):
    """m times the mean of score over out-degree at the sources of arrivals, near 1 where they come in random order. Graphs of a checked size are broadcast, one at a time."""
    out = None
    for name in dict.fromkeys(cut[0] for cut in CUTS):
        of = [cut for cut in CUTS if cut[0] == name]
        e = save(edges(spark, sf_dir, name).select("src", "dst", "ord"), "edges")
        row = _arrivals_on_arrays(e, of) if dense.fits(e, ways=2) else _arrivals_joined(snapshots(spark, sf_dir, of))
        row = save(row, "means")
        discard(e)
        out = row if out is None else out.unionByName(row)
    return out.select("g", "m", "arrivals", F.round("mx", 6).alias("mx"))


R.add("exp_w01_graphs", arrivals_by_graph, f"WITH {_snapshots_sql()}, {_rounds_sql()}, m AS (SELECT g, count(*) AS m FROM o GROUP BY 1) SELECT z.g, any_value(m) AS m, count(*) AS arrivals, round(any_value(m) * avg(s / d), 6) AS mx FROM z JOIN d ON d.g = z.g AND d.src = z.src JOIN x10 ON x10.g = z.g AND node = z.src JOIN m ON m.g = z.g WHERE NOT old GROUP BY z.g")


def degrees_by_graph(spark, sf_dir):
    """Shares of arriving and of existing edges whose source has at most d edges. Windows run over a row a degree."""
    z = snapshots(spark, sf_dir)
    d = z.where("old").groupBy("g", "src").agg(F.count("*").alias("d"))
    e = d.groupBy("g", "d").agg(F.sum("d").alias("ends"))
    a = z.where("NOT old").join(d, ["g", "src"]).groupBy("g", "d").agg(F.count("*").alias("arrivals"))
    x = e.join(a, ["g", "d"], "left").na.fill(0)
    run = Window.partitionBy("g").orderBy("d").rowsBetween(Window.unboundedPreceding, 0)
    share = lambda c: F.round(F.sum(c).over(run) / F.sum(c).over(Window.partitionBy("g")), 9)
    return x.select("g", "d", share("arrivals").alias("arriving"), share("ends").alias("existing"))


R.add("exp_w02_graphs", degrees_by_graph, f"WITH {_snapshots_sql()}, e AS (SELECT g, d, sum(d) AS k FROM d GROUP BY 1, 2), a AS (SELECT z.g, d.d, count(*) AS k FROM z JOIN d ON d.g = z.g AND d.src = z.src WHERE NOT old GROUP BY 1, 2) SELECT e.g, e.d, round(sum(coalesce(a.k, 0)) OVER (PARTITION BY e.g ORDER BY e.d) / sum(coalesce(a.k, 0)) OVER (PARTITION BY e.g), 9) AS arriving, round(sum(e.k) OVER (PARTITION BY e.g ORDER BY e.d) / sum(e.k) OVER (PARTITION BY e.g), 9) AS existing FROM e LEFT JOIN a ON a.g = e.g AND a.d = e.d")


def exponents_by_graph(spark, sf_dir, low: int = 10, high: int = 1000):
    """Power laws of in-degree and score, between two ranks, on several graphs. Ranks beyond ``high`` never leave the partition they are in."""
    e = None
    for name in FITTED:
        x = edges(spark, sf_dir, name).select(F.lit(name).alias("g"), "src", "dst")
        e = x if e is None else e.unionByName(x)
    e = save(e, "graphs")
    v = e.groupBy("g", F.col("dst").alias("node")).agg(F.count("*").cast("double").alias("score")).withColumn("vector", F.lit("in-degree"))
    v = v.unionByName(scores_by_graph(e).select("g", "node", F.round("score", 14).alias("score"), F.lit("pagerank").alias("vector")))
    v = v.withColumn("rank", F.row_number().over(Window.partitionBy("g", "vector").orderBy(F.desc("score"), "node"))).where(F.col("rank") <= high)
    return M.powerlaw(v, low, high, ("g", "vector"))


_FITTED = " UNION ALL ".join(f"SELECT '{g}' AS g, src, dst FROM ({edges_sql(g)})" for g in FITTED)
R.add("exp_w03_graphs", exponents_by_graph, f"WITH o AS ({_FITTED}), {_rounds_sql()}, v AS (SELECT g, 'in-degree' AS vector, count(*)::DOUBLE AS score FROM o GROUP BY g, dst UNION ALL SELECT g, 'pagerank', s FROM x10), r AS (SELECT *, row_number() OVER (PARTITION BY g, vector ORDER BY score DESC) AS rank FROM v) SELECT g, vector, {M._FIT} FROM r WHERE rank BETWEEN 10 AND 1000 GROUP BY 1, 2")


def update_orders(spark, sf_dir, sizes=(1, 10, 100, 1000)):
    """Work of batches of growing size after the first half of the arrivals, in real and in permuted order, beside the bound for random order."""
    spec, out = Spec(reps=2, seed=9), None
    for name in ("handoff", "cobuy"):
        for permuted in (False, True):
            e = save(in_order(spark, sf_dir, name, permuted), "history")
            m, n = e.count(), G.nodes(e).count()
            at = m // 2
            store = update.WalkStore.create(e.where(F.col("t") <= at).select("src", "dst", "ord"), spec)
            for size in sizes:
                to = min(at + size, m)
                ledger = store.apply(e.where((F.col("t") > at) & (F.col("t") <= to)).select(F.lit("+").alias("op"), "src", "dst", "ord"))
                bound = n * spec.reps / spec.eps**2 * (harmonic(to) - harmonic(at))
                row = ledger.select(F.lit(name).alias("graph"), F.lit("permuted" if permuted else "real").alias("order"), F.lit(to - at).alias("batch"), "walks_rerouted", "steps_redone", F.lit(round(bound, 3)).alias("bound_steps"), "visits_read")
                out, at = row if out is None else out.unionByName(row), to
    return out


R.add("exp_w09_orders", update_orders)
SLIDE = Spec(reps=2, seed=18)


def sliding_expiry(spark, sf_dir):
    """The visits after a window over arrivals slides by half its length: the older half leaves and the next arrives, in one batch."""
    e = save(in_order(spark, sf_dir, "handoff"), "history")
    m = e.count()
    store = update.WalkStore.create(e.where(F.col("t") <= m // 2).select("src", "dst", "ord"), SLIDE)
    gone = e.where(F.col("t") <= m // 4).select(F.lit("-").alias("op"), "src", "dst", "ord")
    new = e.where((F.col("t") > m // 2) & (F.col("t") <= 3 * m // 4)).select(F.lit("+").alias("op"), "src", "dst", "ord")
    store.apply(gone.unionByName(new))
    return store.visits().select("src", "rep", "pos", "node", "ended")


_HO = f"SELECT src, dst, ord, t, count(*) OVER () AS m FROM ({_in_order_sql('handoff')})"
R.add("exp_w10_sliding", sliding_expiry, "WITH RECURSIVE " + update.update_sql(f"SELECT src, dst, ord FROM ({_HO}) WHERE t <= m // 2", f"SELECT CASE WHEN t <= m // 4 THEN '-' ELSE '+' END AS op, src, dst, ord FROM ({_HO}) WHERE t <= m // 4 OR (t > m // 2 AND t <= 3 * m // 4)", SLIDE) + " SELECT src, rep, pos, node, ended FROM w1")
R.add("exp_w16_words", lambda s, d: M.exp_w16(s, d, "words", (1, 5)), M._w16_sql("words", (1, 5)))


def rank_agreement(spark, sf_dir, reps=(1, 5, 20)):
    """The walk-store ranking against the exact one: shares of common nodes among the top, rank correlation over all nodes, and Kendall's tau of the exact top 100."""
    e = save(edges(spark, sf_dir, "cobuy").select("src", "dst", "ord"), "edges")
    truth = exact.power_iteration(e, rounds=25).select("node", F.round("score", 13).alias("score"))
    truth, out = save(numbered(truth, [F.desc("score"), F.asc("node")], "i").select("node", "i"), "truth"), None
    for r in reps:
        found = build_store(e, Spec(reps=r, seed=16)).groupBy("node").agg(F.count("*").alias("visits"))  # each node starts walks, so none is missing
        x = save(numbered(found, [F.desc("visits"), F.asc("node")], "j").join(truth, "node").select("i", "j"), "ranks")
        top = x.where("i <= 100")  # the stated hundred: their pairs are 4,950
        pairs = top.alias("a").join(F.broadcast(top.alias("b")), F.expr("a.i < b.i")).agg(F.avg(F.when(F.expr("a.j < b.j"), 1.0).otherwise(-1.0)).alias("tau"))
        share = lambda k: F.round(F.count_if((F.col("i") <= k) & (F.col("j") <= k)) / k, 9).alias(f"top_{k}")
        row = x.agg(share(20), share(100), F.round(F.corr(F.col("i").cast("double"), F.col("j").cast("double")), 9).alias("spearman")).crossJoin(pairs).select(F.lit(r).alias("r"), "top_20", "top_100", "spearman", F.round("tau", 9).alias("tau_100"))
        out = row if out is None else out.unionByName(row)
    return out


def _agreement_sql(reps=(1, 5, 20)) -> str:
    e = f"SELECT src, dst, ord FROM ({edges_sql('cobuy')})"
    found = " UNION ALL ".join(f"SELECT {r} AS r, * FROM (WITH RECURSIVE {walks_sql(e, Spec(reps=r, seed=16))} SELECT node, count(*) AS visits FROM w0 GROUP BY node)" for r in reps)
    return f"WITH o AS (SELECT 0 AS g, src, dst FROM ({e})), {_rounds_sql(25)}, f AS ({found}), t AS (SELECT node, row_number() OVER (ORDER BY round(s, 13) DESC, node) AS i FROM x25), j AS (SELECT r, i, row_number() OVER (PARTITION BY r ORDER BY visits DESC, f.node) AS j FROM f JOIN t ON t.node = f.node), k AS (SELECT a.r, avg(CASE WHEN a.j < b.j THEN 1 ELSE -1 END) AS tau FROM j a JOIN j b ON a.r = b.r AND a.i < b.i WHERE a.i <= 100 AND b.i <= 100 GROUP BY 1) SELECT j.r, round(count(*) FILTER (i <= 20 AND j <= 20) / 20, 9) AS top_20, round(count(*) FILTER (i <= 100 AND j <= 100) / 100, 9) AS top_100, round(corr(i, j), 9) AS spearman, round(any_value(tau), 9) AS tau_100 FROM j JOIN k ON k.r = j.r GROUP BY 1"


R.add("rank_agreement", rank_agreement, _agreement_sql())
SIZED = Spec(reps=2, seed=1)


def store_size(spark, sf_dir):
    """Rows that a store holds and rounds that it took; a round shuffles the walks alive in it."""
    v = update.WalkStore.create(edges(spark, sf_dir, "cobuy"), SIZED).visits()
    return v.groupBy("pos").agg(F.count("*").alias("alive")).agg(F.sum("alive").alias("visits"), F.max("alive").alias("walks"), F.count("*").alias("rounds"), F.sum(F.when(F.col("pos") > 0, F.col("alive")).otherwise(0)).alias("rows_moved"))


R.add("store_size", store_size, f"WITH RECURSIVE {walks_sql(edges_sql('cobuy'), SIZED)}, p AS (SELECT pos, count(*) AS alive FROM w0 GROUP BY 1) SELECT sum(alive)::BIGINT AS visits, max(alive) AS walks, count(*) AS rounds, sum(CASE WHEN pos > 0 THEN alive ELSE 0 END)::BIGINT AS rows_moved FROM p")


def store_bytes(spark, sf_dir):
    """Stored visits, layers and bytes of a store's files, before and after a batch and its compaction."""
    e = save(in_order(spark, sf_dir, "cobuy"), "history")
    m, rows = e.count(), []
    store = update.WalkStore.create(e.where(F.col("t") <= m - m // 10).select("src", "dst", "ord"), SIZED)
    rows.append(("built", *store.size().values()))
    store.apply(e.where(F.col("t") > m - m // 10).select(F.lit("+").alias("op"), "src", "dst", "ord"))
    rows.append(("changed", *store.size().values()))
    store.compact()
    rows.append(("compacted", *store.size().values()))
    return spark.createDataFrame(rows, "state string, live_visits long, stored_visits long, layers long, bytes long")


R.add("store_bytes", store_bytes)
