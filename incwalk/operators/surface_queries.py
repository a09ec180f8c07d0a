"""The engine's SQL surface, its data source and table function, bucketed tables, and walks by scans."""

from __future__ import annotations

import uuid

from pyspark.sql import functions as F

from incwalk.engine import Engine
from incwalk.functions.tables import gini
from incwalk.operators import walk_queries as W
from incwalk.operators.registry_of import Registry
from incwalk.plans.scans import scan_walks
from incwalk.plans.walks import Spec
from incwalk.sources.coin_edges import coin_edges_sql
from incwalk.sources.graphs import edges, edges_sql
from incwalk.store import fresh_path

R = Registry()


def _name():
    """A view of one's own for each call, so that results of earlier calls keep theirs."""
    return "g" + uuid.uuid4().hex


def engine_pagerank(spark, sf_dir):
    store = Engine(spark).edges(_name(), edges(spark, sf_dir, "cobuy")).store(reps=2, seed=1)
    return store.pagerank().select("node", "visits", F.round("score", 12).alias("score"))


R.add("engine_pagerank", engine_pagerank, W.R.sql["pagerank_counts"])


def engine_update(spark, sf_dir):
    """Estimates in SQL after a batch through the facade."""
    base, changes = W._scenario(spark, sf_dir, ("00",), ("01",))
    store = Engine(spark).edges(_name(), base).store(reps=W.SPEC.reps, seed=W.SPEC.seed)
    store.update(changes)
    return spark.sql(f"SELECT v.node, count(*) AS visits, count(DISTINCT v.src, v.rep) AS walks, coalesce(any_value(d), 0) AS outdeg FROM visits_{store.name} v LEFT JOIN (SELECT src, count(*) AS d FROM edges_{store.name} GROUP BY src) e ON e.src = v.node GROUP BY v.node")


R.add("engine_update", engine_update, W._update_sql(("00",), ("01",)) + " SELECT node, count(*) AS visits, count(DISTINCT (w1.src, rep)) AS walks, coalesce(any_value(deg), 0) AS outdeg FROM w1 LEFT JOIN dg ON dg.src = w1.node GROUP BY node")


def udtf_steps(spark, sf_dir):
    """Steps of all stored walks, by a table function joined laterally."""
    store = Engine(spark).edges(_name(), edges(spark, sf_dir, "cobuy")).store(reps=2, seed=1)
    return spark.sql(f"SELECT w.src, w.rep, s.pos, s.node, s.next FROM segments_{store.name} w, LATERAL segment_steps(w.path) s")


R.add("udtf_steps", udtf_steps, f"{W._W} SELECT src, rep, pos, node, lead(node) OVER (PARTITION BY src, rep ORDER BY pos) AS next FROM w0")


def lateral_top(spark, sf_dir):
    """The three latest edges of each customer with an account over 9000, by a lateral subquery."""
    name = _name()
    edges(spark, sf_dir, "cobuy").createOrReplaceTempView(f"edges_{name}")
    spark.read.parquet(f"{sf_dir}/customer.parquet").createOrReplaceTempView(f"customer_{name}")
    return spark.sql(f"SELECT c_custkey, dst, ord FROM customer_{name}, LATERAL (SELECT dst, ord FROM edges_{name} WHERE src = c_custkey ORDER BY ord DESC, dst LIMIT 3) WHERE c_acctbal > 9000")


R.add("lateral_top", lateral_top, f"SELECT c_custkey, dst, ord FROM customer, LATERAL (SELECT dst, ord FROM ({edges_sql('cobuy')}) WHERE src = c_custkey ORDER BY ord DESC, dst LIMIT 3) WHERE c_acctbal > 9000")


def uniform_edges(spark, sf_dir):
    Engine(spark)
    return spark.read.format("coin_edges").option("nodes", 500).option("edges", 20_000).option("seed", 19).load()


R.add("uniform_edges", uniform_edges, coin_edges_sql(500, 20_000, 19))


def degree_gini(spark, sf_dir):
    """Inequality of out-degrees: a grouped pandas aggregate over histograms, whose groups have a row for each distinct degree."""
    out = None
    for name in ("cobuy", "buys", "handoff"):
        h = edges(spark, sf_dir, name).groupBy("src").agg(F.count("*").alias("d")).groupBy("d").agg(F.count("*").alias("k")).withColumn("graph", F.lit(name))
        out = h if out is None else out.unionByName(h)
    return out.groupBy("graph").agg(gini()("d", "k").alias("g")).select("graph", F.round("g", 9).alias("gini"))


_H = " UNION ALL ".join(f"SELECT '{g}' AS graph, count(*) AS d FROM ({edges_sql(g)}) GROUP BY src" for g in ("cobuy", "buys", "handoff"))
R.add("degree_gini", degree_gini, f"SELECT graph, round(2 * sum(i * d) / (count(*) * sum(d)) - (count(*) + 1) / count(*), 9) AS gini FROM (SELECT graph, d, row_number() OVER (PARTITION BY graph ORDER BY d) AS i FROM ({_H})) GROUP BY 1")


def bucketed(spark, sf_dir, buckets: int = 8):
    """Edges and degrees written in the same buckets by source: their join moves no row."""
    e, names = edges(spark, sf_dir, "cobuy").select("src", "dst", "ord"), []
    for rows in (e, e.groupBy("src").agg(F.count("*").alias("deg"))):
        names.append(f"incwalk_{uuid.uuid4().hex}")
        rows.write.bucketBy(buckets, "src").sortBy("src").option("path", fresh_path(spark, "bucketed")).saveAsTable(names[-1])
    return spark.table(names[0]).join(spark.table(names[1]).hint("merge"), "src").select("src", "dst", "deg")


R.add("bucketed_join", bucketed, f"SELECT src, dst, count(*) OVER (PARTITION BY src) AS deg FROM ({edges_sql('cobuy')})")
SCAN = Spec(reps=2, seed=20)
R.add("scan_walks", lambda s, d: scan_walks(edges(s, d, "cobuy").select("src", "dst", "ord"), SCAN)[0].groupBy("node").agg(F.count("*").alias("visits")))
R.add("scan_ledger", lambda s, d: scan_walks(edges(s, d, "cobuy").select("src", "dst", "ord"), SCAN)[1])
