"""Exact iterations: PageRank, alternating, HITS and cosine scores, and their faster or local variants.

Scores are frames keyed by node (and seed), so many seeds advance together; a round is one join
with the edges and one aggregate. Lineage is cut every few rounds; with many seeds it is cut every
round, and the tables of the round before go, so that one round's shuffles are on disk at a time.
A graph of a checked size is broadcast instead, and seeds take a task each (``dense``).
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from incwalk.plans import dense
from incwalk.plans import graph as G
from incwalk.store import discard, save

CUT = 5


def weighted(edges: DataFrame) -> DataFrame:
    """``(src, dst, out_w, in_w)``: one over the out-degree of src and one over the in-degree of dst."""
    e = edges.select("src", "dst")
    return e.join(e.groupBy("src").agg((1 / F.count("*")).alias("out_w")), "src").join(e.groupBy("dst").agg((1 / F.count("*")).alias("in_w")), "dst")


def _teleport(edges: DataFrame, seeds: DataFrame | None) -> DataFrame:
    """``(seed, node, tele)``: uniform over nodes under seed -1, or all on each seed (weights where given)."""
    if seeds is None:
        n = G.nodes(edges)
        return n.crossJoin(n.agg((1 / F.count("*")).alias("tele"))).select(F.lit(-1).cast("long").alias("seed"), "node", "tele")
    if "node" in seeds.columns:
        return seeds.select("seed", "node", F.col("weight").alias("tele"))
    return seeds.select("seed", F.col("seed").alias("node"), F.lit(1.0).alias("tele"))


def power_iteration(edges: DataFrame, eps: float = 0.2, rounds: int = 10, seeds: DataFrame | None = None, dangling: str = "leak", start: DataFrame | None = None, engine: str = "auto", best: int | None = None) -> DataFrame:
    """``(seed, node, score)``. ``dangling``: the mass at nodes without edges leaks, spreads uniformly, or goes back to the seed. A caller that reads only each seed's ``best`` largest scores says so; further rows may be left out then, no tie of the last one is."""
    local = start is None and engine != "joins" and dense.fits(edges)
    if local and seeds is None:
        return dense.uniform_power(edges, eps, rounds, dangling)
    tele = save(_teleport(edges, seeds), "teleport")
    if local:
        return dense.power(edges, tele, eps, rounds, dangling, best)
    e = save(weighted(edges).select("src", "dst", "out_w"), "weighted")
    x = start if start is not None else tele.withColumnRenamed("tele", "score")
    last = None
    for i in range(1, rounds + 1):
        moved = x.join(e, x.node == e.src).select("seed", F.col("dst").alias("node"), (F.col("score") * F.col("out_w") * (1 - eps)).alias("score"))
        base = tele.select("seed", "node", (F.col("tele") * eps).alias("score"))
        if dangling != "leak":
            stuck = x.join(e.select(F.col("src").alias("node")).distinct(), "node", "left_anti").groupBy("seed").agg((F.sum("score") * (1 - eps)).alias("lost"))
            base = base.unionByName(tele.join(stuck, "seed").select("seed", "node", (F.col("tele") * F.col("lost")).alias("score")))
        x = moved.unionByName(base).groupBy("seed", "node").agg(F.sum("score").alias("score"))
        if i % (CUT if seeds is None else 1) == 0:
            x = save(x, "scores")
            discard(last)
            last = x
    return x


def alternating_iteration(edges: DataFrame, eps: float = 0.2, rounds: int = 10, seeds: DataFrame | None = None, divide: bool = True, engine: str = "auto", best: int | None = None) -> DataFrame:
    """``(seed, node, hub, auth)``; ``best`` as above, by ``auth``. With ``divide`` shares by degree; without, HITS, rescaled each round by one factor so that jumps keep their relative size."""
    tele = save(_teleport(edges, seeds), "teleport")
    if seeds is not None and engine != "joins" and dense.fits(edges, ways=2):
        return dense.alternating(edges, tele, eps, rounds, divide, best)
    e = save(weighted(edges), "weighted")
    h, scale = tele.withColumnRenamed("tele", "hub"), tele.select("seed").distinct().withColumn("scale", F.lit(1.0))
    a = None
    for i in range(1, rounds + 1):
        a = h.join(e, h.node == e.src).groupBy("seed", F.col("dst").alias("node")).agg(F.sum(F.col("hub") * F.col("out_w") if divide else F.col("hub")).alias("auth"))
        back = a.join(e, a.node == e.dst).select("seed", F.col("src").alias("node"), (F.col("auth") * (F.col("in_w") if divide else F.lit(1.0)) * (1 - eps)).alias("hub"))
        jump = tele.join(scale, "seed").select("seed", "node", (F.col("tele") * eps * F.col("scale")).alias("hub"))
        h = back.unionByName(jump).groupBy("seed", "node").agg(F.sum("hub").alias("hub"))
        if not divide:
            h = save(h, "hubs")
            top = h.groupBy("seed").agg(F.max("hub").alias("top"))
            h = h.join(top, "seed").select("seed", "node", (F.col("hub") / F.col("top")).alias("hub"))
            a = a.join(top, "seed").select("seed", "node", (F.col("auth") / F.col("top")).alias("auth"))
            scale = save(scale.join(top, "seed").select("seed", (F.col("scale") / F.col("top")).alias("scale")), "scale")
        elif i % CUT == 0:
            h = save(h, "hubs")
    a = h.join(e, h.node == e.src).groupBy("seed", F.col("dst").alias("node")).agg(F.sum(F.col("hub") * F.col("out_w") if divide else F.col("hub")).alias("auth"))
    return h.join(a, ["seed", "node"], "full").select("seed", "node", F.coalesce("hub", F.lit(0.0)).alias("hub"), F.coalesce("auth", F.lit(0.0)).alias("auth"))


def cosine_hubs(edges: DataFrame, seeds: DataFrame) -> DataFrame:
    """``(seed, node, hub)``: cosine of the 0-1 neighbour sets; only nodes that share a neighbour with a seed come up."""
    e = edges.select("src", "dst")
    own = e.join(seeds.select(F.col("seed").alias("src")), "src", "left_semi").select(F.col("src").alias("seed"), "dst")
    common = own.join(e, "dst").groupBy("seed", F.col("src").alias("node")).agg(F.count("*").alias("common"))
    d = e.groupBy("src").agg(F.count("*").alias("d"))
    x = common.join(d.select(F.col("src").alias("seed"), F.col("d").alias("d_seed")), "seed").join(d.select(F.col("src").alias("node"), F.col("d").alias("d_node")), "node")
    return x.select("seed", "node", (F.col("common") / F.sqrt(F.col("d_seed") * F.col("d_node"))).alias("hub"))


def cosine_authorities(edges: DataFrame, hubs: DataFrame) -> DataFrame:
    return hubs.join(edges.select(F.col("src").alias("node"), "dst"), "node").groupBy("seed", F.col("dst").alias("node")).agg(F.sum("hub").alias("auth"))


def aitken(edges: DataFrame, eps: float = 0.2, rounds: int = 8, every: int = 4) -> DataFrame:
    """Power iteration with component-wise delta-squared extrapolation after every ``every`` rounds; where the denominator vanishes the last iterate stays."""
    x = None
    for _ in range(rounds // every):
        a = power_iteration(edges, eps, every - 2, start=x)
        b = save(power_iteration(edges, eps, 1, start=a), "aitken")
        c = save(power_iteration(edges, eps, 1, start=b), "aitken")
        j = c.join(a.select("node", F.col("score").alias("a")), "node", "left").join(b.select("node", F.col("score").alias("b")), "node", "left")
        bend = F.col("score") - 2 * F.col("b") + F.col("a")
        jump = F.col("a") - F.pow(F.col("b") - F.col("a"), F.lit(2)) / bend
        x = save(j.select("seed", "node", F.when((F.abs(bend) > 1e-12) & (jump > 0), jump).otherwise(F.col("score")).alias("score")), "aitken")
    return x


def neighbour_mean(edges: DataFrame, targets: DataFrame, eps: float = 0.2, depth: int = 5, keep: float = 0.0) -> DataFrame:
    """``(node, target, score)``: a node's personalised vector is eps on itself and the rest the mean of its out-neighbours' vectors, from the bottom up; entries under ``keep`` are dropped each round."""
    e = weighted(edges).select("src", "dst", "out_w")
    base = targets.select("node", F.col("node").alias("target"), F.lit(eps).alias("score"))
    x = base
    for i in range(depth):
        up = x.join(e, x.node == e.dst).select(F.col("src").alias("node"), "target", (F.col("score") * F.col("out_w") * (1 - eps)).alias("score"))
        x = up.unionByName(base).groupBy("node", "target").agg(F.sum("score").alias("score")).where(F.col("score") >= keep)
        if i % CUT == CUT - 1:
            x = save(x, "vectors")
    return x


def lumped_update(edges: DataFrame, old: DataFrame, changed: DataFrame, eps: float = 0.2, hops: int = 1, rounds: int = 10) -> DataFrame:
    """Scores after a change from a small chain: nodes within ``hops`` of changed sources, and one node for all others with weights by the old scores. ``old``: node, score; the others keep their old scores, rescaled."""
    near = changed.select("node")
    for _ in range(hops):
        near = near.union(edges.join(near, edges.src == near.node, "left_semi").select(F.col("dst").alias("node"))).distinct()
    near = save(near.distinct(), "near")
    e = weighted(edges).select("src", "dst", "out_w")
    far_mass = old.join(near, "node", "left_anti").agg(F.sum("score").alias("mass"))
    inside = near.withColumn("in", F.lit(True))
    name = lambda c: F.when(F.col(f"{c}_in"), F.col(c)).otherwise(F.lit(-1))
    w = e.join(inside.select(F.col("node").alias("src"), F.col("in").alias("src_in")), "src", "left").join(inside.select(F.col("node").alias("dst"), F.col("in").alias("dst_in")), "dst", "left")
    w = w.join(old.select(F.col("node").alias("src"), "score"), "src", "left").crossJoin(far_mass)
    share = F.when(F.col("src_in"), F.col("out_w")).otherwise(F.col("out_w") * F.coalesce("score", F.lit(0.0)) / F.col("mass"))
    chain = save(w.select(name("src").alias("src"), name("dst").alias("dst"), share.alias("w")).groupBy("src", "dst").agg(F.sum("w").alias("w")), "chain")
    n = G.nodes(edges).agg(F.count("*").alias("n"))
    tele = save(near.crossJoin(n).select("node", (1 / F.col("n")).alias("tele")).union(n.crossJoin(near.agg(F.count("*").alias("k"))).select(F.lit(-1).cast("long"), ((F.col("n") - F.col("k")) / F.col("n")))), "tele")
    x = old.join(near, "node").select("node", "score").union(far_mass.select(F.lit(-1).cast("long"), "mass"))
    for i in range(1, rounds + 1):
        x = x.join(chain, x.node == chain.src).select(F.col("dst").alias("node"), (F.col("score") * F.col("w") * (1 - eps)).alias("score")).union(tele.select("node", F.col("tele") * eps)).groupBy("node").agg(F.sum("score").alias("score"))
        if i % CUT == 0:
            x = save(x, "lumped")
    x = save(x, "lumped")
    rest = old.join(near, "node", "left_anti").crossJoin(far_mass).crossJoin(x.where("node = -1").select(F.col("score").alias("now")))
    return x.where("node <> -1").union(rest.select("node", F.col("score") * F.col("now") / F.col("mass")))
