"""Low-rank factors and block-structured start vectors."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from incwalk.functions import coins
from incwalk.plans import exact
from incwalk.plans import graph as G
from incwalk.store import save


def _orthonormal(x: DataFrame, rank: int) -> DataFrame:
    """Columns v0.. made orthonormal over all rows: one aggregate gives the rank x rank inner products, whose inverse Cholesky factor the rows are multiplied with."""
    pairs = [(i, j) for i in range(rank) for j in range(i, rank)]
    sums = x.agg(*(F.sum(F.col(f"v{i}") * F.col(f"v{j}")).alias(f"g{i}_{j}") for i, j in pairs)).first()
    gram = np.zeros((rank, rank))
    for i, j in pairs:
        gram[i, j] = gram[j, i] = sums[f"g{i}_{j}"] or 0.0
    scale = max(float(np.trace(gram)), 1e-300)
    turn = np.linalg.inv(np.linalg.cholesky(gram + np.eye(rank) * scale * 1e-13)).T
    return x.select("node", *(sum((F.col(f"v{i}") * float(turn[i, j]) for i in range(j + 1)), F.lit(0.0)).alias(f"v{j}") for j in range(rank)))


def _times(x: DataFrame, edges: DataFrame, rank: int, near: str, far: str) -> DataFrame:
    return edges.select(F.col(near).alias("node"), F.col(far).alias("__far")).join(x, "node").groupBy(F.col("__far").alias("node")).agg(*(F.sum(f"v{i}").alias(f"v{i}") for i in range(rank)))


def low_rank(edges: DataFrame, rank: int = 8, rounds: int = 3, seed: int = 21) -> tuple[DataFrame, DataFrame]:
    """``(left, right)``, rows (node, v0 ..): the 0-1 link matrix is close to left times right transposed.

    Subspace iteration from a start drawn by coins. Each half round is a join with the edges and one
    aggregate; the driver only sees rank x rank numbers.
    """
    e = save(edges.select("src", "dst"), "links")
    start = [((coins.coin(seed, f"svd{i}", F.col("dst"), 0, 0)[0]) / coins.FULL - 0.5).alias(f"v{i}") for i in range(rank)]
    right = e.select("dst").distinct().select(F.col("dst").alias("node"), *start)
    for _ in range(rounds):
        left = _orthonormal(save(_times(right, e, rank, "dst", "src"), "left"), rank)
        right = _orthonormal(save(_times(left, e, rank, "src", "dst"), "right"), rank)
    return save(_times(right, e, rank, "dst", "src"), "left"), save(right, "right")


def low_rank_scores(edges: DataFrame, seeds: DataFrame, rank: int = 8) -> DataFrame:
    """``(seed, node, score)``: the stated seeds against every target, by products of factors."""
    left, right = low_rank(edges, rank)
    own = seeds.select("seed").join(left.withColumnRenamed("node", "seed"), "seed").select("seed", *(F.col(f"v{i}").alias(f"w{i}") for i in range(rank)))
    return right.join(F.broadcast(own)).select("seed", "node", sum((F.col(f"v{i}") * F.col(f"w{i}") for i in range(rank)), F.lit(0.0)).alias("score"))


def block_start(edges: DataFrame, blocks: DataFrame, eps: float = 0.2, rounds: int = 10) -> DataFrame:
    """``(seed, node, score)``: scores inside each block times the score of the block, to start a power iteration from. Jumps reach a block by its share of the nodes, as those of the whole graph do. ``blocks``: node, block."""
    b = save(blocks.join(G.nodes(edges), "node", "left_semi").select("node", "block"), "blocks")
    tagged = edges.select("src", "dst").join(b.select(F.col("node").alias("src"), F.col("block").alias("src_block")), "src").join(b.select(F.col("node").alias("dst"), F.col("block").alias("dst_block")), "dst")
    tagged = save(tagged, "tagged")
    sizes = b.groupBy("block").agg((1 / F.count("*")).alias("weight"))
    tele = b.join(sizes, "block").select(F.col("block").alias("seed"), "node", "weight")
    local = exact.power_iteration(tagged.where("src_block = dst_block"), eps, rounds, tele)
    total = local.groupBy("seed").agg(F.sum("score").alias("sum"))
    local = save(local.join(total, "seed").select(F.col("seed").alias("block"), "node", (F.col("score") / F.col("sum")).alias("local")), "local")
    out = tagged.groupBy("src").agg((1 / F.count("*")).alias("out_w"))
    moves = tagged.join(out, "src").join(local.select(F.col("node").alias("src"), "local"), "src").groupBy("src_block", "dst_block").agg(F.sum(F.col("out_w") * F.col("local")).alias("w"))
    moves, n = save(moves, "moves"), b.agg(F.count("*").alias("n"))
    base = save(b.groupBy("block").agg(F.count("*").alias("k")).crossJoin(n).select("block", (F.col("k") / F.col("n")).alias("tele")), "block-teleport")
    x = base.withColumnRenamed("tele", "score")
    for i in range(1, rounds + 1):
        x = x.join(moves, x.block == moves.src_block).select(F.col("dst_block").alias("block"), (F.col("score") * F.col("w") * (1 - eps)).alias("score")).unionByName(base.select("block", (F.col("tele") * eps).alias("score"))).groupBy("block").agg(F.sum("score").alias("score"))
        if i % exact.CUT == 0:
            x = save(x, "block-scores")
    return local.join(x, "block").select(F.lit(-1).cast("long").alias("seed"), "node", (F.col("local") * F.col("score")).alias("score"))
