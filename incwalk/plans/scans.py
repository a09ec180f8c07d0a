"""Walks where edges may only be scanned: short segments from all nodes first, then walks that hop along them.

A scan extends all segments by a step, so ``short`` scans grow a supply of segments of that length
at every node, as many as ``reps`` and its in-degree together. A walk then takes an unused segment
of the node where it stands and moves on by a whole segment at once; where a node's supply is used
up, its walks wait for one more scan that takes each a step. No segment is used twice, so walks stay
independent. With ``short`` near one over the square root of eps both parts need about as many scans.
"""

from __future__ import annotations

import math
from dataclasses import replace

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from incwalk.plans import graph as G
from incwalk.plans.walks import Spec, _step, heads, tables
from incwalk.store import save

_PATH = "array<struct<pos:int,node:bigint,role:string,next:bigint,ended:string>>"


def scan_walks(edges: DataFrame, spec: Spec, short: int | None = None) -> tuple[DataFrame, DataFrame]:
    """``(visits, ledger)``: R forward walks a node until their first reset, and a row of what they took.

    ``visits`` has ``src, rep, pos, node, ended`` as in the walk store. The ledger has ``segment_scans``, the
    rounds of hops, ``single_scans`` that walks waited for, ``segments`` made and used, and ``longest``, the scans
    that walking step by step would take.
    """
    if spec.alternating:
        raise ValueError("scans are for forward walks")
    short = short or math.ceil(1 / math.sqrt(spec.eps))
    adj, deg = tables(edges, spec)
    empty, none = F.array().cast(_PATH), F.lit(None).cast("string")
    supply = G.degrees(edges).select("node", F.explode(F.sequence(F.lit(0), F.col("indeg") + spec.reps - 1)).alias("k"))
    x = supply.select(F.col("node").alias("src"), F.col("k").cast("int").alias("rep"), F.lit(0).alias("pos"), "node", F.lit("hub").alias("role"), empty.alias("path"), none.alias("ended"))
    for i in range(short):
        x = _step(x, adj, deg, spec, 0, "segment")
        if i % spec.fuse == spec.fuse - 1:
            x = save(x, "segments")
    made = save(x.select(F.col("src").alias("at"), F.col("rep").cast("long").alias("slot"), F.col("path").alias("seg"), F.col("node").alias("to"), F.col("ended").alias("stop")), "segments")

    frontier = save(heads(G.nodes(edges), replace(spec, kind="pagerank")), "frontier")
    taken = frontier.select("node", F.lit(0).cast("long").alias("taken")).where("false")
    out, rounds, single = None, 0, 0
    while not frontier.isEmpty():
        asked = G.numbered_within(frontier.withColumn("one", F.lit(0)), ["node"], "one", ["src", "rep"], "src").drop("one")
        asked = asked.join(taken, "node", "left").withColumn("slot", F.col("slot") + F.coalesce("taken", F.lit(0))).drop("taken")
        got = save(asked.join(made, (F.col("node") == F.col("at")) & (asked.slot == made.slot), "left").select("src", "rep", "pos", "node", "role", "seg", "to", "stop"), "asked")
        hop = got.where("seg IS NOT NULL")
        wait = got.where("seg IS NULL")
        waits = not wait.isEmpty()
        moved = hop.select("src", "rep", F.explode("seg").alias("v"), F.col("pos").alias("base")).select("src", "rep", (F.col("base") + F.col("v.pos")).alias("pos"), "v.node", "v.ended")
        live = hop.where("stop IS NULL").select("src", "rep", (F.col("pos") + F.size("seg")).alias("pos"), F.col("to").alias("node"), "role")
        if waits:
            y = save(_step(wait.select("src", "rep", "pos", "node", "role", empty.alias("path"), none.alias("ended")), adj, deg, spec, 0, "single"), "single")
            moved = moved.unionByName(y.select("src", "rep", F.explode("path").alias("v")).select("src", "rep", "v.pos", "v.node", "v.ended"))
            live = live.unionByName(y.where("ended IS NULL").select("src", "rep", "pos", "node", "role"))
        out = moved if out is None else out.unionByName(moved)
        taken = save(taken.unionByName(hop.groupBy("node").agg(F.count("*").alias("taken"))).groupBy("node").agg(F.sum("taken").alias("taken")), "taken")
        frontier, rounds, single = save(live, "frontier"), rounds + 1, single + waits
    visits = save(out, "visits")
    used = taken.agg(F.coalesce(F.sum("taken"), F.lit(0)).alias("segments_used"))
    ledger = made.agg(F.count("*").alias("segments_made")).crossJoin(used).crossJoin(visits.agg((F.max("pos") + 1).alias("longest")))
    return visits, ledger.select(F.lit(short).alias("segment_scans"), F.lit(rounds).alias("hop_rounds"), F.lit(single).alias("single_scans"), "segments_made", "segments_used", "longest")
