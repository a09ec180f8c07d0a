"""Whole histories of arrivals in one pass: what the maintained store would do batch by batch, walk by walk.

A walk's repairs depend on its own visits, on the graph at the batch and on coins of its key, and on no
other walk. Where the arrivals may be broadcast, a task takes some walks through all batches: it looks at
their visits where edges arrived, cuts and regrows them as ``WalkStore.apply`` does, and gives the sums of
the ledger. The edges of a node at any cut are the first ones of its row in the order of arrival.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from incwalk.functions import coins
from incwalk.plans import graph as G
from incwalk.plans.walks import Adjacency, Spec, dealt

#: Nodes whose walks a task takes through the batches at a time.
NODES = 20_000
SUMS = "epoch int, walks_rerouted long, steps_redone long, visits_read long"
_SUMS = pa.schema([("epoch", pa.int32()), ("walks_rerouted", pa.int64()), ("steps_redone", pa.int64()), ("visits_read", pa.int64())])


class History(Adjacency):
    """Rows of all arrivals (src, dst, t) and, by way, cut and place, how many of a row have arrived by then."""

    def __init__(self, arrivals: DataFrame, cuts: list[int], both: bool, count: int):
        super().__init__(arrivals.select("src", "dst", F.col("t").alias("ord")), both, count)
        cut = sum((F.when(F.col("t") > c, 1).otherwise(0) for c in cuts), F.lit(0)).alias("cut")
        self.by_cut = np.zeros((2, len(cuts), len(self.nodes) + 1), np.int32)
        for role, near in enumerate(("src", "dst")):
            t = arrivals.groupBy(F.col(near).alias("node"), cut).count().toArrow()
            self.by_cut[role, t.column("cut").to_numpy(), self.find(t.column("node").to_numpy())] = t.column("count").to_numpy()
        np.cumsum(self.by_cut, axis=1, out=self.by_cut)
        self.born = (self.by_cut.sum(axis=0) == 0).sum(axis=0)  # the first cut at which a node has an edge

    def to(self, place: np.ndarray, role: np.ndarray, slot: np.ndarray) -> np.ndarray:
        """Where slots lead that are taken."""
        out = np.zeros(len(place), np.int32)
        for code, name in enumerate(self.ways):
            own = np.flatnonzero(role == code)
            out[own] = self.targets(place[own], slot[own], name)
        return out


def _grown(g: History, keys: list[str], heads: tuple, spec: Spec, epoch: int) -> tuple:
    """All visits (walk, position, place, role, open) from the heads on, at the graph of a cut; a visit is open unless it was reset."""
    walk, pos, place, role = heads
    out, stop = [], coins.threshold(spec.eps)
    while len(walk):
        a, b = coins.python_coins(spec.seed, "build", [keys[i] for i in walk.tolist()], epoch, pos)
        deg = g.by_cut[role, epoch, place].astype(np.int64)
        stays = (role == 1) | (a >= stop)
        out.append((walk, pos, place, role, stays))
        goes = stays & (deg > 0)
        walk, pos, place, role, b, deg = (x[goes] for x in (walk, pos, place, role, b, deg))
        pos, place, role = pos + 1, g.to(place, role, b * deg >> 32), 1 - role if spec.alternating else role
    kinds = (np.int64, np.int64, np.int32, np.int8, bool)
    return tuple(np.concatenate([x[i] for x in out]) if out else np.zeros(0, kind) for i, kind in enumerate(kinds))


def _lives(g: History, nodes: np.ndarray, spec: Spec) -> np.ndarray:
    """Walks rerouted, steps redone and visits read, of the walks of some nodes, by batch."""
    reps, cuts = spec.reps * (2 if spec.alternating else 1), g.by_cut.shape[1]
    keys = [f"{n}:{r}" for n in nodes.tolist() for r in range(reps)]
    start = np.repeat(g.find(nodes), reps).astype(np.int32)
    role0 = (np.tile(np.arange(reps), len(nodes)) >= spec.reps).astype(np.int8)
    born = g.born[start]
    visits, ledger = _grown(g, keys, (np.zeros(0, np.int64),) * 4, spec, 0), np.zeros((cuts, 3), np.int64)
    for epoch in range(cuts):
        fresh = np.flatnonzero(born == epoch)
        heads = fresh, np.zeros(len(fresh), np.int64), start[fresh], role0[fresh]
        if epoch:
            walk, pos, place, role, is_open = visits
            before, now = g.by_cut[role, epoch - 1, place], g.by_cut[role, epoch, place]
            seen = np.flatnonzero(is_open & (now > before))
            _, b = coins.python_coins(spec.seed, "update", [keys[i] for i in walk[seen].tolist()], epoch, pos[seen])
            slot = b * now[seen].astype(np.int64) >> 32
            switch = slot >= before[seen]
            at, slot = seen[switch], slot[switch]
            order = np.lexsort((pos[at], walk[at]))
            at, slot = at[order], slot[order]
            first = np.r_[True, walk[at][1:] != walk[at][:-1]][: len(at)]
            at, slot = at[first], slot[first]
            upto = np.full(len(keys), np.iinfo(np.int64).max)
            upto[walk[at]] = pos[at]
            turned = 1 - role[at] if spec.alternating else role[at]
            again = walk[at], pos[at] + 1, g.to(place[at], role[at], slot), turned
            heads = tuple(np.concatenate(x) for x in zip(again, heads, strict=True))
            visits = tuple(x[pos <= upto[walk]] for x in visits)
            ledger[epoch, 0], ledger[epoch, 2] = len(at), len(seen)
        grown = _grown(g, keys, heads, spec, epoch)
        ledger[epoch, 1] = len(grown[0])
        visits = tuple(np.concatenate(x) for x in zip(visits, grown, strict=True))
    return ledger


def ledgers(arrivals: DataFrame, spec: Spec, cuts: list[int], count: int) -> dict[int, tuple[int, int, int]]:
    """By batch, from 1: walks rerouted, steps redone and visits read. ``arrivals`` (src, dst, t) has each edge once, ``t`` from 1; ``count`` is their number up to the last cut."""
    arrivals = arrivals.where(F.col("t") <= cuts[-1])
    held = arrivals.sparkSession.sparkContext.broadcast(History(arrivals, cuts, spec.alternating, count))

    def run(batches):
        for batch in batches:
            nodes = batch.column("node").to_numpy()
            for a in range(0, len(nodes), NODES):
                ledger = _lives(held.value, nodes[a : a + NODES], spec)
                yield pa.RecordBatch.from_arrays([pa.array(np.arange(len(ledger), dtype=np.int32)), *(pa.array(c) for c in ledger.T.copy())], schema=_SUMS)

    sums = dealt(G.nodes(arrivals), "node").mapInArrow(run, SUMS).groupBy("epoch").agg(*(F.sum(c).alias(c) for c in _SUMS.names[1:]))
    return {r["epoch"]: (r["walks_rerouted"], r["steps_redone"], r["visits_read"]) for r in sums.collect()}  # a row a batch
