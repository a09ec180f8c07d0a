"""Personalised walks stitched out of stored segments, their fetch ledgers, and what is read off them.

``waves`` is what the queries run: a walk falls into independent excursions at its resets, all
excursions of all seeds advance together, and the first unused segments of a node go to the lowest
excursion numbers, so that nothing is broadcast that grows with the graph. ``stitched_walk`` walks
each seed alone, step by step, against broadcast tables of a checked size, as a reference for tests.
"""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from incwalk.functions import coins, theory
from incwalk.plans import exact
from incwalk.plans import graph as G
from incwalk.plans.walks import COMPACT_EDGES, LOCAL_EDGES, ROLES, Adjacency, Spec, _words, advance, both_ways, dealt, held_rows, segments
from incwalk.store import _shuffles_end, discard, save

#: Stored visits that the driver may sort for a broadcast, and that may be broadcast where Spark sorts them.
LOCAL_VISITS, COMPACT_VISITS = 4_000_000, 100_000_000
WALK = "seed long, pos long, node long, role string, how string, fetches long"
_WALK = pa.schema([("seed", pa.int64()), ("pos", pa.int64()), ("node", pa.int64()), ("role", pa.string()), ("how", pa.string()), ("fetches", pa.int64())])


def pick_seeds(edges: DataFrame, how_many: int = 100, low: int = 20, high: int = 30) -> DataFrame:
    """Nodes of out-degree ``low`` to ``high``, smallest digest first."""
    d = edges.groupBy("src").agg(F.count("*").alias("friends")).where(F.col("friends").between(low, high))
    return d.orderBy(F.md5(F.concat(F.lit("seed|"), F.col("src").cast("string"))), "src").limit(how_many).select(F.col("src").alias("seed"), "friends")


def stitched_walk(visits: DataFrame | None, edges: DataFrame, seeds: DataFrame, length: int, spec: Spec, policy: str = "lazy", fetch: str = "full") -> DataFrame:
    """``(seed, pos, node, role, how, fetches)``: a walk of ``length`` visits or more per seed; ``fetches`` counts up to each visit.

    Policies: ``lazy`` flips the coin once and then takes a segment of at least one step (its own
    coin is known to have survived); ``once`` lets the segment carry the coin; ``literal`` flips
    before and within, which visits the seed too often. ``fetch``: ``full`` brings a node's segments
    and neighbours at once; ``edge`` brings the segments, or one edge a call. Without ``visits``
    every step is a query of its own.
    """
    if edges.count() > LOCAL_EDGES or (visits is not None and visits.count() > LOCAL_VISITS):
        raise ValueError("too large to broadcast; use waves()")
    sc = edges.sparkSession.sparkContext
    graph = sc.broadcast(Adjacency(edges, spec.alternating))
    stored: dict = {}
    if visits is not None:
        start = F.when(F.col("rep") < spec.reps, "hub").otherwise("auth")
        for r in segments(visits).select("src", "rep", "path", "ended", start.alias("role")).orderBy("src", "rep").toArrow().to_pylist():
            stored.setdefault((r["src"], r["role"]), []).append((r["path"], r["ended"]))
    held = sc.broadcast(stored)
    stop, alternating, seed0, crude = coins.threshold(spec.eps), spec.alternating, spec.seed, visits is None

    def walk(seed):
        g, store = graph.value, held.value
        out, used, fetched, fetches, toss = [(seed, "hub", "start", 0)], {}, set(), 0, 0

        def other(role):
            return ("auth" if role == "hub" else "hub") if alternating else "hub"

        survived = False
        while len(out) < length:
            node, role = out[-1][0], out[-1][1]
            if not survived and role == "hub":
                toss += 1
                a, _ = coins.python_coin(seed0, "personal", seed, 0, toss)
                if a < stop and (policy != "once" or (node, role) in fetched):
                    if policy != "once" or used.get((node, role), 0) >= len(store.get((node, role), ())):
                        out.append((seed, "hub", "reset", fetches))
                        continue
            key = (node, role)
            own = store.get(key, ())
            k = used.get(key, 0)
            if policy == "lazy" and role == "hub":
                while k < len(own) and len(own[k][0]) < 2:
                    k += 1
            if key in fetched and k < len(own):
                used[key] = k + 1
                path = own[k][0][1:]
                r = role
                for x in path:
                    r = other(r)
                    out.append((x, r, "segment", fetches))
                out.append((seed, "hub", "reset", fetches))
                survived = False
                continue
            if key not in fetched:
                fetched.add(key)
                fetches += 1
                if own or policy == "literal":
                    survived = policy != "literal"
                    continue
            elif fetch == "edge" or crude:
                fetches += 1
            survived = False
            deg = g.degree(node, role)
            if not deg:
                out.append((seed, "hub", "reset", fetches))
                continue
            toss += 1
            _, b = coins.python_coin(seed0, "step", seed, 0, toss)
            out.append((g.target(node, b * deg >> 32, role), other(role), "step", fetches))
        return out

    def run(batches):
        for batch in batches:
            for seed in batch.column("seed").to_pylist():
                w = walk(seed)
                yield pa.RecordBatch.from_arrays([pa.array([seed] * len(w), pa.int64()), pa.array(range(len(w)), pa.int64()), *(pa.array([x[i] for x in w], _WALK.field(i + 2).type) for i in range(4))], schema=_WALK)

    return seeds.select("seed").repartition("seed").mapInArrow(run, WALK)


def waves(visits: DataFrame | None, edges: DataFrame, seeds: DataFrame, length: int, spec: Spec, policy: str = "lazy") -> DataFrame:
    """``(seed, pos, node, role, how, asks, hand)`` of walks of ``length`` visits.

    ``how`` a visit came about (``reset``, ``step`` by hand, inside a ``segment``); ``asks`` marks
    visits from which the walk went on by what a fetch at that node brought, ``hand`` those that went on by hand.
    Policies as in ``stitched_walk``; alternating walks take segments that start in their role.
    Without ``visits`` every step is by hand. Seeds whose excursions fall short of ``length``, as
    beside nodes without out-edges, start as many again until none does.

    Two engines take the same walks: joins round by round, and, where edges and stored visits are
    under a checked number, one task a seed against broadcast arrays.
    """
    visits = save(visits, "visits") if visits is not None else None
    return (_waves_local if _on_arrays(visits, edges, spec) else _waves_joined)(visits, edges, seeds, length, spec, policy)


class Stored:
    """Tails of the usable segments by place and role, for broadcast: 4 bytes a stored visit, 8 a segment and 16 a node and role.

    Up to ``LOCAL_VISITS`` the driver sorts the visits; beyond it Spark does, and the driver gets 6 bytes a visit.
    """

    def __init__(self, visits: DataFrame | None, spec: Spec, policy: str, g: Adjacency):
        self.width = 2 if spec.alternating else 1
        self.flat, self.place = np.zeros(0, np.int32), np.zeros(1, np.int64)
        keys = np.zeros(0, np.int64)
        if visits is not None:
            node, head = self._ordered(visits, g)
            first = np.flatnonzero(head >= 0)
            size = np.diff(np.r_[first, len(node)])
            rep = head[first].astype(np.int64)
            keep = (size > 1) | (rep >= spec.reps) if policy == "lazy" else np.ones(len(first), bool)
            keys = (node[first].astype(np.int64) * self.width + (rep >= spec.reps))[keep]
            self.flat = node[np.repeat(keep, size) & (head < 0)]
            self.place = np.r_[0, np.cumsum(size[keep] - 1)]
        self.many = np.bincount(keys, minlength=(len(g.nodes) + 1) * self.width)
        self.first = np.cumsum(self.many) - self.many

    @staticmethod
    def _ordered(visits: DataFrame, g: Adjacency) -> tuple[np.ndarray, np.ndarray]:
        """Places of the visits by walk and position; beside the first of a walk, which is at its source, the number of the walk, and -1 beside the others."""
        v = visits.select("src", "rep", "pos", "node")
        if v.count() <= LOCAL_VISITS:
            t = v.toArrow()
            src, rep, pos, node = (t.column(c).to_numpy() for c in v.columns)
            order = np.lexsort((pos, rep, src))
            return g.find(node[order]).astype(np.int32), np.where(pos == 0, rep, -1)[order].astype(np.int16)
        spark = v.sparkSession
        held, schema = spark.sparkContext.broadcast(g.nodes), pa.schema([("src", pa.int64()), ("rep", pa.int32()), ("pos", pa.int32()), ("at", pa.int32())])

        def places(batches):
            for batch in batches:
                at = np.searchsorted(held.value, batch.column("node").to_numpy()).astype(np.int32)
                yield pa.RecordBatch.from_arrays([batch.column("src"), batch.column("rep"), batch.column("pos"), pa.array(at)], schema=schema)

        rows = v.mapInArrow(places, "src long, rep int, pos int, at int")
        rows = rows.repartitionByRange(int(spark.conf.get("spark.sql.shuffle.partitions")), "src").sortWithinPartitions("src", "rep", "pos")
        with _shuffles_end(spark):
            t = rows.select("at", F.when(F.col("pos") == 0, F.col("rep")).otherwise(-1).cast("short").alias("head")).toArrow()  # in the order of the ranges
        return t.column("at").to_numpy(), t.column("head").to_numpy()

    def segments(self, key: np.ndarray, k: np.ndarray) -> np.ndarray:
        """The number of the ``k``-th segment of each key; -1 where there is none."""
        return np.where((k > 0) & (k <= self.many[key]), self.first[key] + k - 1, -1)

    def tails(self, segments: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """The tails end to end: which of the given segments, how far in, and the place."""
        size = self.place[segments + 1] - self.place[segments]
        which = np.repeat(np.arange(len(segments)), size)
        i = np.arange(len(which)) - np.repeat(np.cumsum(size) - size, size)
        return which, i, self.flat[self.place[segments][which] + i]


HOW = ("reset", "step", "segment")
_WAVES = pa.schema([("seed", pa.int64()), ("pos", pa.int64()), ("node", pa.int64()), ("role", pa.string()), ("how", pa.string()), ("asks", pa.bool_()), ("hand", pa.bool_())])
_VISITED = pa.schema([("seed", pa.int64()), ("node", pa.int64()), ("role", pa.string()), ("visits", pa.int64())])
_PREFIX = pa.schema([("seed", pa.int64()), ("s", pa.int32()), ("f", pa.int64()), ("raw", pa.int64())])


def _wave(g: Adjacency, store: Stored, seed: int, used: np.ndarray, heads: tuple, spec: Spec, policy: str) -> tuple[list, tuple]:
    """All heads (excursion, position, place, role, how) a step on, in the order of excursions: the visits that come of it, and the next heads."""
    exc, at, place, role, how = heads
    stop, names = coins.threshold(spec.eps), [f"{seed}:{x}" for x in exc.tolist()]
    a, b = coins.python_coins(spec.seed, "wave", names, 0, at)
    alive = (role == 1) | (a >= stop)
    asks = np.ones(len(exc), bool) if policy == "once" else alive.copy()
    key, k = place.astype(np.int64) * store.width + role, np.zeros(len(exc), np.int64)
    order = np.flatnonzero(asks)
    order = order[np.argsort(key[order], kind="stable")]
    if len(order):
        own, n = key[order], np.arange(len(order))
        k[order] = used[own] + n - np.maximum.accumulate(np.where(np.r_[True, own[1:] != own[:-1]], n, 0)) + 1
    if policy == "literal":  # the coin is flipped again after the fetch
        again = np.flatnonzero((k == 1) & (role == 0))
        ends = again[coins.python_coins(spec.seed, "wave-again", [names[i] for i in again.tolist()], 0, at[again])[0] < stop]
        k[ends], alive[ends] = 0, False
    np.maximum.at(used, key[k > 0], k[k > 0].astype(used.dtype))
    segment = store.segments(key, k)
    takes = segment >= 0
    hand = alive & ~takes
    made = [(exc, at, place, role, how, asks & (alive | takes), hand)]
    own = np.flatnonzero(takes)
    which, i, to = store.tails(segment[own])
    which, none = own[which], np.zeros(len(i), bool)
    made.append((exc[which], at[which] + i + 1, to, ((role[which] + i + 1) % 2 if spec.alternating else 0 * i).astype(np.int8), np.full(len(i), 2, np.int8), none, none))
    h = np.flatnonzero(hand)
    deg, to = advance(g, place[h], role[h], b[h], spec.alternating)
    h, to = h[deg > 0], to[deg > 0]
    return made, (exc[h], at[h] + 1, to, 1 - role[h] if spec.alternating else role[h], np.ones(len(h), np.int8))


def _stitched(g: Adjacency, store: Stored, seed: int, length: int, spec: Spec, policy: str) -> list[np.ndarray]:
    """Place, role, how, asks and hand of the first ``length`` visits of a seed's walk."""
    start, used = g.find(np.array([seed]))[0], np.zeros((len(g.nodes) + 1) * store.width, np.int32)
    made, total, begun, more = [], 0, 0, excursions(length, spec, policy)
    while total < length:
        exc = np.arange(begun, begun + more)
        heads = exc, np.zeros(more, np.int64), np.full(more, start, np.int32), np.zeros(more, np.int8), np.zeros(more, np.int8)
        while len(heads[0]):
            got, heads = _wave(g, store, seed, used, heads, spec, policy)
            made += got
            total += sum(len(x[0]) for x in got)
        begun, more = begun + more, begun + more
    exc, at = (np.concatenate([x[i] for x in made]) for i in range(2))
    order = np.lexsort((at, exc))[:length]
    return [np.concatenate([x[i] for x in made])[order] for i in range(2, 7)]


def _each_walk(visits, edges, seeds, length, spec, policy, give, spelled) -> DataFrame:
    """``give(seed, names, place, role, how, asks, hand)`` makes batches out of the walk of each seed, a task a seed."""
    sc, seeds = edges.sparkSession.sparkContext, seeds.select("seed")
    graph = held_rows(edges, spec.alternating)
    store = sc.broadcast(Stored(visits, spec, policy, graph.value))

    def run(batches):
        for batch in batches:
            for seed in batch.column("seed").to_pylist():
                yield from give(seed, np.r_[graph.value.nodes, seed], *_stitched(graph.value, store.value, seed, length, spec, policy))

    return dealt(seeds, "seed").mapInArrow(run, spelled)


#: Visits in a batch of rows.
BATCH = 100_000


def _waves_local(visits: DataFrame | None, edges: DataFrame, seeds: DataFrame, length: int, spec: Spec, policy: str) -> DataFrame:
    def rows(seed, names, place, role, how, asks, hand):
        for a in range(0, len(place), BATCH):
            part = slice(a, a + BATCH)
            pos = np.arange(a, min(a + BATCH, len(place)))
            yield pa.RecordBatch.from_arrays([pa.array(np.full(len(pos), seed, np.int64)), pa.array(pos), pa.array(names[place[part]]), _words(list(ROLES), role[part]), _words(list(HOW), how[part]), pa.array(asks[part]), pa.array(hand[part])], schema=_WAVES)

    return _each_walk(visits, edges, seeds, length, spec, policy, rows, "seed long, pos long, node long, role string, how string, asks boolean, hand boolean")


def _on_arrays(visits: DataFrame | None, edges: DataFrame, spec: Spec) -> bool:
    return spec.engine == "local" or spec.engine == "auto" and spec.coin == "portable" and edges.count() <= COMPACT_EDGES and (visits is None or visits.count() <= COMPACT_VISITS)


def visit_counts(visits: DataFrame | None, edges: DataFrame, seeds: DataFrame, length: int, spec: Spec, policy: str = "lazy") -> DataFrame:
    """``(seed, node, role, visits)`` of the walks of ``waves``; where a task has a seed's walk, that is counted there."""
    visits = save(visits, "visits") if visits is not None else None
    if not _on_arrays(visits, edges, spec):
        return _waves_joined(visits, edges, seeds, length, spec, policy).groupBy("seed", "node", "role").agg(F.count("*").alias("visits"))

    def rows(seed, names, place, role, how, asks, hand):
        many = np.bincount(place.astype(np.int64) * 2 + role)
        seen = np.flatnonzero(many)
        yield pa.RecordBatch.from_arrays([pa.array(np.full(len(seen), seed, np.int64)), pa.array(names[seen // 2]), _words(list(ROLES), seen % 2), pa.array(many[seen])], schema=_VISITED)

    return _each_walk(visits, edges, seeds, length, spec, policy, rows, "seed long, node long, role string, visits long")


def prefix_ledger(visits: DataFrame, edges: DataFrame, seeds: DataFrame, lengths: tuple[int, ...], spec: Spec) -> DataFrame:
    """``(seed, s, f, raw)`` of the first ``s`` visits of each seed's walk: fetches, and visits beyond R summed over nodes."""
    visits, r = save(visits, "visits"), spec.reps
    if not _on_arrays(visits, edges, spec):
        w = save(fetched(_waves_joined(visits, edges, seeds, max(lengths), spec, "lazy")).select("seed", "pos", "node", "fetches"), "walk")
        upto = w.select("*", F.explode(F.array(*(F.lit(s) for s in lengths))).alias("s")).where("pos < s").groupBy("s", "seed", "node").agg(F.count("*").alias("x"), F.max("fetches").alias("f"))
        return upto.groupBy("seed", "s").agg(F.max("f").alias("f"), F.sum(F.greatest(F.col("x") - r, F.lit(0))).alias("raw"))

    def rows(seed, names, place, role, how, asks, hand):
        asked, calls = np.flatnonzero(asks), np.zeros(len(place), np.int64)
        calls[asked[np.unique(place[asked].astype(np.int64) * 2 + role[asked], return_index=True)[1]]] = 1
        calls = np.cumsum(calls)
        f = [int(calls[min(s, len(place)) - 1]) for s in lengths]
        raw = [int(np.maximum(np.unique(place[:s], return_counts=True)[1] - r, 0).sum()) for s in lengths]
        yield pa.RecordBatch.from_arrays([pa.array([seed] * len(f), pa.int64()), pa.array(lengths, pa.int32()), pa.array(f, pa.int64()), pa.array(raw, pa.int64())], schema=_PREFIX)

    return _each_walk(visits, edges, seeds, max(lengths), spec, "lazy", rows, "seed long, s int, f long, raw long")


def _waves_joined(visits: DataFrame | None, edges: DataFrame, seeds: DataFrame, length: int, spec: Spec, policy: str) -> DataFrame:
    keys = ["node", "role"]
    if visits is not None:
        start = F.when(F.col("rep") < spec.reps, "hub").otherwise("auth")
        own = segments(visits).withColumn("role", start)
        if policy == "lazy":  # survival is decided before, so segments without a step are passed over
            own = own.where((F.size("path") > 1) | (F.col("role") == "auth"))
        own = own.select(F.col("src").alias("node"), "role", F.row_number().over(Window.partitionBy("src", "role").orderBy("rep")).alias("k"), F.slice("path", 2, 1 << 30).alias("tail"))
    else:
        own = edges.sparkSession.createDataFrame([], "node long, role string, k int, tail array<long>")
    stored = save(own, "stored")
    adj, deg = both_ways(edges, spec)
    adj = save(adj.select(F.col("src").alias("node"), F.col("way").alias("role"), "slot", "dst"), "adj")
    deg = save(adj.groupBy(*keys).agg(F.count("*").alias("deg")), "deg")
    many = excursions(length, spec, policy)
    used = save(edges.sparkSession.createDataFrame([], "seed long, node long, role string, used long"), "used")
    other = F.when(F.col("role") == "hub", "auth").otherwise("hub") if spec.alternating else F.lit("hub")
    survives = lambda tag: (F.col("role") == "auth") | (coins.coin(spec.seed, tag, F.concat_ws(":", F.col("seed").cast("string"), F.col("exc").cast("string")), F.lit(0), F.col("at"), spec.coin)[0] >= coins.threshold(spec.eps))
    done, short, begun = None, seeds.select("seed"), 0
    while True:
        frontier = short.select("seed", F.explode(F.sequence(F.lit(begun), F.lit(begun + many - 1))).alias("exc"), F.col("seed").alias("node"), F.lit("hub").alias("role"), F.lit(0).alias("at"), F.lit("reset").alias("how"))
        while True:
            b = coins.coin(spec.seed, "wave", F.concat_ws(":", F.col("seed").cast("string"), F.col("exc").cast("string")), F.lit(0), F.col("at"), spec.coin)[1]
            x = frontier.withColumn("alive", survives("wave")).withColumn("again", survives("wave-again") if policy == "literal" else F.lit(True)).withColumn("b", b)
            turn = Window.partitionBy("seed", "node", "role", "asks").orderBy("exc")
            x = x.withColumn("asks", F.lit(True) if policy == "once" else F.col("alive"))
            x = x.join(used, ["seed", *keys], "left").withColumn("k", F.when(F.col("asks"), F.row_number().over(turn) + F.coalesce("used", F.lit(0))).cast("int"))
            if policy == "literal":  # the coin is flipped again after the fetch
                x = x.withColumn("k", F.when((F.col("k") > 1) | F.col("again"), F.col("k"))).withColumn("alive", F.col("alive") & ((F.coalesce("k", F.lit(0)) > 0)))
            x = x.join(stored, [*keys, "k"], "left").join(deg, keys, "left")
            goes = F.col("alive") & F.col("tail").isNull()
            slot = F.when(goes & F.col("deg").isNotNull(), coins.slot(F.col("b"), F.col("deg")))
            x = x.withColumn("hand", goes).withColumn("asks", F.col("asks") & (F.col("alive") | F.col("tail").isNotNull())).withColumn("slot", slot)
            x = save(x.join(adj, [*keys, "slot"], "left").select("seed", "exc", "at", "node", "role", "how", "asks", "hand", "k", "tail", "dst"), "wave")
            tails = x.where("tail IS NOT NULL").select("seed", "exc", "at", "role", F.posexplode("tail").alias("i", "node"))
            tails = tails.select("seed", "exc", (F.col("at") + F.col("i") + 1).alias("at"), "node", F.when(F.col("i") % 2 == 1, F.col("role")).otherwise(other).alias("role"), F.lit("segment").alias("how"), F.lit(False).alias("asks"), F.lit(False).alias("hand"))
            seen = x.select("seed", "exc", "at", "node", "role", "how", "asks", "hand").unionByName(tails)
            done = seen if done is None else done.unionByName(seen)
            frontier = x.where("dst IS NOT NULL").select("seed", "exc", F.col("dst").alias("node"), other.alias("role"), (F.col("at") + 1).alias("at"), F.lit("step").alias("how"))
            if frontier.isEmpty():
                break
            took = x.where("k IS NOT NULL").groupBy("seed", *keys).agg(F.max("k").alias("used"))
            used, old = save(used.unionByName(took).groupBy("seed", *keys).agg(F.max("used").cast("long").alias("used")), "used"), used
            discard(old)
        full = done.groupBy("seed").count().where(F.col("count") >= length)
        short = save(short.join(full, "seed", "left_anti"), "short")
        if short.isEmpty():
            break
        begun, many = begun + many, begun + many
    place = Window.partitionBy("seed").orderBy("exc", "at")
    return done.withColumn("pos", F.row_number().over(place) - 1).where(F.col("pos") < length).select("seed", F.col("pos").cast("long").alias("pos"), "node", "role", "how", "asks", "hand")


def margin(policy: str) -> float:
    """The literal policy resets more often than ``eps`` says."""
    return 2.0 if policy == "literal" else 1.3


def excursions(length: int, spec: Spec, policy: str) -> int:
    """How many a walk of ``length`` visits starts with: a margin over the share of resets."""
    return math.ceil(margin(policy) * length * spec.eps) + 20


def fetched(walk: DataFrame, fetch: str = "full") -> DataFrame:
    """Adds ``fetches`` up to each visit: one where a walk first goes on from a node (and role); with ``fetch="edge"`` also one for each later step by hand, since a call brings the segments or one edge."""
    first = F.row_number().over(Window.partitionBy("seed", "node", "role", "asks").orderBy("pos")) == 1
    x = walk.withColumn("__call", ((first & F.col("asks")) | (F.col("hand") & F.lit(fetch == "edge"))).cast("long"))
    upto = Window.partitionBy("seed").orderBy("pos").rowsBetween(Window.unboundedPreceding, 0)
    return x.withColumn("fetches", F.sum("__call").over(upto)).drop("__call")


def waves_sql(edges_sql: str, spec: Spec, seeds_sql: str, length: str, policy: str = "lazy", stitched: bool = True) -> str:
    """CTEs up to ``pw``, the visits of ``waves`` by the same coins, for SQL engines: all excursions advance together, and segments in use are counted by rows that travel with them. Graphs on which no seed falls short."""
    from incwalk.plans.walks import walks_sql

    t = coins.threshold(spec.eps)
    h = coins.sql_digest(spec.seed, "wave", "(seed || ':' || exc)", "0", "stp")
    h2 = coins.sql_digest(spec.seed, "wave-again", "(seed || ':' || exc)", "0", "stp")
    turn = "CASE WHEN role = 'hub' THEN 'auth' ELSE 'hub' END" if spec.alternating else "'hub'"
    usable = "(size > 1 OR role = 'auth')" if policy == "lazy" else "true"
    asks = "true" if policy == "once" else "alive"
    kept = "k > 1 OR again" if policy == "literal" else "true"
    none = "" if stitched else " WHERE false"
    return f"""{walks_sql(edges_sql, spec)},
sd AS ({seeds_sql}),
lg AS (SELECT ({length})::BIGINT AS len),
sg AS (SELECT src AS node, role, row_number() OVER (PARTITION BY src, role ORDER BY rep) AS k, tail FROM
  (SELECT src, rep, CASE WHEN rep < {spec.reps} THEN 'hub' ELSE 'auth' END AS role, count(*) AS size, list(node ORDER BY pos)[2:] AS tail FROM w0 GROUP BY 1, 2) WHERE {usable}),
wv AS (
  SELECT 0 AS round, 'head' AS kind, seed, exc, seed AS node, 'hub' AS role, 0::BIGINT AS stp, 'reset' AS how, false AS asks, false AS hand, 0::BIGINT AS k, NULL::BIGINT AS dst, NULL::BIGINT[] AS tail
  FROM sd, range((SELECT ceil({margin(policy)}::DOUBLE * len * {spec.eps}::DOUBLE)::BIGINT + 20 FROM lg)) e(exc)
  UNION ALL
  SELECT * FROM (
    WITH hd AS (SELECT *, role = 'auth' OR {coins.sql_a("h")} >= {t} AS alive, role = 'auth' OR {coins.sql_a("h2")} >= {t} AS again FROM
                 (SELECT round, seed, exc, node, role, stp, how, {h} AS h, {h2} AS h2 FROM wv WHERE kind = 'head')),
    us AS (SELECT seed, node, role, max(k) AS used FROM wv WHERE kind = 'used' GROUP BY 1, 2, 3),
    ks AS (SELECT hd.*, {asks} AS asks0, CASE WHEN {asks} THEN row_number() OVER (PARTITION BY hd.seed, hd.node, hd.role, {asks} ORDER BY exc) + coalesce(us.used, 0) END AS k0 FROM hd LEFT JOIN us ON us.seed = hd.seed AND us.node = hd.node AND us.role = hd.role),
    kk AS (SELECT * REPLACE (alive AND {"coalesce(" + "CASE WHEN k0 > 1 OR again THEN k0 END, 0) > 0" if policy == "literal" else "true"} AS alive), CASE WHEN {kept.replace("k >", "k0 >")} THEN k0 END AS k FROM ks),
    sx AS (SELECT kk.*, sg.tail FROM kk LEFT JOIN (SELECT * FROM sg{none}) sg ON sg.node = kk.node AND sg.role = kk.role AND sg.k = kk.k),
    gx AS (SELECT sx.*, d.deg, alive AND tail IS NULL AS hand, asks0 AND (alive OR tail IS NOT NULL) AS asks FROM sx LEFT JOIN d0 d ON d.src = sx.node AND d.way = sx.role),
    nx AS (SELECT gx.*, a.dst FROM gx LEFT JOIN a0 a ON gx.hand AND a.src = gx.node AND a.way = gx.role AND a.slot = ({coins.sql_b("gx.h")} * gx.deg) >> 32),
    gone AS (SELECT max(round) + 1 AS round, count(dst) AS n FROM nx)
    SELECT gone.round, 'done', seed, exc, node, role, stp, how, asks, hand, k, dst, tail FROM nx, gone
    UNION ALL SELECT gone.round, 'head', seed, exc, dst, {turn}, stp + 1, 'step', false, false, 0, NULL, NULL FROM nx, gone WHERE dst IS NOT NULL
    UNION ALL SELECT gone.round, 'used', seed, 0, node, role, 0, '', false, false, max(k), NULL, NULL FROM (SELECT seed, node, role, k FROM nx WHERE k IS NOT NULL UNION ALL SELECT seed, node, role, used FROM us), gone WHERE gone.n > 0 GROUP BY ALL)),
vs AS (SELECT seed, exc, stp, node, role, how, asks, hand FROM wv WHERE kind = 'done'
  UNION ALL SELECT seed, exc, stp + i, tail[i], CASE WHEN i % 2 = 0 THEN role ELSE {turn} END, 'segment', false, false FROM (SELECT *, unnest(range(1, len(tail) + 1)) AS i FROM wv WHERE kind = 'done' AND tail IS NOT NULL)),
pw AS (SELECT * FROM (SELECT seed, row_number() OVER (PARTITION BY seed ORDER BY exc, stp) - 1 AS pos, node, role, how, asks, hand FROM vs), lg WHERE pos < len)"""


def fetched_sql(fetch: str = "full") -> str:
    """CTE ``pf``: ``pw`` with the running count of ``fetched``."""
    more = " OR hand" if fetch == "edge" else ""
    return f"pf AS (SELECT *, sum(call) OVER (PARTITION BY seed ORDER BY pos) AS fetches FROM (SELECT *, ((asks AND row_number() OVER (PARTITION BY seed, node, role, asks ORDER BY pos) = 1){more})::INT AS call FROM pw))"


def frequencies(walk: DataFrame) -> DataFrame:
    """Of a walk's visits, or of their counts by node and role."""
    n = F.sum("visits") if "visits" in walk.columns else F.count("*")
    total = walk.groupBy("seed").agg(n.alias("n"))
    return walk.groupBy("seed", "node").agg(n.alias("visits")).join(total, "seed").select("seed", "node", "visits", (F.col("visits") / F.col("n")).alias("score"))


def exclude_known(scores: DataFrame, edges: DataFrame, seeds: DataFrame | None = None) -> DataFrame:
    """Without the seed itself and its direct neighbours. ``seeds``: those of the scores, where they are few, so that only their edges are shuffled."""
    known = edges.select(F.col("src").alias("seed"), F.col("dst").alias("node"))
    if seeds is not None:
        known = known.join(F.broadcast(seeds.select("seed")), "seed", "left_semi")
    return scores.where("node <> seed").join(known, ["seed", "node"], "left_anti")


def top(scores: DataFrame, k: int, by: str = "score") -> DataFrame:
    """The k best of each seed, ties by node; Spark limits groups before the shuffle."""
    w = Window.partitionBy("seed").orderBy(F.desc(by), "node")
    return scores.withColumn("rank", F.row_number().over(w)).where(F.col("rank") <= k)


def fitted_alpha(edges: DataFrame, seeds: DataFrame, alternating: bool = False, rounds: int = 5) -> float | None:
    """Mean exponent of the seeds' exact scores (authority scores of alternating walks) against ranks from 2 to 20 times a seed's out-degree; None where no seed has three such ranks."""
    most = 20 * (seeds.agg(F.max("friends")).first()[0] or 0) + 1  # the ranks that count, and the seed itself
    if alternating:
        x = exact.alternating_iteration(edges, rounds=rounds, seeds=seeds, best=most).select("seed", "node", F.col("auth").alias("score"))
    else:
        x = exact.power_iteration(edges, rounds=rounds, seeds=seeds, best=most).select("seed", "node", "score")
    x = x.where((F.col("node") != F.col("seed")) & (F.col("score") > 0))
    x = x.withColumn("rank", F.row_number().over(Window.partitionBy("seed").orderBy(F.desc("score"), "node"))).join(seeds, "seed")
    x = x.where(F.col("rank").between(2 * F.col("friends"), 20 * F.col("friends")))
    fits = x.groupBy("seed").agg((-F.regr_slope(F.log("score"), F.log("rank"))).alias("alpha"), F.count("*").alias("points"))
    return fits.where("points >= 3").agg(F.avg("alpha")).first()[0]


def usable_alpha(edges: DataFrame, seeds: DataFrame, spec: Spec) -> float:
    """The fitted exponent; 0.75 where that is none of the model's."""
    alpha = fitted_alpha(edges, seeds, spec.alternating)
    return alpha if alpha is not None and 0 < alpha < 1 else 0.75


def topk_length(edges: DataFrame, seeds: DataFrame, k: int, spec: Spec, c: float = 5.0, alpha: float | None = None) -> int:
    """Visits after which the k-th node of a seed is expected ``c`` times, by the fitted exponent or the one given.

    Of the visits of an alternating walk ``(1 - eps) / (2 - eps)`` are to authorities, which are what it ranks.
    """
    alpha = usable_alpha(edges, seeds, spec) if alpha is None else alpha
    every = (2 - spec.eps) / (1 - spec.eps) if spec.alternating else 1
    return math.ceil(every * theory.walk_length(max(G.nodes(edges).count(), k), k, c, alpha))


def topk_personalised(visits: DataFrame, edges: DataFrame, seeds: DataFrame, k: int, spec: Spec, c: float = 5.0, alpha: float | None = None, exclude: str | None = None) -> DataFrame:
    """``(seed, node, visits, score, rank)``: the ``k`` nodes visited most by a stitched walk of the length that the rule asks for; ``exclude="friends"`` leaves out the seed and its neighbours. Alternating walks rank authorities."""
    walk = save(visit_counts(visits, edges, seeds, topk_length(edges, seeds, k, spec, c, alpha), spec), "counts")
    scores = frequencies(walk.where("role = 'auth'") if spec.alternating else walk)
    return top(exclude_known(scores, edges, seeds) if exclude == "friends" else scores, k)


def alpha_sql(spec: Spec, rounds: int = 5) -> str:
    """``alpha`` as ``usable_alpha`` has it, out of ``e0`` and ``sd``."""
    w = "SELECT src, dst, 1 / count(*) OVER (PARTITION BY src) AS ow, 1 / count(*) OVER (PARTITION BY dst) AS iw FROM e0"
    if spec.alternating:
        step = ", ".join(f"m{i} AS (SELECT seed, dst AS node, sum(s * ow) AS s FROM y{i - 1} JOIN ew ON src = node GROUP BY 1, 2), y{i} AS (SELECT seed, node, sum(s) AS s FROM (SELECT seed, src AS node, s * iw * {1 - spec.eps!r}::DOUBLE AS s FROM m{i} JOIN ew ON dst = node UNION ALL SELECT seed, node, {spec.eps!r}::DOUBLE * s FROM y0) GROUP BY 1, 2)" for i in range(1, rounds + 1))
        last = f"SELECT seed, dst AS node, sum(s * ow) AS s FROM y{rounds} JOIN ew ON src = node GROUP BY 1, 2"
    else:
        step = ", ".join(f"y{i} AS (SELECT seed, node, sum(s) AS s FROM (SELECT seed, dst AS node, s * ow * {1 - spec.eps!r}::DOUBLE AS s FROM y{i - 1} JOIN ew ON src = node UNION ALL SELECT seed, node, {spec.eps!r}::DOUBLE * s FROM y0) GROUP BY 1, 2)" for i in range(1, rounds + 1))
        last = f"SELECT seed, node, s FROM y{rounds}"
    return f"""WITH ew AS ({w}), y0 AS (SELECT seed, seed AS node, 1.0::DOUBLE AS s FROM sd), {step},
  rk AS (SELECT seed, s, row_number() OVER (PARTITION BY seed ORDER BY s DESC, node) AS rank FROM ({last}) WHERE node <> seed AND s > 0),
  ft AS (SELECT seed, -regr_slope(ln(s), ln(rank)) AS a, count(*) AS points FROM rk JOIN sd USING (seed) WHERE rank BETWEEN 2 * friends AND 20 * friends GROUP BY 1)
  SELECT CASE WHEN avg(a) > 0 AND avg(a) < 1 THEN avg(a) ELSE 0.75 END AS alpha FROM ft WHERE points >= 3"""


def topk_length_sql(k: int, spec: Spec, c: float = 5.0) -> str:
    every = f"{(2 - spec.eps) / (1 - spec.eps)!r}::DOUBLE" if spec.alternating else "1"
    return f"SELECT ceil({every} * {c!r}::DOUBLE / (1 - alpha) * {k} * pow(greatest((SELECT count(*) FROM n0), {k})::DOUBLE / {k}, 1 - alpha)) FROM ({alpha_sql(spec)})"


def segment_frequency(visits: DataFrame, seeds: DataFrame) -> DataFrame:
    own = visits.join(seeds.select(F.col("seed").alias("src")), "src", "left_semi").where("rep >= 0")
    return own.groupBy(F.col("src").alias("seed"), "node").agg(F.count("*").alias("visits"))


def segment_endpoints(visits: DataFrame, seeds: DataFrame) -> DataFrame:
    return segment_frequency(visits.where("ended IS NOT NULL"), seeds)
