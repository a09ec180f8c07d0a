"""The walk store: segments from every node until their first reset, in long form.

A visit is ``(src, rep, pos, node, role, next, ended, epoch)``: walk ``rep`` of node ``src`` stands
at ``node`` as its ``pos``-th visit and goes on to ``next``. ``ended`` is ``reset``, ``stuck`` (survived its coin where there
is no edge) or null. Role ``hub`` flips the reset coin and steps forward; role ``auth``, in
alternating walks only, steps back without a coin. Two engines take the same walks by the same
coins: ``rounds`` joins the frontier with the slot table, several steps a job; ``local`` walks in
one stage against a broadcast adjacency, for graphs of a checked size.
"""

from __future__ import annotations

import weakref
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark import Broadcast
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from incwalk.functions import coins
from incwalk.plans import graph as G
from incwalk.store import _shuffles_end, discard, save

#: Edges that the driver may sort for a broadcast.
LOCAL_EDGES = 4_000_000
#: Edges that may be broadcast where Spark sorts them: 4 bytes each, twice for alternating walks.
COMPACT_EDGES = 40_000_000
#: Live walks up to which a round picks the rows of the slot table by the nodes it stands at.
SMALL_FRONTIER = 200_000
VISIT = "src long, rep int, pos int, node long, role string, next long, ended string, epoch int"
_ARROW = pa.schema([("src", pa.int64()), ("rep", pa.int32()), ("pos", pa.int32()), ("node", pa.int64()), ("role", pa.string()), ("next", pa.int64()), ("ended", pa.string()), ("epoch", pa.int32())])


@dataclass(frozen=True)
class Spec:
    reps: int = 2
    eps: float = 0.2
    seed: int = 1
    kind: str = "pagerank"  # or "alternating"
    coin: str = "portable"
    fuse: int = 4
    engine: str = "auto"

    @property
    def alternating(self) -> bool:
        return self.kind == "alternating"


def walk_key(src: Column, rep: Column) -> Column:
    return F.concat_ws(":", src.cast("string"), rep.cast("string"))


def heads(nodes: DataFrame, spec: Spec) -> DataFrame:
    """R walks a node; for alternating walks R that start forward and R that start back."""
    total = spec.reps * (2 if spec.alternating else 1)
    h = nodes.select(F.col("node").alias("src"), F.explode(F.sequence(F.lit(0), F.lit(total - 1))).alias("rep"))
    return h.select("src", "rep", F.lit(0).alias("pos"), F.col("src").alias("node"), F.when(F.col("rep") < spec.reps, "hub").otherwise("auth").alias("role"))


def grow(start: DataFrame, edges: DataFrame, spec: Spec, epoch: int = 0, tag: str = "build", adjacency: tuple[DataFrame, DataFrame] | None = None, count: int | None = None) -> DataFrame:
    """All visits from the heads on, the heads' own included. ``adjacency``: slot and degree tables, and ``count``: the number of edges, where they are at hand."""
    if on_broadcast(edges, spec, count):
        return _grow_local(start, edges, spec, epoch, tag, count)
    return _grow_rounds(start, adjacency or tables(edges, spec), spec, epoch, tag)


def _is_local(edges: DataFrame, spec: Spec, count: int | None = None) -> bool:
    if spec.engine != "auto":
        if spec.engine == "local" and (count if count is not None else edges.count()) > 4 * LOCAL_EDGES:
            raise ValueError("too many edges to broadcast; use engine='rounds' or 'auto'")
        return spec.engine == "local"
    return spec.coin == "portable" and (count if count is not None else edges.count()) <= LOCAL_EDGES


def on_broadcast(edges: DataFrame, spec: Spec, count: int | None = None) -> bool:
    """Whether walks grow on a broadcast adjacency: of a size that the driver sorts, or of one that Spark sorts for it."""
    if spec.engine != "auto" or spec.coin != "portable":
        return _is_local(edges, spec, count)
    return (count if count is not None else edges.count()) <= COMPACT_EDGES


def _step(frontier: DataFrame, adj: DataFrame, deg: DataFrame, spec: Spec, epoch: int, tag: str) -> DataFrame:
    """One step of all live walks. Rows that ended pass through; ``path`` gathers the visits of this job."""
    live = F.col("ended").isNull()
    a, b = coins.coin(spec.seed, tag, walk_key(F.col("src"), F.col("rep")), F.lit(epoch), F.col("pos"), spec.coin)
    key = [F.when(live, F.col("node")).alias("node_key"), "*"]
    x = frontier.select(*key).join(deg.select(F.col("src").alias("node_key"), F.col("way").alias("role"), "deg"), ["node_key", "role"], "left")
    stop = F.when(~live, F.col("ended")).when((F.col("role") == "hub") & (a < coins.threshold(spec.eps)), F.lit("reset")).when(F.col("deg").isNull(), F.lit("stuck"))
    x = x.select("src", "rep", "pos", "node", "role", "path", live.alias("live"), stop.alias("ended"), F.when(stop.isNull(), coins.slot(b, F.col("deg"))).alias("slot"))
    x = x.join(adj.select(F.col("src").alias("node"), F.col("way").alias("role"), "slot", F.col("dst").alias("next")), ["node", "role", "slot"], "left")
    visit = F.struct("pos", "node", "role", "next", "ended")
    moved = F.col("ended").isNull()
    turned = F.when(F.col("role") == "hub", "auth").otherwise("hub") if spec.alternating else F.lit("hub")
    return x.select("src", "rep", F.when(moved, F.col("pos") + 1).otherwise(F.col("pos")).alias("pos"), F.when(moved, F.col("next")).otherwise(F.col("node")).alias("node"), F.when(moved, turned).otherwise(F.col("role")).alias("role"), F.when(F.col("live"), F.array_append("path", visit)).otherwise(F.col("path")).alias("path"), "ended")


def both_ways(edges: DataFrame, spec: Spec) -> tuple[DataFrame, DataFrame]:
    """Slot and degree tables by the way of the step, as the role names it. Fast coins go with salted numbering, so that no task sorts a whole hub; portable ones with the order of arrival, which SQL shares."""
    number = G.slots if spec.coin == "portable" else G.salted_slots
    adj = number(edges).withColumn("way", F.lit("hub"))
    if spec.alternating:
        adj = adj.unionByName(number(G.reverse(edges)).withColumn("way", F.lit("auth")))
    return adj, adj.groupBy("src", "way").agg(F.count("*").alias("deg"))


def tables(edges: DataFrame, spec: Spec) -> tuple[DataFrame, DataFrame]:
    adj, deg = both_ways(edges, spec)
    return save(adj.select("src", "way", "slot", "dst"), "adj"), save(deg, "deg")


def _grow_rounds(start, adjacency, spec, epoch, tag) -> DataFrame:
    """A small frontier first picks the rows of the tables that it can need, by semi joins that its size lets Spark broadcast, so that a repair of few walks shuffles no whole graph."""
    empty = F.array().cast("array<struct<pos:int,node:bigint,role:string,next:bigint,ended:string>>")
    frontier, out = save(start.select("src", "rep", "pos", "node", "role"), "frontier"), None
    while True:
        few = frontier.count() <= SMALL_FRONTIER
        x = frontier.select("*", empty.alias("path"), F.lit(None).cast("string").alias("ended"))
        for _ in range(1 if few else spec.fuse):
            adj, deg = adjacency
            if few:
                here = frontier.select(F.col("node").alias("src"), F.col("role").alias("way")).distinct()
                adj, deg = adj.join(here, ["src", "way"], "left_semi"), deg.join(here, ["src", "way"], "left_semi")
            x = _step(x, adj, deg, spec, epoch, tag)
        x = save(x, "frontier")
        visits = x.select("src", "rep", F.explode("path").alias("v")).select("src", "rep", "v.pos", "v.node", "v.role", "v.next", "v.ended", F.lit(epoch).alias("epoch"))
        out = visits if out is None else out.unionByName(visits)
        frontier = x.where("ended IS NULL").select("src", "rep", "pos", "node", "role")
        if frontier.isEmpty():
            return out


class Adjacency:
    """Compressed rows of a graph, for broadcast: nodes as places in their sorted list, 4 bytes an edge and way; slots in the order of arrival.

    Up to ``LOCAL_EDGES`` the driver sorts the edges. Beyond it Spark numbers and sorts them, and only the far ends come to the driver.
    """

    def __init__(self, edges: DataFrame, both: bool, count: int | None = None, ways: tuple[str, ...] | None = None):
        e = edges.select("src", "dst", "ord" if "ord" in edges.columns else F.lit(0).cast("long").alias("ord"))
        ways = ways or (("hub", "auth") if both else ("hub",))
        if (count if count is not None else e.count()) > LOCAL_EDGES:
            self._by_spark(e, ways)
            return
        t = e.toArrow()
        s, d, o = (t.column(c).to_numpy() for c in ("src", "dst", "ord"))
        self.nodes = np.union1d(np.unique(s), np.unique(d))
        s, d = (np.searchsorted(self.nodes, x).astype(np.int32) for x in (s, d))
        self.ways = {}
        for way in ways:
            near, far = (s, d) if way == "hub" else (d, s)
            self.ways[way] = self._starts(np.bincount(near, minlength=len(self.nodes))), far[np.lexsort((far, o, near))]

    def _by_spark(self, e: DataFrame, ways: tuple[str, ...]) -> None:
        spark, number = e.sparkSession, pa.schema([("s", pa.int32()), ("d", pa.int32()), ("ord", pa.int64())])
        self.nodes = np.sort(G.nodes(e).toArrow().column("node").to_numpy())
        held, n = spark.sparkContext.broadcast(self.nodes), len(self.nodes)

        def places(batches):
            for batch in batches:
                s, d = (np.searchsorted(held.value, batch.column(c).to_numpy()).astype(np.int32) for c in ("src", "dst"))
                yield pa.RecordBatch.from_arrays([pa.array(s), pa.array(d), batch.column("ord")], schema=number)

        numbered = save(e.mapInArrow(places, "s int, d int, ord long"), "numbered")
        parts, self.ways = int(spark.conf.get("spark.sql.shuffle.partitions")), {}
        for way in ways:
            near, far = ("s", "d") if way == "hub" else ("d", "s")
            size, sized = np.zeros(n, np.int64), numbered.groupBy(near).count().toArrow()
            size[sized.column(near).to_numpy()] = sized.column("count").to_numpy()
            rows = numbered.repartitionByRange(parts, near).sortWithinPartitions(near, "ord", far).select(far)
            with _shuffles_end(spark):
                self.ways[way] = self._starts(size), rows.toArrow().column(far).to_numpy()  # in the order of the ranges
        discard(numbered)

    @staticmethod
    def _starts(sizes: np.ndarray) -> np.ndarray:
        return np.r_[0, np.cumsum(sizes)]

    def find(self, nodes: np.ndarray) -> np.ndarray:
        """Places of nodes; the number of nodes itself, which has no edges, for one that is in no edge."""
        at = np.searchsorted(self.nodes, nodes)
        return np.where(self.nodes[np.minimum(at, len(self.nodes) - 1)] == nodes, at, len(self.nodes)) if len(self.nodes) else at

    def degrees(self, places: np.ndarray, role: str = "hub") -> np.ndarray:
        starts = self.ways[role][0]
        return starts[np.minimum(places + 1, len(self.nodes))] - starts[places]

    def targets(self, places: np.ndarray, slots: np.ndarray, role: str = "hub") -> np.ndarray:
        starts, to = self.ways[role]
        return to[starts[places] + slots]

    def degree(self, node: int, role: str = "hub") -> int:
        return int(self.degrees(self.find(np.array([node])), role)[0])

    def target(self, node: int, slot: int, role: str = "hub") -> int:
        return int(self.nodes[self.targets(self.find(np.array([node])), np.array([slot]), role)[0]])


#: Whether both ways are held, and the broadcast rows, of each table of edges that is still referred to.
_HELD: weakref.WeakKeyDictionary = weakref.WeakKeyDictionary()


def held_rows(edges: DataFrame, both: bool, count: int | None = None) -> Broadcast:
    """The broadcast adjacency of ``edges``: a query that walks, scores and walks again sorts its graph once."""
    got = _HELD.get(edges)
    if got is None or (both and not got[0]):
        got = _HELD[edges] = both, edges.sparkSession.sparkContext.broadcast(Adjacency(edges, both, count))
    return got[1]


def _words(names: list[str], codes: np.ndarray) -> pa.Array:
    """Text out of a few names by code; null where that is negative."""
    return pa.array(names, pa.string()).take(pa.array(codes, pa.int32(), mask=codes < 0))


ROLES = ("hub", "auth")


def dealt(rows: DataFrame, key: str) -> DataFrame:
    """By ``key`` to some tasks a core: the number is given, since Spark would join small partitions, which are much work here, into one."""
    spark = rows.sparkSession
    return rows.repartition(max(int(spark.conf.get("spark.sql.shuffle.partitions")), 3 * spark.sparkContext.defaultParallelism), key)


def advance(g: Adjacency, place: np.ndarray, role: np.ndarray, b: np.ndarray, alternating: bool) -> tuple[np.ndarray, np.ndarray]:
    """Degree in its role, and where the coin leads, for each place; places without an edge stay."""
    deg, to = np.zeros(len(place), np.int64), place.copy()
    for code, name in enumerate(ROLES[: 2 if alternating else 1]):
        own = np.flatnonzero(role == code)
        deg[own] = g.degrees(place[own], name)
        own = own[deg[own] > 0]
        to[own] = g.targets(place[own], b[own] * deg[own] >> 32, name)
    return deg, to


def _grow_local(start, edges, spec, epoch, tag, count=None) -> DataFrame:
    """All walks of a batch advance together."""
    held = held_rows(edges, spec.alternating, count)
    stop_below, alternating, seed = coins.threshold(spec.eps), spec.alternating, spec.seed

    def run(batches):
        g = held.value
        for batch in batches:
            src, rep, pos, node = (batch.column(c).to_numpy() for c in ("src", "rep", "pos", "node"))
            keys = [f"{s}:{r}" for s, r in zip(src.tolist(), rep.tolist(), strict=True)]
            role = np.fromiter((r == "auth" for r in batch.column("role").to_pylist()), np.int8, len(src))
            live, place, names = np.arange(len(src)), g.find(node), node
            while len(live):
                a, b = coins.python_coins(seed, tag, [keys[i] for i in live.tolist()], epoch, pos)
                deg, to = advance(g, place, role, b, alternating)
                ended = np.where((role == 0) & (a < stop_below), 0, np.where(deg == 0, 1, -1))
                goes = ended < 0
                after = np.where(goes, to, 0)
                following = g.nodes[after] if len(g.nodes) else after
                yield pa.RecordBatch.from_arrays([pa.array(src[live]), pa.array(rep[live], pa.int32()), pa.array(pos, pa.int32()), pa.array(names), _words(list(ROLES), role), pa.array(following, pa.int64(), mask=~goes), _words(["reset", "stuck"], ended), pa.array(np.full(len(live), epoch, np.int32))], schema=_ARROW)
                live, place, names, pos = live[goes], to[goes], following[goes], pos[goes] + 1
                role = 1 - role[goes] if alternating else role[goes]

    return dealt(start.select("src", "rep", "pos", "node", "role"), "src").mapInArrow(run, VISIT)


def build_store(edges: DataFrame, spec: Spec) -> DataFrame:
    """R fresh walks from every node (2R alternating ones)."""
    return grow(heads(G.nodes(edges), spec), edges, spec)


def segments(visits: DataFrame) -> DataFrame:
    """One row a walk: ``path`` in order, ``ended`` and length."""
    ordered = F.array_sort(F.collect_list(F.struct("pos", "node", "role", "ended")))
    s = visits.groupBy("src", "rep").agg(ordered.alias("v"))
    return s.select("src", "rep", F.col("v.node").alias("path"), F.element_at("v.ended", -1).alias("ended"), F.size("v").alias("length"))


def walks_sql(edges_sql: str, spec: Spec, name: str = "w0") -> str:
    """CTEs ``e0``, ``a0``, ``d0`` and the recursive visits ``w0`` (hub walks or alternating ones) for SQL engines."""
    total = spec.reps * (2 if spec.alternating else 1)
    h = coins.sql_digest(spec.seed, "build", "(src || ':' || rep)", "0", "pos")
    back = "UNION ALL SELECT dst, row_number() OVER (PARTITION BY dst ORDER BY ord, src) - 1, src, 'auth' FROM e0" if spec.alternating else ""
    turn = "CASE WHEN role = 'hub' THEN 'auth' ELSE 'hub' END" if spec.alternating else "'hub'"
    return f"""
e0 AS ({edges_sql}),
a0 AS (SELECT src, row_number() OVER (PARTITION BY src ORDER BY ord, dst) - 1 AS slot, dst, 'hub' AS way FROM e0 {back}),
d0 AS (SELECT src, way, count(*) AS deg FROM a0 GROUP BY 1, 2),
n0 AS (SELECT src AS node FROM e0 UNION SELECT dst FROM e0),
r0 AS (
  SELECT node AS src, rep, 0::BIGINT AS pos, node, CASE WHEN rep < {spec.reps} THEN 'hub' ELSE 'auth' END AS role FROM n0, range({total}) t(rep)
  UNION ALL
  SELECT x.src, x.rep, x.pos + 1, a.dst, {turn}
  FROM (SELECT *, {h} AS h FROM r0) x JOIN d0 d ON d.src = x.node AND d.way = x.role
  JOIN a0 a ON a.src = x.node AND a.way = x.role AND a.slot = ({coins.sql_b("x.h")} * d.deg) >> 32
  WHERE x.role <> 'hub' OR {coins.sql_a("x.h")} >= {coins.threshold(spec.eps)}),
{name} AS (
  SELECT x.src, x.rep, x.pos, x.node, x.role, CASE WHEN x.role = 'hub' AND {coins.sql_a("h")} < {coins.threshold(spec.eps)} THEN 'reset' WHEN d.deg IS NULL THEN 'stuck' END AS ended
  FROM (SELECT *, {h} AS h FROM r0) x LEFT JOIN d0 d ON d.src = x.node AND d.way = x.role)"""
