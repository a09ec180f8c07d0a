"""The maintained walk store: edges arrive and leave in batches, and only walks that change are touched.

The store is layers. The first holds all visits, in buckets by node; each batch adds the visits it
grew and a cut for each walk it rerouted, and rewrites nothing. A visit is dead where a later cut of
its walk lies at or before it. A batch reads the visits at the sources of its changes (a visit knows
where it went, so no walk is read whole), the edges at those sources, and slots where its regrown
walks pass; compaction merges the layers after ``MOST_LAYERS``. A manifest published last makes a
batch count wholly or not at all, and lets another driver go on from the folder.

A batch changes only walks that would have behaved differently. At a source with ``d_surv`` edges
left over from before and ``d`` in all, a continuing (or stuck) visit draws a slot among ``d``: a
slot of a new edge switches it there, which is what the single arrivals one after another do; a
visit whose edge left draws among all ``d``. The first such visit of a walk cuts it, and the walk
grows again from the edge drawn, by coins of the new epoch.
"""

from __future__ import annotations

import json
import math
from dataclasses import asdict

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from incwalk.functions import coins, theory
from incwalk.plans import graph as G
from incwalk.plans import history
from incwalk.plans.ranking import numbered
from incwalk.plans.walks import Spec, grow, heads, on_broadcast, tables, walk_key
from incwalk.store import fresh_path, publish, published, save

#: Layers after which a batch compacts the store.
MOST_LAYERS = 12
#: Visits in a bucket of the first layer, about; and the most buckets.
BUCKET, MOST_BUCKETS = 2_000_000, 4096
KINDS = ("visits", "cuts", "edges", "adj", "deg", "counts")
LOG = "epoch int, walks_rerouted long, steps_redone long, edges_added long, edges_gone long, visits_read long, gate_sources long, gate_calls long"


def last_changes(changes: DataFrame) -> DataFrame:
    """Of several changes of an edge in a batch the last by ``ord`` holds; self-loops are dropped."""
    last = changes.where("src <> dst").groupBy("src", "dst").agg(F.max(F.struct("ord", "op")).alias("c"))
    return last.select("src", "dst", F.col("c.op").alias("op"), F.col("c.ord").alias("ord"))


def effective(edges: DataFrame, last: DataFrame) -> tuple[DataFrame, DataFrame]:
    """``(gone, added)``: absent edges cannot leave, present ones cannot arrive."""
    gone = last.where("op = '-'").join(edges.select("src", "dst"), ["src", "dst"], "left_semi").select("src", "dst")
    added = last.where("op = '+'").join(edges.select("src", "dst"), ["src", "dst"], "left_anti").select("src", "dst", "ord")
    return gone, added


def changed_edges(edges: DataFrame, changes: DataFrame) -> tuple[DataFrame, DataFrame, DataFrame]:
    """``(new edge set, edges gone, edges added)``."""
    gone, added = effective(edges, last_changes(changes))
    return edges.select("src", "dst", "ord").join(gone, ["src", "dst"], "left_anti").unionByName(added), gone, added


class WalkStore:
    """A store of walks in a folder. ``create`` builds it, ``open`` goes on with one that is there."""

    def __init__(self, spark: SparkSession, folder: str, state: dict):
        self.spark, self.folder, self.state = spark, folder, state
        self.spec = Spec(**state["spec"])

    @classmethod
    def create(cls, edges: DataFrame, spec: Spec, folder: str | None = None) -> WalkStore:
        """Walks from all nodes of ``edges`` (src, dst, ord)."""
        spark = edges.sparkSession
        folder = folder or fresh_path(spark, "store")
        e = edges.select("src", "dst", "ord")
        m = e.count()
        n = m if m <= BUCKET * spec.eps / spec.reps else G.nodes(e).count()  # sizes the buckets alone
        buckets = max(4, min(MOST_BUCKETS, math.ceil(n * spec.reps / spec.eps / BUCKET)))
        store = cls(spark, folder, {"epoch": 0, "m": m, "buckets": buckets, "spec": asdict(spec), "batch": None, "layers": {k: [] for k in KINDS}})
        adjacency = None
        if not on_broadcast(e, spec, m):
            adjacency = tables(e, spec)
        visits = grow(heads(G.nodes(e), spec), e, spec, adjacency=adjacency, count=m)
        layers = {"visits": store._base(visits), "edges": store._layer("edges", e.withColumn("op", F.lit("+")).withColumn("epoch", F.lit(0)))}
        if adjacency:
            layers |= {"adj": store._layer("adj", adjacency[0].withColumn("epoch", F.lit(0))), "deg": store._layer("deg", adjacency[1].withColumn("epoch", F.lit(0)))}
        store._publish({k: [v] for k, v in layers.items()})
        return store

    @classmethod
    def open(cls, spark: SparkSession, folder: str) -> WalkStore | None:
        """The store as last published; None where there is none."""
        text = published(spark, folder, "manifest-")
        return cls(spark, folder, json.loads(text)) if text else None

    # layers
    def _layer(self, kind: str, df: DataFrame, partition_by: list[str] | None = None) -> dict:
        path = fresh_path(self.spark, "layer").rsplit("/", 1)[1]
        save(df, kind, f"{self.folder}/{kind}-{path}", partition_by)
        return {"path": f"{self.folder}/{kind}-{path}", "schema": df.schema.json()}

    def _bucket(self, node) -> F.Column:
        return F.pmod(F.xxhash64(node), F.lit(self.state["buckets"])).cast("int")

    def _base(self, visits: DataFrame) -> dict:
        """A layer in buckets by node."""
        rows = visits.select("src", "rep", "pos", "node", "role", "next", "ended", "epoch").withColumn("bucket", self._bucket(F.col("node")))
        spread = F.pmod(F.xxhash64("src", "rep"), F.lit(max(1, int(self.spark.conf.get("spark.sql.shuffle.partitions")) // self.state["buckets"])))
        return self._layer("visits", rows.repartition("bucket", spread).sortWithinPartitions("bucket", "node"), ["bucket"])

    def _read(self, kind: str, buckets: list[int] | None = None) -> DataFrame | None:
        from pyspark.sql.types import StructType

        out = None
        for x in self.state["layers"][kind]:
            df = self.spark.read.schema(StructType.fromJson(json.loads(x["schema"]))).parquet(x["path"])
            if "bucket" in df.columns:
                df = (df.where(F.col("bucket").isin(buckets)) if buckets is not None else df).drop("bucket")
            out = df if out is None else out.unionByName(df)
        return out

    def _publish(self, more: dict, **state) -> None:
        layers = {k: self.state["layers"][k] + more.get(k, []) for k in KINDS}
        self.state = self.state | state | {"layers": layers}
        publish(self.spark, f"{self.folder}/manifest-{self.state['epoch']:09d}", json.dumps(self.state))

    @property
    def epoch(self) -> int:
        return self.state["epoch"]

    # reading
    def _live(self, visits: DataFrame) -> DataFrame:
        cuts = self._read("cuts")
        if cuts is None:
            return visits
        c = cuts.select(F.col("src").alias("c_src"), F.col("rep").alias("c_rep"), F.col("pos").alias("c_pos"), F.col("epoch").alias("c_epoch"))
        dead = (F.col("src") == F.col("c_src")) & (F.col("rep") == F.col("c_rep")) & (F.col("c_epoch") > F.col("epoch")) & (F.col("pos") >= F.col("c_pos"))
        return visits.join(c, dead, "left_anti")

    def visits(self) -> DataFrame:
        """All live visits."""
        return self._live(self._read("visits"))

    def visits_at(self, nodes: DataFrame) -> DataFrame:
        """Live visits at the given nodes (and roles, where ``nodes`` has them): only their buckets of the first layer are read."""
        keys = [c for c in ("node", "role") if c in nodes.columns]
        buckets = None
        if self.state["buckets"] > 8:  # reading few buckets whole costs less than asking which
            buckets = [r[0] for r in nodes.select(self._bucket(F.col("node"))).distinct().collect()]  # as many as there are buckets, at most
        return self._live(self._read("visits", buckets).join(nodes.select(*keys).distinct(), keys, "left_semi"))

    def segments_of(self, nodes: DataFrame) -> DataFrame:
        """Live visits of the walks that start at the given nodes."""
        return self._live(self._read("visits").join(nodes.select(F.col("node").alias("src")).distinct(), "src", "left_semi"))

    def through(self, nodes: DataFrame) -> DataFrame:
        """Live visits of all walks that pass through the given nodes."""
        return self.visits().join(self.visits_at(nodes).select("src", "rep").distinct(), ["src", "rep"], "left_semi")

    def edges(self) -> DataFrame:
        """Live edges. An edge that left and came back is in several layers; its last one holds."""
        return self._live_edges(self._read("edges"))

    def _live_edges(self, e: DataFrame) -> DataFrame:
        if len(self.state["layers"]["edges"]) > 1:
            gone = e.where("op = '-'").select(F.col("src").alias("g_src"), F.col("dst").alias("g_dst"), F.col("epoch").alias("g_epoch"))
            e = e.where("op = '+'").join(gone, (F.col("src") == F.col("g_src")) & (F.col("dst") == F.col("g_dst")) & (F.col("g_epoch") > F.col("epoch")), "left_anti")
        return e.select("src", "dst", "ord")

    def _adjacency(self) -> tuple[DataFrame, DataFrame] | None:
        """Slot and degree tables: of a node's rows those of its last layer."""
        adj, deg = self._read("adj"), self._read("deg")
        if adj is None:
            return None
        if len(self.state["layers"]["adj"]) > 1:
            later = deg.where("epoch > 0").select(F.col("src").alias("l_src"), F.col("way").alias("l_way"), F.col("epoch").alias("l_epoch"))
            old = (F.col("src") == F.col("l_src")) & (F.col("way") == F.col("l_way")) & (F.col("l_epoch") > F.col("epoch"))
            adj, deg = adj.join(later, old, "left_anti"), deg.join(later, old, "left_anti").where("deg > 0")
        return adj.select("src", "way", "slot", "dst"), deg.select("src", "way", "deg")

    def counters(self) -> DataFrame:
        """``W`` (walks through a node), visits, continuing visits and degrees: counted once, then kept up by the signed changes of each batch."""
        if not self.state["layers"]["counts"]:
            self._publish({"counts": [self._layer("counts", self._count(self.visits()))]})
        sums = self._read("counts").groupBy("node").agg(*(F.sum(c).alias(c) for c in ("w_segments", "visits", "continuing"))).where("visits > 0")
        return sums.join(G.degrees(self.edges()), "node", "full").na.fill(0)

    @staticmethod
    def _count(visits: DataFrame, sign: int = 1) -> DataFrame:
        per_walk = visits.groupBy("node", "src", "rep").agg(F.count("*").alias("n"), F.count_if(F.col("ended").isNull()).alias("c"))
        return per_walk.groupBy("node").agg((F.count("*") * sign).alias("w_segments"), (F.sum("n") * sign).alias("visits"), (F.sum("c") * sign).alias("continuing"))

    # changing
    def _slots(self, own: DataFrame) -> DataFrame:
        """Survivors first; then the order of arrival, or of salts under fast coins."""
        return G.numbered_within(own, ["node", "role"], "fresh", ["ord", "to"], None if self.spec.coin == "portable" else "to")

    def apply(self, changes: DataFrame, reroute: str = "suffix", gate: str | None = None, batch: int | None = None) -> DataFrame:
        """Applies a batch of ``changes`` (op, src, dst, ord) and gives its ledger, a row.

        ``reroute="restart"`` grows a cut walk from its own source instead, which is simpler and
        biased: walks not chosen are conditioned on few visits to the source, the chosen ones are not.
        ``gate="ledger"`` counts the sources at which the counters alone would have let the store
        be called; ``gate="skip"`` draws from the counters which visits switch, and reads no visit at
        sources where none does (for batches that only add edges).
        """
        spec, epoch = self.spec, self.epoch + 1
        last = save(last_changes(changes.select("op", "src", "dst", "ord")), "changes")
        ways = {"hub": ("src", "dst")} | ({"auth": ("dst", "src")} if spec.alternating else {})
        e = self._read("edges")
        at = {way: save(self._live_edges(e.join(last.select(near).distinct(), near, "left_semi")), "at") for way, (near, _) in ways.items()}
        gone, added = effective(at["hub"], last)
        both = save(added.withColumn("fresh", F.lit(1)).unionByName(gone.select("src", "dst", F.lit(None).cast("long").alias("ord"), F.lit(0).alias("fresh"))), "effective")
        gone, added = both.where("fresh = 0").select("src", "dst"), both.where("fresh = 1").select("src", "dst", "ord")
        ids = own = lost = None
        for way, (near, far) in ways.items():
            who = both.select(F.col(near).alias("node"), F.lit(way).alias("role")).distinct()
            rows = at[way].join(gone, ["src", "dst"], "left_anti").withColumn("fresh", F.lit(0)).unionByName(added.withColumn("fresh", F.lit(1)))
            rows = rows.select(F.col(near).alias("node"), F.lit(way).alias("role"), F.col(far).alias("to"), "ord", "fresh").join(who, ["node", "role"], "left_semi")
            left = gone.select(F.col(near).alias("node"), F.col(far).alias("next"), F.lit(way).alias("role"), F.lit(True).alias("lost"))
            ids, own, lost = (who, rows, left) if ids is None else (ids.unionByName(who), own.unionByName(rows), lost.unionByName(left))
        own = slots = save(self._slots(own).select("node", "role", "slot", "to", "ord", "fresh"), "slots")
        degs = ids.join(own.groupBy("node", "role").agg(F.sum(1 - F.col("fresh")).alias("d_surv"), F.count("*").alias("d")), ["node", "role"], "left")
        degs = save(degs.select("node", "role", F.coalesce("d_surv", F.lit(0)).cast("long").alias("d_surv"), F.coalesce("d", F.lit(0)).cast("long").alias("d")), "degrees")

        gated = None
        if gate is not None:
            gated = self._gate(degs, epoch, gate)
        _, b = coins.coin(spec.seed, "update", walk_key(F.col("src"), F.col("rep")), F.lit(epoch), F.col("pos"), spec.coin)
        if gate == "skip":
            if spec.alternating or not gone.isEmpty():
                raise ValueError("the skipping gate is for arrivals at forward walks")
            seen = save(self.visits_at(gated.where("calls")).where("ended IS NULL OR ended = 'stuck'"), "seen")
            x = G.numbered_within(seen.withColumn("one", F.lit(0)), ["node", "role"], "one", ["src", "rep", "pos"])
            picks = gated.select("node", F.explode("picks").alias("slot"))
            fresh = F.col("d_surv") + coins.slot(b, F.col("d") - F.col("d_surv"))  # a switching visit takes a uniform new edge
            x = x.join(picks, ["node", "slot"], "left_semi").drop("slot").join(degs, ["node", "role"]).withColumn("slot", fresh)
        else:
            seen = save(self.visits_at(degs).where("ended IS NULL OR ended = 'stuck'"), "seen")
            x = seen.join(degs, ["node", "role"]).join(lost, ["node", "next", "role"], "left").withColumn("slot", coins.slot(b, F.col("d")))
            x = x.where(F.col("lost") | (F.col("slot") >= F.col("d_surv")) & (F.col("d") > 0))
        first = x.groupBy("src", "rep").agg(F.min(F.struct("pos", "node", "role", "slot", "d")).alias("c")).select("src", "rep", "c.*")
        cut = save(first.join(slots.select("node", "role", "slot", "to"), ["node", "role", "slot"], "left").select("src", "rep", "pos", "node", "role", "to"), "cuts")

        arrived = G.nodes(added)
        known = self.visits_at(arrived).where("pos = 0 AND rep = 0 AND src = node").select("node")
        fresh = heads(arrived.join(known, "node", "left_anti"), spec)
        turned = F.when(F.col("role") == "hub", "auth").otherwise("hub") if spec.alternating else F.lit("hub")
        if reroute == "restart":
            again = cut.select("src", "rep", F.lit(0).alias("pos"), F.col("src").alias("node"), F.when(F.col("rep") < spec.reps, "hub").otherwise("auth").alias("role"))
            stay, marks = None, cut.select("src", "rep", F.lit(0).alias("pos"))
        else:
            stay = cut.select("src", "rep", "pos", "node", "role", F.col("to").alias("next"), F.when(F.col("to").isNull(), "stuck").alias("ended"), F.lit(epoch).alias("epoch"))
            again = cut.where("to IS NOT NULL").select("src", "rep", (F.col("pos") + 1).alias("pos"), F.col("to").alias("node"), turned.alias("role"))
            marks = cut.select("src", "rep", "pos")
        n_added, n_gone = both.agg(F.count_if(F.col("fresh") == 1), F.count_if(F.col("fresh") == 0)).first()
        m = self.state["m"] + n_added - n_gone
        more = {"edges": [self._layer("edges", added.select("src", "dst", "ord", F.lit("+").alias("op"), F.lit(epoch).alias("epoch")).unionByName(gone.select("src", "dst", F.lit(None).cast("long").alias("ord"), F.lit("-").alias("op"), F.lit(epoch).alias("epoch"))))]}
        new, adjacency = self._with(more["edges"]).edges(), None
        if not on_broadcast(new, spec, m):
            # the touched nodes' slots again, in the order of arrival that a fresh build has
            if self.state["layers"]["adj"]:
                listed = G.numbered_within(own.drop("slot").withColumn("one", F.lit(0)), ["node", "role"], "one", ["ord", "to"], None if spec.coin == "portable" else "to")
                more["adj"] = [self._layer("adj", listed.select(F.col("node").alias("src"), F.col("role").alias("way"), "slot", F.col("to").alias("dst"), F.lit(epoch).alias("epoch")))]
                more["deg"] = [self._layer("deg", degs.select(F.col("node").alias("src"), F.col("role").alias("way"), F.col("d").alias("deg"), F.lit(epoch).alias("epoch")))]
            else:
                whole = tables(new, spec)
                more["adj"], more["deg"] = [self._layer("adj", whole[0].withColumn("epoch", F.lit(0)))], [self._layer("deg", whole[1].withColumn("epoch", F.lit(0)))]
            adjacency = self._with(more["adj"], "adj")._with(more["deg"], "deg")._adjacency()
        grown = save(grow(again.unionByName(fresh), new, spec, epoch, adjacency=adjacency, count=m), "grown")
        tail = grown if stay is None else stay.unionByName(grown)
        more |= {"visits": [self._layer("visits", tail.select("src", "rep", "pos", "node", "role", "next", "ended", "epoch"))], "cuts": [self._layer("cuts", marks.withColumn("epoch", F.lit(epoch)))]}
        if self.state["layers"]["counts"]:
            walks = cut.select("src", "rep")
            before = self._count(self.visits().join(walks, ["src", "rep"], "left_semi"), -1)
            after = self._with(more["visits"], "visits")._with(more["cuts"], "cuts").visits().where("epoch <= %d" % epoch)
            now = self._count(after.join(walks.union(fresh.select("src", "rep")), ["src", "rep"], "left_semi"))
            more["counts"] = [self._layer("counts", before.unionByName(now))]
        row = (epoch, cut.count(), grown.count(), n_added, n_gone, seen.count(), *(gated.agg(F.count("*"), F.count_if("calls")).first() if gated is not None else (None, None)))
        self._publish(more, epoch=epoch, m=m, batch=batch if batch is not None else self.state["batch"])
        if len(self.state["layers"]["visits"]) > MOST_LAYERS:
            self.compact()
        return self.spark.createDataFrame([row], LOG)

    def _with(self, layers: list, kind: str = "edges") -> WalkStore:
        """The store as it will be with these layers."""
        state = self.state | {"layers": self.state["layers"] | {kind: self.state["layers"][kind] + layers}}
        return WalkStore(self.spark, self.folder, state)

    def compact(self) -> None:
        """Merges the layers: live visits in buckets, live edges, slots and counts."""
        layers = {"visits": [self._base(self.visits())], "cuts": [], "edges": [self._layer("edges", self.edges().withColumn("op", F.lit("+")).withColumn("epoch", F.lit(0)))]}
        if adjacency := self._adjacency():
            layers |= {"adj": [self._layer("adj", adjacency[0].withColumn("epoch", F.lit(0)))], "deg": [self._layer("deg", adjacency[1].withColumn("epoch", F.lit(0)))]}
        if self.state["layers"]["counts"]:
            layers["counts"] = [self._layer("counts", self._read("counts").groupBy("node").agg(*(F.sum(c).alias(c) for c in ("w_segments", "visits", "continuing"))))]
        self.state = self.state | {"layers": {k: [] for k in KINDS}}
        self._publish(layers)

    def _gate(self, degs: DataFrame, epoch: int, how: str) -> DataFrame:
        """``(node, role, calls, picks)``: by the continuing visits V of a source and its share p of new edges, whether any visit switches, and which.

        The first switching visit is geometric in p, and so is the distance to each next one; a first
        one beyond V means that the store need not be called.
        """
        spec = self.spec
        v = self.visits_counted().join(degs, "node", "right").na.fill(0, ["going"])
        p = (F.col("d") - F.col("d_surv")) / F.greatest(F.col("d"), F.lit(1))
        rows = v.select("node", "role", "going", p.alias("p"))
        if how == "ledger":
            a, _ = coins.coin(spec.seed, "gate", F.concat_ws(":", F.col("node").cast("string"), "role"), F.lit(epoch), F.lit(0), spec.coin)
            return rows.select("node", "role", (a < F.floor((1 - F.pow(1 - F.col("p"), F.col("going"))) * coins.FULL)).alias("calls"))

        def skip(batches):
            for batch in batches:
                got = {"node": [], "role": [], "picks": []}
                for node, role, going, p in zip(*(batch.column(c).to_pylist() for c in ("node", "role", "going", "p")), strict=True):
                    at, picks, toss = -1, [], 0
                    while p > 0:
                        a, b = coins.python_coin(spec.seed, "skip", f"{node}:{role}", epoch, toss)
                        u, toss = (a * coins.FULL + b + 0.5) / coins.FULL**2, toss + 1
                        at += 1 + (math.floor(math.log(u) / math.log1p(-p)) if p < 1 else 0)
                        if at >= going:
                            break
                        picks.append(at)
                    for c, x in zip(got, (node, role, picks), strict=True):
                        got[c].append(x)
                yield pa.RecordBatch.from_arrays([pa.array(got["node"], pa.int64()), pa.array(got["role"], pa.string()), pa.array(got["picks"], pa.list_(pa.int64()))], names=list(got))

        drawn = rows.repartition("node").mapInArrow(skip, "node long, role string, picks array<long>")
        return save(drawn.withColumn("calls", F.size("picks") > 0), "gate")

    def visits_counted(self) -> DataFrame:
        """``(node, going)``: continuing and stuck visits, which are all that can switch. A stuck visit is the last of its walk."""
        c = self.counters()
        stuck = self.visits().where("ended = 'stuck'").groupBy("node").agg(F.count("*").alias("stuck"))
        return c.join(stuck, "node", "left").select("node", (F.col("continuing") + F.coalesce("stuck", F.lit(0))).alias("going"))

    def size(self) -> dict:
        """What the store takes: live and stored visits, layers, and bytes of the files."""
        from incwalk.store import _file_system

        fs, place = _file_system(self.spark, self.folder)
        return {"live_visits": self.visits().count(), "stored_visits": self._read("visits").count(), "layers": len(self.state["layers"]["visits"]), "bytes": fs.getContentSummary(place).getLength()}


def counters(visits: DataFrame, edges: DataFrame) -> DataFrame:
    """A recount of what ``WalkStore.counters`` keeps up."""
    return WalkStore._count(visits).join(G.degrees(edges), "node", "full").na.fill(0)


def gate(counter: DataFrame) -> DataFrame:
    """Chance that an arrival at a node has to call the walk store: by walks, and by continuing visits, which is exact for one arrival."""
    d = F.col("outdeg") + 1
    return counter.select("node", F.round(1 - F.pow(1 - 1 / d, F.col("w_segments")), 9).alias("p_segments"), F.round(1 - F.pow(1 - 1 / d, F.col("continuing")), 9).alias("p_visits"))


def whole_history(m: int, batches: int = 6) -> list[int]:
    """Cuts of all ``m`` arrivals from the empty graph on: each batch after the first is as large as all before it."""
    return [0, *sorted({-(-m >> i) for i in range(batches)})] if m else [0]


def in_batches(m: int, first: int, size: int) -> list[int]:
    """Cuts of the arrivals after ``first`` into batches of ``size``."""
    return [first, *range(first + size, m, size), m]


_REPLAYED = "epoch int, from_t int, to_t int, walks_rerouted long, steps_redone long, bound_steps double, visits_read long"


def replay(edges: DataFrame, spec: Spec, cuts: list[int], gate: str | None = None) -> DataFrame:
    """Builds on the first ``cuts[0]`` arrivals, then applies the others in batches that end at the further cuts; one ledger row a batch, with the bound of the theory.

    ``edges`` has each edge once. Where they may be broadcast and no gate is asked for, tasks take the walks through all
    batches by themselves, with the same coins and the same ledger; otherwise a store goes from batch to batch.
    """
    e = save(numbered(edges.select("src", "dst", "ord"), [F.asc("ord"), F.asc("src"), F.asc("dst")], "t"), "history")
    n, out = G.nodes(e).count(), None

    def bound(a, b):
        return round(n * spec.reps / spec.eps**2 * (theory.harmonic(b) - theory.harmonic(a)) * (16 if spec.alternating else 1), 3)

    if gate is None and spec.coin == "portable" and on_broadcast(e, spec, cuts[-1]):
        sums = history.ledgers(e, spec, cuts, cuts[-1]) if len(cuts) > 1 else {}
        rows = [(k, a, b, *sums.get(k, (0, 0, 0))) for k, (a, b) in enumerate(zip(cuts, cuts[1:], strict=False), 1)]
        return e.sparkSession.createDataFrame([(*x[:5], bound(*x[1:3]), x[5]) for x in rows], _REPLAYED)
    store = WalkStore.create(e.where(F.col("t") <= cuts[0]).select("src", "dst", "ord"), spec)
    for a, b in zip(cuts, cuts[1:], strict=False):
        batch = e.where((F.col("t") > a) & (F.col("t") <= b)).select(F.lit("+").alias("op"), "src", "dst", "ord")
        ledger = store.apply(batch, gate=gate)
        row = ledger.select("epoch", F.lit(a).alias("from_t"), F.lit(b).alias("to_t"), "walks_rerouted", "steps_redone", F.lit(bound(a, b)).alias("bound_steps"), "visits_read")
        out = row if out is None else out.unionByName(row)
    return out if out is not None else edges.sparkSession.createDataFrame([], _REPLAYED)


def update_sql(edges_sql: str, changes_sql: str, spec: Spec, epoch: int = 1, restart: bool = False) -> str:
    """CTEs up to ``w1``, the visits after one batch, by replay of the same coins (hub walks)."""
    from incwalk.plans.walks import walks_sql

    hu = coins.sql_digest(spec.seed, "update", "(src || ':' || rep)", str(epoch), "pos")
    hb = coins.sql_digest(spec.seed, "build", "(src || ':' || rep)", str(epoch), "pos")
    t = coins.threshold(spec.eps)
    again = "SELECT src, rep, 0::BIGINT AS pos, src AS node FROM c1" if restart else "SELECT c.src, c.rep, c.pos + 1 AS pos, a.dst AS node FROM c1 c JOIN a1 a ON a.src = c.node AND a.slot = c.slot"
    keep = "SELECT w.src, w.rep, pos, node, ended FROM w0 w ANTI JOIN c1 c ON c.src = w.src AND c.rep = w.rep" if restart else "SELECT w.src, w.rep, w.pos, w.node, w.ended FROM w0 w LEFT JOIN c1 c ON c.src = w.src AND c.rep = w.rep WHERE c.pos IS NULL OR w.pos < c.pos UNION ALL SELECT src, rep, pos, node, CASE WHEN d = 0 THEN 'stuck' END FROM c1"
    return f"""{walks_sql(edges_sql, spec)},
ch AS ({changes_sql}),
lc AS (SELECT src, dst, max(ord) AS ord, arg_max(op, (ord, op)) AS op FROM ch GROUP BY 1, 2),
gone AS (SELECT src, dst FROM lc SEMI JOIN e0 USING (src, dst) WHERE op = '-'),
added AS (SELECT src, dst, ord FROM lc ANTI JOIN e0 USING (src, dst) WHERE op = '+' AND src <> dst),
e1 AS (SELECT src, dst, ord, 0 AS fresh FROM e0 ANTI JOIN gone USING (src, dst) UNION ALL SELECT src, dst, ord, 1 FROM added),
a1 AS (SELECT src, row_number() OVER (PARTITION BY src ORDER BY fresh, ord, dst) - 1 AS slot, dst FROM e1),
g1 AS (SELECT src, row_number() OVER (PARTITION BY src ORDER BY ord, dst) - 1 AS slot, dst FROM e1),
dg AS (SELECT src, count(*) AS deg FROM g1 GROUP BY 1),
tn AS (SELECT src FROM gone UNION SELECT src FROM added),
d1 AS (SELECT tn.src, coalesce(sum(1 - fresh), 0)::BIGINT AS d_surv, count(e1.dst) AS d FROM tn LEFT JOIN e1 ON e1.src = tn.src GROUP BY 1),
x1 AS (SELECT v.*, d.d_surv, d.d, ({coins.sql_b("h")} * d.d) >> 32 AS slot, g.src IS NOT NULL AS lost
  FROM (SELECT *, lead(node) OVER (PARTITION BY src, rep ORDER BY pos) AS nxt, {hu} AS h FROM w0) v
  JOIN d1 d ON d.src = v.node LEFT JOIN gone g ON g.src = v.node AND g.dst = v.nxt WHERE v.ended IS NULL OR v.ended = 'stuck'),
c1 AS (SELECT * FROM (SELECT src, rep, pos, node, slot, d, row_number() OVER (PARTITION BY src, rep ORDER BY pos) AS k FROM x1 WHERE lost OR (slot >= d_surv AND d > 0)) WHERE k = 1),
nn AS (SELECT node FROM (SELECT src AS node FROM added UNION SELECT dst FROM added) ANTI JOIN n0 USING (node)),
r1 AS (
  SELECT * FROM ({again} UNION ALL SELECT node, rep, 0, node FROM nn, range({spec.reps}) t(rep))
  UNION ALL
  SELECT x.src, x.rep, x.pos + 1, a.dst FROM (SELECT *, {hb} AS h FROM r1) x JOIN dg d ON d.src = x.node JOIN g1 a ON a.src = x.node AND a.slot = ({coins.sql_b("x.h")} * d.deg) >> 32
  WHERE {coins.sql_a("x.h")} >= {t}),
w1 AS ({keep} UNION ALL SELECT x.src, x.rep, x.pos, x.node, CASE WHEN {coins.sql_a("h")} < {t} THEN 'reset' WHEN d.deg IS NULL THEN 'stuck' END FROM (SELECT *, {hb} AS h FROM r1) x LEFT JOIN dg d ON d.src = x.node)"""
