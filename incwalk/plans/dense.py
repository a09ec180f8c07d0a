"""Exact iterations over a graph of a checked size: a task a seed, against broadcast arrays.

A round of a seed is a weighted count over the edges. A score is a sum of positive parts, so rows are
those of the joins of ``exact``: nodes that a seed has reached, and nodes that it jumps to.

Where only the ranks of a few nodes are asked, seeds of one connected part advance together, as the columns of a
matrix over the rows of that part, and what a seed has reached stays in the task (``link_ranks``).
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from incwalk.plans import graph as G
from incwalk.plans.walks import LOCAL_EDGES, Adjacency, _words, dealt, held_rows
from incwalk.store import save

#: Edges that are broadcast, times the ways of the steps: 4 bytes each, and 24 bytes a node.
DENSE_EDGES = 100_000_000
#: Edges whose scores are gathered at a time, so that they stay in a core's cache.
GATHERED = 1 << 16
#: Rows in a batch of results.
BATCH = 100_000
_SCORE = pa.schema([("seed", pa.int64()), ("node", pa.int64()), ("score", pa.float64())])
_BOTH = pa.schema([("seed", pa.int64()), ("node", pa.int64()), ("hub", pa.float64()), ("auth", pa.float64())])


class Numbered(Adjacency):
    """Edges as rows of places, and the weights of a step either way by place. Steps forward alone need no rows by source."""

    def __init__(self, edges: DataFrame, both: bool = True):
        e = edges.select("src", "dst")
        super().__init__(e, both, ways=("auth", "hub") if both else ("auth",))
        self._weigh()

    @classmethod
    def over(cls, g: Adjacency) -> Numbered:
        """The same over rows that are held both ways."""
        own = cls.__new__(cls)
        own.nodes, own.ways = g.nodes, g.ways
        own._weigh()
        return own

    def _weigh(self) -> None:
        both = "hub" in self.ways
        into = np.diff(self.ways["auth"][0])
        out = np.diff(self.ways["hub"][0]) if both else np.bincount(self.ways["auth"][1], minlength=len(self.nodes))
        self.out_w, self.in_w, self.stuck = 1 / np.maximum(out, 1), 1 / np.maximum(into, 1), out == 0

    def forward(self, x: np.ndarray) -> np.ndarray:
        return self._sums("auth", x)

    def back(self, x: np.ndarray) -> np.ndarray:
        return self._sums("hub", x)

    def _sums(self, way: str, x: np.ndarray) -> np.ndarray:
        """Sum of ``x`` over the row of each place, some whole rows at a time; where few edges leave what isn't zero, over those alone."""
        starts, to = self.ways[way]
        if len(self.ways) == 2:
            first, far = self.ways["hub" if way == "auth" else "auth"]
            some = np.flatnonzero(x)
            size = first[some + 1] - first[some]
            if 8 * size.sum() < len(far):
                at = np.repeat(first[some] - np.cumsum(size) + size, size) + np.arange(size.sum())
                return np.bincount(far[at], np.repeat(x[some], size), len(self.nodes))
        full = np.flatnonzero(np.diff(starts))
        at, out = np.r_[starts[full], len(to)], np.zeros(len(self.nodes))
        cuts = np.unique(np.r_[np.searchsorted(at[:-1], np.arange(0, len(to), GATHERED)), len(full)])
        for a, b in zip(cuts, cuts[1:], strict=False):
            out[full[a:b]] = np.add.reduceat(x.take(to[at[a] : at[b]]), at[a:b] - at[a])
        return out

    def starts(self, nodes: list[int], weights: list[float]) -> tuple[np.ndarray, np.ndarray, dict[int, float]]:
        """Jumps by place and whether a place is jumped to; those to nodes without any edge beside them."""
        tele, named, others = np.zeros(len(self.nodes)), np.zeros(len(self.nodes), bool), {}
        for node, w in zip(nodes, weights, strict=True):
            i = int(np.searchsorted(self.nodes, node))
            if i < len(self.nodes) and self.nodes[i] == node:
                tele[i] += w
                named[i] = True
            else:
                others[node] = others.get(node, 0.0) + w
        return tele, named, others


def fits(edges: DataFrame, ways: int = 1) -> bool:
    return ways * edges.count() <= DENSE_EDGES


def _each(tele: DataFrame, run, schema: pa.Schema, spelled: str) -> DataFrame:
    """``run(nodes, weights)`` for the jumps of each seed gives columns of results."""

    def rows(batches):
        for batch in batches:
            for seed, nodes, weights in zip(*(batch.column(c).to_pylist() for c in ("seed", "nodes", "weights")), strict=True):
                got = run(nodes, weights)
                for at in range(0, len(got[0]), BATCH):
                    part = [np.asarray(c)[at : at + BATCH] for c in got]
                    yield pa.RecordBatch.from_arrays([pa.array(np.full(len(part[0]), seed, np.int64)), *(pa.array(c) for c in part)], schema=schema)

    jumps = tele.groupBy("seed").agg(F.collect_list(F.struct("node", "tele")).alias("j")).select("seed", F.col("j.node").alias("nodes"), F.col("j.tele").alias("weights"))
    return dealt(jumps, "seed").mapInArrow(rows, spelled)


def _best(scores: np.ndarray, best: int | None) -> np.ndarray:
    """Which rows to give: all, or those with the ``best`` largest scores and all that tie with the last of them."""
    if best is None or len(scores) <= best:
        return np.ones(len(scores), bool)
    return scores >= np.partition(scores, len(scores) - best)[len(scores) - best]


def uniform_power(edges: DataFrame, eps: float, rounds: int, dangling: str) -> DataFrame:
    """All nodes alike under seed -1: the rounds of one vector, which are sums over the edges, in a task."""
    spark = edges.sparkSession
    held = spark.sparkContext.broadcast(Numbered(edges, both=False))

    def run(batches):
        for batch in batches:
            g = held.value
            x = tele = np.full(len(g.nodes), 1 / max(1, len(g.nodes)))
            for _ in range(rounds if batch.num_rows else 0):
                lost = 0.0 if dangling == "leak" else (1 - eps) * x[g.stuck].sum()
                x = g.forward(x * g.out_w) * (1 - eps) + tele * (eps + lost)
            for at in range(0, len(x) if batch.num_rows else 0, BATCH):
                part = x[at : at + BATCH]
                yield pa.RecordBatch.from_arrays([pa.array(np.full(len(part), -1, np.int64)), pa.array(g.nodes[at : at + BATCH]), pa.array(part)], schema=_SCORE)

    return spark.range(1, numPartitions=1).mapInArrow(run, "seed long, node long, score double")


def power(edges: DataFrame, tele: DataFrame, eps: float, rounds: int, dangling: str, best: int | None = None) -> DataFrame:
    held = edges.sparkSession.sparkContext.broadcast(Numbered(edges, both=False))

    def run(nodes, weights):
        g = held.value
        tele, named, others = g.starts(nodes, weights)
        x, far = tele.copy(), dict(others)
        for _ in range(rounds):
            lost = 0.0 if dangling == "leak" else (1 - eps) * (x[g.stuck].sum() + sum(far.values()))
            x = g.forward(x * g.out_w) * (1 - eps) + tele * (eps + lost)
            far = {k: w * (eps + lost) for k, w in others.items()}
        keep = (x > 0) | named
        nodes, x = np.r_[g.nodes[keep], np.array(list(far), np.int64)], np.r_[x[keep], np.array(list(far.values()), float)]
        some = _best(x, best)
        return nodes[some], x[some]

    return _each(tele, run, _SCORE, "seed long, node long, score double")


def alternating(edges: DataFrame, tele: DataFrame, eps: float, rounds: int, divide: bool, best: int | None = None) -> DataFrame:
    held = held_rows(edges, True)

    def run(nodes, weights):
        g = Numbered.over(held.value)
        tele, named, others = g.starts(nodes, weights)
        out_w, in_w = (g.out_w, g.in_w) if divide else (np.float64(1), np.float64(1))
        h, far, scale = tele.copy(), dict(others), 1.0
        for _ in range(rounds):
            h = g.back(g.forward(h * out_w) * in_w) * (1 - eps) + tele * eps * scale
            far = {k: w * eps * scale for k, w in others.items()}
            if not divide:
                top = max(float(h.max(initial=0.0)), *far.values(), 0.0) if far else float(h.max(initial=0.0))
                h, far, scale = h / top, {k: w / top for k, w in far.items()}, scale / top
        a = g.forward(h * out_w)
        keep = (h > 0) | (a > 0) | named
        nodes, h, a = np.r_[g.nodes[keep], np.array(list(far), np.int64)], np.r_[h[keep], np.array(list(far.values()), float)], np.r_[a[keep], np.zeros(len(far))]
        some = _best(a, best)
        return nodes[some], h[some], a[some]

    return _each(tele, run, _BOTH, "seed long, node long, hub double, auth double")


_MEAN = pa.schema([("g", pa.string()), ("m", pa.int64()), ("arrivals", pa.int64()), ("mx", pa.float64())])


def arrival_means(edges: DataFrame, names: list[str], eps: float = 0.2, rounds: int = 10) -> DataFrame:
    """``(g, m, arrivals, mx)`` of the graphs ``names``: the i-th has the edges whose ``old`` has bit i, and the others arrive
    in it. Scores are sums over the edges in any order, so nothing is sorted: a task a graph, 9 bytes an edge broadcast."""
    spark, number = edges.sparkSession, pa.schema([("s", pa.int32()), ("d", pa.int32()), ("old", pa.int8())])
    nodes = np.sort(G.nodes(edges).toArrow().column("node").to_numpy())
    named = spark.sparkContext.broadcast(nodes)

    def places(batches):
        for batch in batches:
            s, d = (np.searchsorted(named.value, batch.column(c).to_numpy()).astype(np.int32) for c in ("src", "dst"))
            yield pa.RecordBatch.from_arrays([pa.array(s), pa.array(d), batch.column("old")], schema=number)

    t = edges.select("src", "dst", "old").mapInArrow(places, "s int, d int, old byte").toArrow()
    held = spark.sparkContext.broadcast((len(nodes), *(t.column(c).to_numpy() for c in ("s", "d", "old"))))

    def run(batches):
        for i, name in ((i, name) for batch in batches for i, name in zip(*(batch.column(c).to_pylist() for c in ("i", "g")), strict=True)):
            n, s, d, old = held.value
            own = (old >> i & 1).astype(bool)
            a, b = s[own], d[own]
            out = np.bincount(a, minlength=n)
            more, here = np.bincount(s, minlength=n) - out, out > 0
            inside = here.copy()
            inside[b] = True
            x = tele = inside / max(1, inside.sum())
            for _ in range(rounds):
                x = np.bincount(b, (x / np.maximum(out, 1) * (1 - eps)).take(a), n) + tele * eps
            arrivals = int(more[here].sum())
            if arrivals:
                mx = len(a) * float((more[here] * x[here] / out[here]).sum()) / arrivals
                yield pa.RecordBatch.from_arrays([pa.array([name]), pa.array([len(a)]), pa.array([arrivals]), pa.array([mx])], schema=_MEAN)

    return dealt(spark.createDataFrame(list(enumerate(names)), "i int, g string"), "i").mapInArrow(run, "g string, m long, arrivals long, mx double")


#: Seeds that advance together, at most; bytes of one matrix of their scores; rows whose scores are added at a time.
TOGETHER, MATRIX, ROWS = 16, 50_000_000, 2048
#: Neighbours from which on a row is summed by itself.
LONG_ROW = 512


def connected(g: Numbered) -> np.ndarray:
    """The smallest place of the connected part that each place is in."""
    starts, near = g.ways["auth"]
    far = np.repeat(np.arange(len(g.nodes), dtype=np.int32), np.diff(starts))
    part = np.arange(len(g.nodes), dtype=np.int32)
    while True:
        a, b = part[near], part[far]
        now, low = part.copy(), np.minimum(a, b)
        np.minimum.at(now, a, low)
        np.minimum.at(now, b, low)
        while not np.array_equal(now, further := now[now]):
            now = further
        if np.array_equal(now, part):
            return part
        part = now


class Part:
    """A connected part of a graph: its places, renumbered, and sums over rows for several columns at once.

    Sums go into arrays that are used again and again, weights by row are applied while a sum is in the cache, and
    what starts at few places is followed from those until it has spread.
    """

    def __init__(self, g: Numbered, places: np.ndarray):
        self.nodes, self.out_w, self.in_w = g.nodes[places], g.out_w[places, None], g.in_w[places, None]
        own = np.zeros(len(g.nodes), np.int32)
        own[places] = np.arange(len(places))
        self.edges = {way: self._own(*g.ways[way], places, own) for way in ("auth", "hub")}
        self.rows = {way: self._cut(*x) for way, x in self.edges.items()}
        self.out = np.diff(self.edges["hub"][0]).astype(float)
        self.together = max(1, min(TOGETHER, MATRIX // (8 * max(1, len(places)))))
        self.held: dict = {}

    @staticmethod
    def _own(starts: np.ndarray, to: np.ndarray, places: np.ndarray, own: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        size = starts[places + 1] - starts[places]
        first = np.r_[0, np.cumsum(size)]
        return first, own[to[np.repeat(starts[places] - first[:-1], size) + np.arange(first[-1])]]

    @staticmethod
    def _cut(first: np.ndarray, near: np.ndarray) -> tuple[list, np.ndarray, list]:
        size, at = np.diff(first), np.intp if len(near) <= LOCAL_EDGES else np.int32
        order = np.argsort(-size, kind="stable")[: np.count_nonzero(size)]
        few = int(np.searchsorted(-size[order], -LONG_ROW))
        short, steps = order[few:], []
        for a in range(0, len(short), ROWS):
            some = short[a : a + ROWS]
            down = -size[some]  # the j-th neighbours of all rows that have so many
            steps.append([near[first[some[: np.searchsorted(down, -j)]] + j].astype(at) for j in range(-down[0])])
        return [(i, near[first[i] : first[i + 1]]) for i in order[:few].tolist()], short, steps

    def _array(self, what: str, shape: tuple[int, int]) -> np.ndarray:
        if what not in self.held or self.held[what].shape != shape:
            self.held[what] = np.zeros(shape)
        return self.held[what]

    def _sums(self, way: str, x: np.ndarray, spread: np.ndarray | None, weight=None, factor=None) -> tuple[np.ndarray, np.ndarray | None]:
        """Sums of ``x`` over rows, times ``weight`` by row and ``factor`` by column, and the rows that have any, where they are few. ``spread``: rows of ``x`` that aren't zero, where those are few."""
        out = self._array(way, x.shape)
        if spread is not None:
            first, far = self.edges["hub" if way == "auth" else "auth"]
            size = first[spread + 1] - first[spread]
            if 8 * size.sum() < len(far):
                out[:] = 0
                to = far[np.repeat(first[spread] - np.cumsum(size) + size, size) + np.arange(size.sum())]
                order = np.argsort(to, kind="stable")
                to, at = np.unique(to[order], return_index=True)
                if len(to):
                    got = np.add.reduceat(x[np.repeat(spread, size)[order]], at, axis=0)
                    got = got if weight is None else got * weight[to]
                    out[to] = got if factor is None else got * factor
                return out, to
        long, short, steps = self.rows[way]
        held, total = self._array("held", (ROWS, x.shape[1])), self._array("total", (ROWS, x.shape[1]))
        if spread is not None or len(long) + len(short) < len(out):
            out[:] = 0
        for i, near in long:
            out[i] = sum(x.take(near[a : a + ROWS], axis=0).sum(axis=0) for a in range(0, len(near), ROWS))
            if weight is not None:
                out[i] *= weight[i]
            if factor is not None:
                out[i] *= factor
        for a, nears in zip(range(0, len(short), ROWS), steps, strict=True):
            own = short[a : a + ROWS]
            t = total[: len(own)]
            t[:] = 0
            for near in nears:
                k = len(near)
                x.take(near, axis=0, out=held[:k], mode="clip")
                np.add(t[:k], held[:k], out=t[:k])
            if weight is not None:
                t *= weight[own]
            if factor is not None:
                t *= factor
            out[own] = t
        return out, None

    def forward(self, x, spread=None, weight=None, factor=None):
        return self._sums("auth", x, spread, weight, factor)

    def back(self, x, spread=None, weight=None, factor=None):
        return self._sums("hub", x, spread, weight, factor)

    def _start(self, at: np.ndarray) -> tuple[np.ndarray, tuple]:
        x = np.zeros((len(self.nodes), len(at)))
        one = at, np.arange(len(at))
        x[one] = 1.0
        return x, one

    @staticmethod
    def _with(spread: np.ndarray | None, at: np.ndarray) -> np.ndarray | None:
        return spread if spread is None else np.union1d(spread, at)

    def power(self, at: np.ndarray, eps: float, rounds: int) -> np.ndarray:
        """Scores of the seeds at ``at``, a column each. What is lost at nodes without an edge goes back to the seed, so that scores sum to one."""
        x, one = self._start(at)
        x, spread = x * (self.out_w if rounds else 1), np.unique(at)  # by out-edge, but for the last, so that equal scores stay equal
        for left in range(rounds - 1, -1, -1):
            moved, by = (1 - eps) * (self.out @ x), self.out_w if left else np.ones_like(self.out_w)
            x, spread = self.forward(x.copy() if x is self.held.get("auth") else x, spread, by * (1 - eps))
            x[one] += (1 - moved) * by[at, 0]
            spread = self._with(spread, at)
        return x

    def authorities(self, at: np.ndarray, eps: float, rounds: int, divide: bool) -> np.ndarray:
        """Authority scores; without ``divide`` up to a factor by seed."""
        h, one = self._start(at)
        spread, top, scale = np.unique(at), None, np.ones(len(at))
        by_out, by_in = (self.out_w * (1 - eps), self.in_w) if divide else (np.full_like(self.out_w, 1 - eps), None)
        if divide:
            h *= self.out_w
        for _ in range(rounds):
            a, spread = self.forward(h, spread, by_in, top)
            h, spread = self.back(a, spread, by_out)
            h[one] += eps * self.out_w[at, 0] if divide else eps * scale
            spread = self._with(spread, at)
            if not divide:
                top = 1 / h.max(axis=0)
                scale = scale * top
        return self.forward(h, spread)[0]

    def cosine(self, at: np.ndarray) -> np.ndarray:
        """Authority scores out of the cosines of neighbour sets, up to a factor by seed."""
        a, spread = self.forward(self._start(at)[0], np.unique(at))
        h, spread = self.back(a, spread, 1 / np.sqrt(np.maximum(self.out, 1))[:, None])
        return self.forward(h, spread)[0]


_RANK = pa.schema([("method", pa.string()), ("seed", pa.int64()), ("node", pa.int64()), ("rank", pa.int64())])
METHODS = ("pagerank", "alternating", "hits", "cosine", "popularity")


def link_ranks(edges: DataFrame, users: DataFrame, eps: float, rounds: int, most: int, least: int) -> DataFrame:
    """``(method, seed, node, rank)`` of the nodes ``wanted`` by each of the ``users`` (seed, wanted) that are among its
    ``most`` best of a method: all nodes but the seed and its neighbours, with a positive score, ties by node. Popular is
    what has ``least`` edges in."""
    sc, g = edges.sparkSession.sparkContext, Numbered(edges)
    into, popular = np.diff(g.ways["auth"][0]), np.zeros(len(g.nodes), np.int64)
    some = np.flatnonzero(into >= least)
    popular[some[np.argsort(-into[some], kind="stable")]] = np.arange(1, len(some) + 1)
    held = sc.broadcast((g, connected(g), popular))

    def placed(batches):
        g, parts, _ = held.value
        for batch in batches:
            at = g.find(batch.column("seed").to_numpy())
            yield pa.RecordBatch.from_arrays([batch.column("seed"), batch.column("wanted"), pa.array(np.r_[parts, -1][at], pa.int64())], names=["seed", "wanted", "part"])

    def ranked(nodes, scores, hidden, wanted):
        scores[hidden] = 0.0
        some = np.flatnonzero((scores > 0) & _best(scores, most))
        some = some[np.lexsort((nodes[some], -scores[some]))][:most]
        rank = np.zeros(len(nodes), np.int64)
        rank[some] = np.arange(1, len(some) + 1)
        return rank[wanted]

    def block(g, popular, part, seeds, wanted):
        at = np.searchsorted(part.nodes, seeds)
        found = (
            part.power(at, eps, rounds).T.copy(),
            part.authorities(at, eps, rounds, True).T.copy(),
            part.authorities(at, eps, rounds, False).T.copy(),
            part.cosine(at).T.copy(),
        )
        starts, to = g.ways["hub"]
        got = []
        for j, place in enumerate(g.find(seeds).tolist()):
            hidden = np.r_[at[j], np.searchsorted(part.nodes, g.nodes[to[starts[place] : starts[place + 1]]])]
            w = np.array(wanted[j], np.int64)
            i = np.minimum(np.searchsorted(part.nodes, w), len(part.nodes) - 1)
            i = i[part.nodes[i] == w]  # the others are out of reach
            for code, scores in enumerate(found):
                rank = ranked(part.nodes, scores[j], hidden, i)
                listed = np.flatnonzero(rank)
                got.append((np.full(len(listed), code), np.full(len(listed), seeds[j]), part.nodes[i[listed]], rank[listed]))
            # popular in the whole graph: the place in the list, less what is hidden before it
            w, before = np.r_[popular, 0][g.find(w)], np.sort(popular[g.find(part.nodes[np.unique(hidden)])])
            rank = w - np.searchsorted(before[before > 0], w)
            listed = np.flatnonzero((w > 0) & (rank <= most) & ~np.isin(w, before))
            got.append((np.full(len(listed), len(found)), np.full(len(listed), seeds[j]), np.array(wanted[j], np.int64)[listed], rank[listed]))
        code, *columns = (np.concatenate(c) for c in zip(*got, strict=True))
        return pa.RecordBatch.from_arrays([_words(list(METHODS), code), *(pa.array(c, pa.int64()) for c in columns)], schema=_RANK)

    def run(batches):
        g, parts, popular = held.value
        part = at = None
        for batch in batches:
            seeds, wanted, own = batch.column("seed").to_numpy(), batch.column("wanted").to_pylist(), batch.column("part").to_numpy()
            first = int(np.searchsorted(own, 0))  # a seed in no edge reaches nothing
            while first < len(seeds):
                if at != own[first]:
                    at, part = own[first], Part(g, np.flatnonzero(parts == own[first]))
                last = min(first + part.together, int(np.searchsorted(own, at, side="right")))
                yield block(g, popular, part, seeds[first:last], wanted[first:last])
                first = last

    spark = edges.sparkSession
    tasks = max(int(spark.conf.get("spark.sql.shuffle.partitions")), 3 * sc.defaultParallelism)
    rows = save(users.mapInArrow(placed, "seed long, wanted array<long>, part long"), "placed").repartitionByRange(tasks, "part", "seed").sortWithinPartitions("part", "seed")
    return rows.mapInArrow(run, "method string, seed long, node long, rank long")
