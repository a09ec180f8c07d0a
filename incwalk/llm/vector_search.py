"""Approximate nearest neighbours: a forest of random-projection trees, one priority queue a query, exact reranking.

Each tree halves a bounded sample by the hyperplane between two of its vectors, at the median, and
every row is routed to its leaf in each tree. A query's queue holds nodes of all trees, keyed by
the largest mean inner product among the leaves below; it gives up leaves best first, until they
hold ``share`` of the rows, or ``candidates`` of them, and ``LEAST`` times the vectors asked for.

A row travels once, to the block of its home leaf (its leaf in the first tree), with its leaf
numbers in the others; a query travels to the blocks that hold rows of its leaves, as a table of
which leaves meet which homes tells exactly. So a row is scored once at most for a query, however
many trees bring it up. Inner products become angles for the splits by one extra coordinate that
makes all norms equal. Vectors are scaled by the largest norm before single precision, which only
picks what is scored in double. Equal vectors are searched once and named by their smallest ids,
which are all that can rank.
"""

from __future__ import annotations

import heapq

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from incwalk.llm.common import save

#: Vectors that trees are fitted on, at most.
SAMPLE = 20_000
#: Leaves of a tree: one for each 4,096 rows, within these bounds. The table of leaves met by homes has at most ``trees`` times the square of that.
LEAVES = 256, 512
#: Different vectors met by each query, for each one of its list and itself; smaller tables are searched whole.
LEAST = 4
#: Rows that one task scores at a time, at most.
BLOCK = 8192


class Tree:
    """Arrays over nodes, parents before children; a leaf has a negative ``left`` that gives its number."""

    def __init__(self, x: np.ndarray, leaf: int, rng: np.random.Generator):
        self.normal, self.offset, self.left, self.right, self.size = [], [], [], [], []
        self._split(x, np.arange(len(x)), leaf, rng)
        self.normal = np.array(self.normal, np.float32)
        self.offset, self.left, self.right = np.array(self.offset, np.float32), np.array(self.left), np.array(self.right)

    def _split(self, x, own, leaf, rng) -> int:
        me = len(self.left)
        for a, v in ((self.normal, np.zeros(x.shape[1], np.float32)), (self.offset, 0.0), (self.left, 0), (self.right, 0)):
            a.append(v)
        if len(own) > leaf:
            for _ in range(5):
                a, b = rng.choice(own, 2, replace=False)
                n = x[a] - x[b]
                if (size := np.linalg.norm(n)) > 1e-9:
                    n = n / size
                    m = x[own] @ n
                    t = float(np.median(m))
                    if 0 < (m <= t).sum() < len(own):
                        self.normal[me], self.offset[me] = n, t
                        self.left[me] = self._split(x, own[m <= t], leaf, rng)
                        self.right[me] = self._split(x, own[m > t], leaf, rng)
                        return me
        self.left[me] = -1 - len(self.size)
        self.size.append(len(own))
        return me

    def hold(self, x: np.ndarray) -> None:
        """Notes which of the sampled rows each leaf holds, as they are routed, and their mean."""
        leaf = self.route(x)
        order = np.argsort(leaf, kind="stable")
        self.rows = np.split(order.astype(np.int32), np.searchsorted(leaf[order], np.arange(1, len(self.size))))
        self.mean = np.stack([x[r, :-1].mean(0) if len(r) else np.zeros(x.shape[1] - 1, np.float32) for r in self.rows])

    def route(self, x: np.ndarray) -> np.ndarray:
        """Leaf numbers of rows."""
        at = np.zeros(len(x), np.int64)
        while (inner := np.flatnonzero(self.left[at] >= 0)).size:
            n = at[inner]
            below = np.einsum("ij,ij->i", x[inner], self.normal[n]) <= self.offset[n]
            at[inner] = np.where(below, self.left[n], self.right[n])
        return -1 - self.left[at]

    def keys(self, q: np.ndarray) -> np.ndarray:
        """For each query and node: the largest mean inner product among the leaves below."""
        leaf = q @ self.mean.T
        out = np.empty((len(q), len(self.left)), np.float32)
        for n in range(len(self.left) - 1, -1, -1):
            out[:, n] = leaf[:, -1 - self.left[n]] if self.left[n] < 0 else np.maximum(out[:, self.left[n]], out[:, self.right[n]])
        return out


def probes(trees: list[Tree], keys: list[np.ndarray], share: float, least: int, candidates: int | None = None, rows: int = 0) -> list[tuple[int, int]]:
    """``(tree, leaf)`` in the order of the shared queue, until the leaves hold ``share`` of the sample (or what stands for ``candidates`` of ``rows`` rows) and at least ``least`` of it, or are all taken. Rows held by several leaves count once. ``keys``: a row of each tree's."""
    heap = [(-float(key[0]), k, 0) for k, key in enumerate(keys)]
    heapq.heapify(heap)
    total = sum(len(r) for r in trees[0].rows)
    want = share * total if candidates is None else min(share, candidates / max(1, rows)) * total
    out, seen, held = [], np.zeros(total, bool), 0
    while heap and (held < want or held < least):
        _, k, n = heapq.heappop(heap)
        t = trees[k]
        if t.left[n] >= 0:
            for child in (int(t.left[n]), int(t.right[n])):
                heapq.heappush(heap, (-float(keys[k][child]), k, child))
            continue
        leaf = -1 - int(t.left[n])
        out.append((k, leaf))
        own = t.rows[leaf]
        held += int((~seen[own]).sum())
        seen[own] = True
    return out


def _matrix(column) -> np.ndarray:
    column = column.combine_chunks() if isinstance(column, pa.ChunkedArray) else column
    n = len(column)
    return column.flatten().to_numpy(zero_copy_only=False).reshape(n, -1) if n else np.zeros((0, 0))


def _lists(rows: list[np.ndarray], dtype) -> pa.ListArray:
    return pa.ListArray.from_arrays(pa.array(np.r_[0, np.cumsum([len(r) for r in rows])], pa.int32()), pa.array(np.concatenate(rows) if rows else [], dtype))


def _widened(x: np.ndarray, widest: float) -> np.ndarray:
    """Scaled to norms of one at most, with the coordinate that makes them one."""
    x = x / widest
    return np.c_[x, np.sqrt(np.maximum(0, 1 - (x**2).sum(1)))].astype(np.float32)


_ROUTED = pa.schema([("cls", pa.int64()), ("is_query", pa.bool_()), ("home", pa.int32()), ("leaf", pa.list_(pa.int32())), ("v", pa.list_(pa.float64()))])


def _route(forest, widest: float):
    """Each row's leaf in every tree, as numbers over all trees."""

    def run(batches):
        first = np.r_[0, np.cumsum([len(t.rows) for t in forest.value])]
        for batch in batches:
            for s in range(0, batch.num_rows, 4000):
                b = batch.slice(s, 4000)
                wide = _widened(_matrix(b.column("v")), widest)
                leaf = np.stack([t.route(wide) + first[k] for k, t in enumerate(forest.value)], 1)
                yield pa.RecordBatch.from_arrays([b.column("cls"), b.column("is_query"), pa.array(leaf[:, 0], pa.int32()), _lists(list(leaf.astype(np.int32)), pa.int32()), b.column("v")], schema=_ROUTED)

    return run


_DEALT = pa.schema([("block", pa.int32()), ("query", pa.bool_()), ("cls", pa.int64()), ("leaf", pa.list_(pa.int32())), ("v", pa.list_(pa.float64()))])


def _deal(forest, blocks, share: float, least: int, candidates: int | None, rows: int):
    """Rows to their blocks; queries, with the numbers of their leaves, to the blocks that hold rows of those."""

    def run(batches):
        trees, (start, many, meets) = forest.value, blocks.value
        first = np.r_[0, np.cumsum([len(t.rows) for t in trees])]
        for batch in batches:
            for s in range(0, batch.num_rows, 1000):
                b = batch.slice(s, 1000)
                x, cls, home = _matrix(b.column("v")), b.column("cls").to_numpy(), b.column("home").to_numpy()
                if not len(x):
                    continue
                salt = (cls.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15) >> np.uint64(40)).astype(np.int64)
                yield pa.RecordBatch.from_arrays([pa.array(start[home] + salt % many[home], pa.int32()), pa.array(np.zeros(len(x), bool)), b.column("cls"), b.column("leaf"), b.column("v")], schema=_DEALT)
                asks = np.flatnonzero(b.column("is_query").to_numpy(zero_copy_only=False))
                if not len(asks):
                    continue
                q = x[asks] / np.maximum(np.abs(x[asks]).max(1, keepdims=True), 1e-300)
                keys = [t.keys((q / np.linalg.norm(q, axis=1, keepdims=True)).astype(np.float32)) for t in trees]
                block, row, leaf = [], [], []
                for i, r in enumerate(asks):
                    found = np.array([first[k] + n for k, n in probes(trees, [key[i] for key in keys], share, least, candidates, rows)], np.int32)
                    for at in np.flatnonzero(meets[:, found].any(1)):
                        block.append(at)
                        row.append(r)
                        leaf.append(found)
                    if len(row) >= 2000 or r == asks[-1]:
                        v = pa.ListArray.from_arrays(pa.array(np.arange(len(row) + 1) * x.shape[1], pa.int32()), pa.array(x[row].ravel(), pa.float64()))
                        yield pa.RecordBatch.from_arrays([pa.array(block, pa.int32()), pa.array(np.ones(len(row), bool)), pa.array(cls[row]), _lists(leaf, pa.int32()), v], schema=_DEALT)
                        block, row, leaf = [], [], []

    return run


_FOUND = pa.schema([("qcls", pa.int64()), ("cls", pa.int64()), ("score", pa.float64()), ("scored", pa.int64())])


def _score(k: int, codes: int, widest: float):
    """Batches come block by block, its rows before its queries. ``scored`` counts the rows compared, on the first row of a query and block."""

    def best_of(qid, q, probed, ids, x, near, leaf):
        asked = np.zeros(codes, bool)
        asked[probed] = True
        hit = np.flatnonzero(asked[leaf].any(1))
        if not len(hit):
            return None
        pick = hit
        if len(hit) > 4 * k:
            own = near[hit] @ (q / max(float(np.abs(q).max()), 1e-300)).astype(np.float32)
            low = np.partition(own, len(own) - k)[len(own) - k]
            pick = hit[own >= low - 1e-4 * max(1e-30, float(np.abs(own).max()))]
        exact = x[pick] @ q
        best = np.lexsort((ids[pick], -exact))[:k]
        return np.full(len(best), qid), ids[pick][best], exact[best], np.r_[len(hit), np.zeros(len(best) - 1, np.int64)]

    def run(batches):
        now, held = None, []
        ids = x = near = leaf = None
        for batch in batches:
            if not batch.num_rows:
                continue
            block, query = batch.column("block").to_numpy(), batch.column("query").to_numpy(zero_copy_only=False)
            cuts = [0, *(np.flatnonzero((block[1:] != block[:-1]) | (query[1:] != query[:-1])) + 1).tolist(), len(block)]
            for a, b in zip(cuts, cuts[1:], strict=False):
                if block[a] != now:
                    now, held, ids = block[a], [], None
                part = batch.slice(a, b - a)
                if not query[a]:
                    held.append((part.column("cls").to_numpy(), _matrix(part.column("v")), _matrix(part.column("leaf"))))
                    ids = None
                    continue
                if not held:
                    continue
                if ids is None:
                    ids, x, leaf = (np.concatenate([h[i] for h in held]) for i in range(3))
                    held, near = [(ids, x, leaf)], (x / widest).astype(np.float32)
                asked = part.column("leaf")
                out = [best_of(qid, q, asked[i].values.to_numpy(), ids, x, near, leaf) for i, (qid, q) in enumerate(zip(part.column("cls").to_numpy(), _matrix(part.column("v")), strict=True))]
                out = [o for o in out if o is not None]
                if out:
                    yield pa.RecordBatch.from_arrays([pa.array(np.concatenate([o[i] for o in out])) for i in range(4)], schema=_FOUND)

    return run


def _blocks(homes: list, codes: int, rows: int, parts: int):
    """``(start, many, meets)``: each home's first block and number of blocks, and which leaves the rows of a block are in. Neighbouring homes share a block up to its size, larger ones are split."""
    size = max(256, min(BLOCK, -(-rows // (4 * parts))))
    top = max(h["home"] for h in homes) + 1
    start, many, meets, held = np.zeros(top, np.int64), np.ones(top, np.int64), [], 0
    for h in sorted(homes, key=lambda h: h["home"]):
        own = np.zeros(codes, bool)
        own[h["leaves"]] = True
        if meets and held + h["n"] <= size:
            start[h["home"]] = len(meets) - 1
            meets[-1] |= own
            held += h["n"]
        else:
            start[h["home"]], many[h["home"]], held = len(meets), -(-h["n"] // BLOCK), h["n"]
            meets += [own] + [own.copy() for _ in range(many[h["home"]] - 1)]
            held = size if many[h["home"]] > 1 else held
    return start, many, np.stack(meets)


def search(vectors: DataFrame, k: int = 20, query_every: int = 20, trees: int = 8, share: float = 0.45, candidates: int | None = None, seed: int = 11, id_col: str = "vec_id", vector_col: str = "embedding") -> tuple[DataFrame, DataFrame]:
    """``(nearest, effort)``: the lists of ``nearest``, and ``(rows, queries, scored)``, distinct vectors, distinct queries and comparisons made."""
    spark = vectors.sparkSession
    empty = spark.createDataFrame([], "query_id long, rank int, vec_id long, score double"), spark.createDataFrame([(0, 0, 0)], "rows long, queries long, scored long")
    v = F.transform(F.col(vector_col), lambda c: c.cast("double"))
    good = F.col("v").isNotNull() & F.forall("v", lambda c: c.isNotNull() & ~F.isnan(c) & (F.abs(c) < float("inf"))) & F.exists("v", lambda c: c != 0)
    rows = vectors.where(F.col(id_col).isNotNull() & F.col(vector_col).isNotNull()).select(F.col(id_col).cast("long").alias("vec_id"), v.alias("v")).where(F.coalesce(good, F.lit(False)))
    peak = F.array_max(F.transform("v", lambda c: F.abs(c)))
    square = F.aggregate("v", F.lit(0.0), lambda a, c: a + (c / F.col("peak")) * (c / F.col("peak")))
    shape = rows.withColumn("peak", peak).groupBy(F.size("v").alias("d")).agg(F.count("*").alias("n"), F.max(F.col("peak") * F.sqrt(square)).alias("norm"), F.max("peak").alias("peak")).orderBy(F.desc("n"), "d").first()
    if shape is None:
        return empty
    rows = rows.where(F.size("v") == shape["d"])
    classes = save(rows.groupBy("v").agg(F.min("vec_id").alias("cls"), F.max(F.col("vec_id") % query_every == 0).alias("is_query")), "classes")
    member = rows.join(classes.select("v", "cls"), "v").select("vec_id", "cls").distinct()
    first = member.withColumn("rn", F.row_number().over(Window.partitionBy("cls").orderBy("vec_id"))).where(F.col("rn") <= k + 1).select("cls", "vec_id")
    asks = rows.where(F.col("vec_id") % query_every == 0).join(classes.select("v", "cls"), "v").select(F.col("vec_id").alias("query_id"), F.col("cls").alias("qcls")).distinct()

    widest = min(float(shape["norm"]), 1.7e308)
    wide = _widened(_matrix(classes.orderBy(F.xxhash64("cls"), "cls").limit(SAMPLE).select("v").toArrow().column("v")), widest)
    rng = np.random.default_rng(seed)
    leaves = min(LEAVES[1], max(LEAVES[0], shape["n"] // 4096))
    grown = [Tree(wide, max(4, -(-len(wide) // leaves)), rng) for _ in range(trees)]
    for t in grown:
        t.hold(wide)
    codes = sum(len(t.rows) for t in grown)
    forest = spark.sparkContext.broadcast(grown)
    routed = save(classes.repartition("cls").select("cls", "is_query", "v").mapInArrow(_route(forest, widest), "cls long, is_query boolean, home int, leaf array<int>, v array<double>"), "routed")
    # a row for each home, each with a number for each leaf at most: both bounded by LEAVES
    homes = routed.select("home", "cls", F.explode("leaf").alias("leaf")).groupBy("home").agg(F.count("*").alias("n"), F.collect_set("leaf").alias("leaves")).select("home", F.floor(F.col("n") / trees).cast("int").alias("n"), "leaves").collect()
    parts = int(spark.conf.get("spark.sql.shuffle.partitions"))
    blocks = spark.sparkContext.broadcast(_blocks(homes, codes, sum(h["n"] for h in homes), parts))
    dealt = routed.mapInArrow(_deal(forest, blocks, share, LEAST * (k + 1), candidates, shape["n"]), "block int, query boolean, cls long, leaf array<int>, v array<double>")
    found = dealt.repartition("block").sortWithinPartitions("block", "query").mapInArrow(_score(k + 1, codes, widest), "qcls long, cls long, score double, scored long")
    found = save(found, "found")
    effort = routed.agg(F.count("*").alias("rows"), F.count_if("is_query").alias("queries")).crossJoin(found.agg(F.coalesce(F.sum("scored"), F.lit(0)).alias("scored")))
    by_class = Window.partitionBy("qcls").orderBy(F.desc("score"), "cls")
    found = found.withColumn("rn", F.row_number().over(by_class)).where(F.col("rn") <= k + 1).select("qcls", "cls", "score").join(first, "cls")
    by_query = Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id")
    ranked = found.join(asks, "qcls").where(F.col("vec_id") != F.col("query_id")).withColumn("rank", F.row_number().over(by_query))
    return ranked.where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score"), effort


def nearest(vectors: DataFrame, k: int = 20, query_every: int = 20, trees: int = 8, share: float = 0.45, candidates: int | None = None, seed: int = 11, id_col: str = "vec_id", vector_col: str = "embedding") -> DataFrame:
    """``query_id``, ``rank`` from 1, ``vec_id`` and ``score`` (inner product in double precision) of each query's nearest.

    Queries are the rows whose id ``query_every`` divides; candidates are all rows but the query's
    own, ties go to smaller ids. Vectors that are null, zero, or hold null or non-finite components
    take no part, nor do null ids or vectors of another length than most. ``share`` of the rows is
    searched for each query, or ``candidates`` of them if that is fewer: recall on vectors without
    structure asks for a share, on clustered ones for a number. With fewer rows than ``k`` all
    candidates come. Repeated rows (of one id and vector) count once; an id with several vectors is a
    candidate with each. Other columns are not read. An empty table gives an empty result.
    """
    return search(vectors, k, query_every, trees, share, candidates, seed, id_col, vector_col)[0]


def brute_force(vectors: np.ndarray, ids: np.ndarray, k: int, query_every: int) -> dict[int, list[int]]:
    """Exact lists, for measuring recall on small inputs."""
    out = {}
    for q in np.flatnonzero(ids % query_every == 0):
        s = vectors @ vectors[q]
        order = np.lexsort((ids, -s))
        out[int(ids[q])] = ids[order[ids[order] != ids[q]][:k]].tolist()
    return out
