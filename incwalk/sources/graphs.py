"""Registry of edge lists ``(src, dst, ord, mult)``: first arrival of each edge, and how often it came.

``ord`` orders arrivals: seconds of a date, or a position. Self-loops are dropped. Text nodes are
the first 15 hexadecimal digits of their MD5, so that no global numbering is needed.
"""

from __future__ import annotations

import hashlib
import re
from collections.abc import Callable

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from incwalk.functions.coins import FULL, coin, slot, sql_a, sql_b, sql_digest, threshold
from incwalk.plans.ranking import numbered
from incwalk.store import _shuffles_end, save, table

PART, SUPPLIER = 10_000_000, 20_000_000
DAY = 86_400


def text_id(c: Column) -> Column:
    return F.conv(F.substring(F.md5(c), 1, 15), 16, 10).cast("long")


def micros(c: str) -> Column:
    """Microseconds since 1970 as the clock reads, whatever the session's zone."""
    whole = F.unix_date(F.to_date(c)) * DAY + F.hour(c) * 3600 + F.minute(c) * 60
    return (whole.cast("long") * 1_000_000 + (F.expr(f"extract(SECOND FROM {c})") * 1_000_000).cast("long")).cast("long")


def dedup(raw: DataFrame) -> DataFrame:
    """First arrival of each edge; partial minima and counts go ahead of the shuffle."""
    good = F.col("src").isNotNull() & F.col("dst").isNotNull() & (F.col("src") != F.col("dst"))
    return raw.where(good).groupBy("src", "dst").agg(F.min("ord").alias("ord"), F.count("*").alias("mult"))


def lag_over_time(df: DataFrame, keys: list[str], value: str, order: list[str], day: Column) -> DataFrame:
    """Adds ``prev``, the value of the row before in ``order`` within ``keys``, without one task per key.

    Windows run inside periods (``day``: a day, a month); a period's first row takes the last value
    of the last period before it that has rows, from a table with a row for each key and period.
    """
    rows = df.withColumn("__day", day)
    inside = Window.partitionBy(*keys, "__day").orderBy(*order)
    rows = rows.withColumn("__lag", F.lag(value).over(inside)).withColumn("__first", F.row_number().over(inside) == 1)
    last = rows.groupBy(*keys, "__day").agg(F.max(F.struct(*order, F.col(value).alias("__v")))["__v"].alias("__v"))
    days = Window.partitionBy(*keys).orderBy("__day")
    carried = last.withColumn("__carry", F.lag("__v").over(days)).drop("__v")
    return rows.join(carried, [*keys, "__day"], "left").withColumn("prev", F.when(F.col("__first"), F.col("__carry")).otherwise(F.col("__lag"))).drop("__day", "__lag", "__first", "__carry")


def _purchases(spark, sf_dir) -> DataFrame:
    o = table(spark, sf_dir, "orders").select("o_orderkey", "o_custkey", "o_orderdate")
    li = table(spark, sf_dir, "lineitem").select("l_orderkey", "l_partkey", "l_suppkey", "l_linenumber")
    return li.join(o, F.col("l_orderkey") == F.col("o_orderkey")).withColumn("ord", F.floor(micros("o_orderdate") / 1_000_000))


#: Rows of a key that a task may sort.
SORTED = 1_000_000


def cobuy(spark, sf_dir):
    """A part's buyers in order. One window by part where no part is hot."""
    order = ["o_orderdate", "o_orderkey", "l_linenumber"]
    with _shuffles_end(spark):
        hot = table(spark, sf_dir, "lineitem").groupBy("l_partkey").count().where(F.col("count") > SORTED).count()
    if hot:
        p = lag_over_time(_purchases(spark, sf_dir), ["l_partkey"], "o_custkey", order, F.trunc("o_orderdate", "month"))
    else:
        p = _purchases(spark, sf_dir).withColumn("prev", F.lag("o_custkey").over(Window.partitionBy("l_partkey").orderBy(*order)))
    return dedup(p.select(F.col("o_custkey").alias("src"), F.col("prev").alias("dst"), "ord"))


def buys(spark, sf_dir):
    return dedup(_purchases(spark, sf_dir).select(F.col("o_custkey").alias("src"), (F.col("l_partkey") + PART).alias("dst"), "ord"))


def buysup(spark, sf_dir):
    return dedup(_purchases(spark, sf_dir).select(F.col("o_custkey").alias("src"), (F.col("l_suppkey") + SUPPLIER).alias("dst"), "ord"))


def _events(spark, sf_dir):
    return table(spark, sf_dir, "events").select("event_id", "user_id", "event_type", "ts").withColumn("ord", micros("ts"))


def handoff(spark, sf_dir):
    e = _events(spark, sf_dir).withColumn("one", F.lit(1))
    return dedup(lag_over_time(e, ["one"], "user_id", ["ts", "event_id"], F.to_date("ts")).select(F.col("user_id").alias("src"), F.col("prev").alias("dst"), "ord"))


def handoff_t(spark, sf_dir):
    e = _events(spark, sf_dir)
    return dedup(lag_over_time(e, ["event_type"], "user_id", ["ts", "event_id"], F.to_date("ts")).select(F.col("user_id").alias("src"), F.col("prev").alias("dst"), "ord"))


#: Words whose pairs a task counts at a time, and words whose ids it remembers.
CHUNK, REMEMBERED = 1_000_000, 500_000
_PAIRS = pa.schema([("src", pa.int64()), ("dst", pa.int64()), ("ord", pa.int64()), ("mult", pa.int64())])


def _word_pairs(batches):
    """First place and count of each pair of neighbouring words, a chunk of texts at a time; equal words make no pair."""
    find, ids = re.compile("[a-zà-ÿ]+").findall, {}

    def counted(words, docs, sizes):
        known: dict[str, int] = {}
        w = np.fromiter((known.setdefault(x, len(known)) for x in words), np.int64, len(words))
        sizes = np.array(sizes, np.int64)
        pos = np.arange(len(w)) - np.repeat(np.cumsum(sizes) - sizes, sizes)
        ord_ = np.repeat(np.array(docs, np.int64), sizes) * 1_000_000 + pos
        pair = (pos[1:] > 0) & (w[1:] != w[:-1])
        code, ord_ = (w[:-1] * len(known) + w[1:])[pair], ord_[:-1][pair]
        order = np.argsort(code, kind="stable")
        code, ord_ = code[order], ord_[order]
        at = np.flatnonzero(np.r_[True, code[1:] != code[:-1]]) if len(code) else np.zeros(0, int)
        if len(ids) > REMEMBERED:
            ids.clear()
        for x in known:
            if x not in ids:
                ids[x] = int(hashlib.md5(x.encode()).hexdigest()[:15], 16)
        named = np.fromiter((ids[x] for x in known), np.int64, len(known))
        first = np.minimum.reduceat(ord_, at) if len(at) else ord_
        columns = (named[code[at] // max(1, len(known))], named[code[at] % max(1, len(known))], first, np.diff(np.r_[at, len(code)]))
        return pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in columns], schema=_PAIRS)

    words, docs, sizes = [], [], []
    for batch in batches:
        for doc, text in zip(batch.column("doc_id").to_pylist(), batch.column("text"), strict=True):
            found = find(text.as_py())
            words += found
            docs.append(doc)
            sizes.append(len(found))
            if len(words) >= CHUNK:
                yield counted(words, docs, sizes)
                words, docs, sizes = [], [], []
    if words:
        yield counted(words, docs, sizes)


def words(spark, sf_dir):
    """Words in order: each task counts pairs of its own texts, and hashes each word it meets once; the shuffle moves a row for each pair and chunk of texts."""
    d = table(spark, sf_dir, "documents").select("doc_id", F.lower("text").alias("text")).where("doc_id IS NOT NULL AND text IS NOT NULL")
    e = d.mapInArrow(_word_pairs, "src long, dst long, ord long, mult long").where("src <> dst")
    return e.groupBy("src", "dst").agg(F.min("ord").alias("ord"), F.sum("mult").alias("mult"))


def links(spark, sf_dir):
    p = table(spark, sf_dir, "pages").select("page_id", F.posexplode(F.regexp_extract_all("html", F.lit('href="([^"]*)"'), 1)).alias("pos", "href"))
    return dedup(p.select("page_id", "pos", "href").select(F.col("page_id").alias("src"), text_id("href").alias("dst"), (F.col("page_id") * 1_000_000 + F.col("pos")).alias("ord")))


#: Vectors in a block of ``near``, and queries of it that are held against a block at a time.
NEAR_BLOCK, NEAR_QUERIES = 8192, 256
#: Further than two sums of the same products can lie apart, and two cosines that round to the same 12 digits.
NEAR_MARGIN = 2e-12


def _vectors(t: pa.Table) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    ids, v, norm = (t.column(i - 3).combine_chunks() for i in range(3))
    return ids.to_numpy(), v.flatten().to_numpy().reshape(len(v), -1) if len(v) else np.zeros((0, 0)), norm.to_numpy()


def _nearest_of_block(k: int):
    """Of each query the ``k`` best of a block and all that may tie with them once rounded: of equal cosines the ``k`` smallest ids, which are all that can count."""
    schema = pa.schema([("src", pa.int64()), ("dst", pa.int64()), ("cosine", pa.float64())])

    def search(queries: pa.Table, rows: pa.Table) -> pa.Table:
        (qid, q, qn), (vid, v, vn) = _vectors(queries), _vectors(rows)
        got = [(np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0))]
        for a in range(0, len(qid) if len(vid) else 0, NEAR_QUERIES):
            part = slice(a, a + NEAR_QUERIES)
            rough = q[part] @ v.T / (qn[part, None] * vn)
            rough[qid[part, None] == vid] = -np.inf
            rough[np.isnan(rough)] = np.inf  # sorts before all numbers, as in SQL
            least = np.partition(rough, -k, axis=1)[:, -k, None] if len(vid) > k else np.full((len(rough), 1), -np.inf)
            i, j = np.nonzero((rough >= least - NEAR_MARGIN) & (rough > -np.inf))
            i += a
            dot = np.zeros(len(i))
            for at in range(q.shape[1]):  # in the order in which SQL adds
                dot += q[i, at] * v[j, at]
            cosine = dot / (qn[i] * vn[j])
            order = np.lexsort((vid[j], cosine, i))
            i, j, cosine = i[order], j[order], cosine[order]
            start = np.flatnonzero(np.r_[True, (i[1:] != i[:-1]) | (cosine[1:] != cosine[:-1])]) if len(i) else np.zeros(0, int)
            keep = np.arange(len(i)) - np.repeat(start, np.diff(np.r_[start, len(i)])) < k
            got.append((qid[i[keep]], vid[j[keep]], cosine[keep]))
        return pa.Table.from_arrays([pa.array(np.concatenate(c)) for c in zip(*got, strict=True)], schema=schema)

    return search


def near(spark, sf_dir, k: int = 10):
    """Vector to its ``k`` most similar ones by cosine, ties to smaller ids. Every vector is a query against all rows: blocks of queries meet blocks of rows as matrices, and the best of a block go to the last ranking."""
    v = table(spark, sf_dir, "embeddings").select("vec_id", F.expr("transform(embedding, x -> double(x))").alias("v"))
    dot = lambda a, b: F.aggregate(F.zip_with(a, b, lambda x, y: x * y), F.lit(0.0), lambda s, x: s + x)
    v = save(v.withColumn("norm", F.sqrt(dot("v", "v"))).where("norm > 0").select(F.col("vec_id").alias("id"), "v", "norm"), "vectors")
    blocks = max(4, -(-v.count() // NEAR_BLOCK))
    own = v.withColumn("own", F.pmod(F.xxhash64("id"), F.lit(blocks)).cast("int"))
    every = F.explode(F.sequence(F.lit(0), F.lit(blocks - 1)))
    q, rows = own.select(F.col("own").alias("a"), every.alias("b"), F.col("id").alias("src"), F.col("v").alias("qv"), F.col("norm").alias("qn")), own.select(every.alias("c"), F.col("own").alias("d"), F.col("id").alias("dst"), F.col("v").alias("rv"), F.col("norm").alias("rn"))
    x = q.groupBy("a", "b").cogroup(rows.groupBy("c", "d")).applyInArrow(_nearest_of_block(k), "src long, dst long, cosine double")
    x = x.select("src", "dst", F.round("cosine", 12).alias("sim"))
    x = x.withColumn("r", F.row_number().over(Window.partitionBy("src").orderBy(F.desc("sim"), F.asc("dst")))).where(F.col("r") <= k)
    return dedup(x.select("src", "dst", (F.col("src") * k + F.col("r") - 1).alias("ord")))


def _attached(spark, edges_: int, n: int, share: Column, seed: int, tag: str, hops: int) -> DataFrame:
    """``(id, pick)``: a node for each of ``edges_`` draws, uniform over ``n`` nodes or, with chance ``share`` (of 2 to the 32), that of a uniform earlier draw.

    The copy is a pointer; pointers double until all rest at a draw that chose for itself.
    """
    a, b = coin(seed, tag, F.col("id"), 0, 0)
    e = spark.range(edges_).select("id", a.alias("a"), b.alias("b"))
    copies = (F.col("a") < share) & (F.col("id") > 0)
    e = e.select("id", F.when(copies, slot(F.col("b"), F.col("id"))).otherwise(F.col("id")).alias("at"), slot(F.col("b"), F.lit(n)).alias("own"))
    for _ in range(max(1, (hops - 1).bit_length())):
        e = save(e, "pointers")
        e = e.join(e.select(F.col("id").alias("at"), F.col("at").alias("next")), "at").select("id", F.col("next").alias("at"), "own")
    e = save(e, "pointers")
    return e.join(e.select(F.col("id").alias("at"), F.col("own").alias("pick")), "at").select("id", "pick")


def pref(spark, sf_dir, n: int = 2000, out: int = 8, mix: float = 0.7, seed: int = 5, hops: int = 120):
    """Preferential attachment without a sequential loop; edge t belongs to node t div ``out``."""
    e = _attached(spark, n * out, n, F.lit(threshold(mix)), seed, "pref", hops)
    return dedup(e.select(F.floor(F.col("id") / out).alias("src"), F.col("pick").alias("dst"), F.col("id").alias("ord")))


def dirichlet(spark, sf_dir, n: int = 1000, m: int = 10_000, seed: int = 6, hops: int = 1000):
    """Arrivals whose source has weight degree + 1, which is a uniform node or the source of a uniform earlier edge; targets are uniform."""
    share = F.floor(F.col("id") * FULL / (F.col("id") + n))
    to = slot(coin(seed, "to", F.col("id"), 0, 0)[1], F.lit(n))
    e = _attached(spark, m, n, share, seed, "from", hops)
    return dedup(e.select(F.col("pick").alias("src"), to.alias("dst"), F.col("id").alias("ord")))


def trap(spark, sf_dir, size: int | None = None):
    """A cycle of N nodes that all point at a centre, the centre and N satellites, and N satellites of the first cycle node: 6N edges on 3N + 1 nodes.

    Cycle nodes are 1 to N, the centre 0, its satellites N + 1 to 2N, the others 2N + 1 to 3N. Without
    ``size`` the cycle is of all customers by their keys.
    """
    if size is None:
        own = save(numbered(table(spark, sf_dir, "customer").select("c_custkey"), [F.asc("c_custkey")], "id"), "customers")
        ids, size = own.select(F.col("id").cast("long").alias("id")), max(1, own.count())
    else:
        ids = spark.range(1, size + 1)
    j = F.col("id")
    pairs = F.array(
        F.struct(j.alias("src"), (j % size + 1).alias("dst")),
        F.struct(j.alias("src"), F.lit(0).cast("long").alias("dst")),
        F.struct(F.lit(0).cast("long").alias("src"), (j + size).alias("dst")),
        F.struct((j + size).alias("src"), F.lit(0).cast("long").alias("dst")),
        F.struct(F.lit(1).cast("long").alias("src"), (j + 2 * size).alias("dst")),
        F.struct((j + 2 * size).alias("src"), F.lit(1).cast("long").alias("dst")),
    )
    raw = ids.select("id", F.posexplode(pairs).alias("k", "e"))
    return dedup(raw.select("e.src", "e.dst", (F.col("id") * 6 + F.col("k")).alias("ord")))


GRAPHS: dict[str, Callable[[SparkSession, str], DataFrame]] = {f.__name__: f for f in (cobuy, buys, buysup, handoff, handoff_t, words, links, near, pref, dirichlet, trap)}

_TEXT = "('0x' || substr(md5({}), 1, 15))::BIGINT"
_P = "(SELECT l_orderkey, l_partkey, l_suppkey, l_linenumber, o_custkey, o_orderkey, o_orderdate, epoch(o_orderdate)::BIGINT AS ord FROM lineitem JOIN orders ON l_orderkey = o_orderkey)"


def _attached_sql(m: int, n: int, share: str, seed: int, tag: str, src: str, dst: str) -> str:
    h = sql_digest(seed, tag, "id", "0", "0")
    draws = f"SELECT id, CASE WHEN {sql_a('h')} < {share} AND id > 0 THEN ({sql_b('h')} * id) >> 32 ELSE id END AS ptr, ({sql_b('h')} * {n}) >> 32 AS own FROM (SELECT id, {h} AS h FROM range({m}) t(id))"
    walk = f"WITH RECURSIVE p AS ({draws}), c AS (SELECT id, ptr FROM p UNION ALL SELECT c.id, p.ptr FROM c JOIN p ON p.id = c.ptr WHERE p.ptr <> c.ptr) SELECT c.id, p.own AS pick FROM c JOIN p ON p.id = c.ptr AND p.ptr = p.id"
    return f"SELECT {src} AS src, {dst} AS dst, id AS ord FROM ({walk})"


_RAW = {
    "cobuy": f"SELECT o_custkey AS src, lag(o_custkey) OVER (PARTITION BY l_partkey ORDER BY o_orderdate, o_orderkey, l_linenumber) AS dst, ord FROM {_P}",
    "buys": f"SELECT o_custkey AS src, l_partkey + {PART} AS dst, ord FROM {_P}",
    "buysup": f"SELECT o_custkey AS src, l_suppkey + {SUPPLIER} AS dst, ord FROM {_P}",
    "handoff": "SELECT user_id AS src, lag(user_id) OVER (ORDER BY ts, event_id) AS dst, epoch_us(ts) AS ord FROM events",
    "handoff_t": "SELECT user_id AS src, lag(user_id) OVER (PARTITION BY event_type ORDER BY ts, event_id) AS dst, epoch_us(ts) AS ord FROM events",
    "words": f"SELECT {_TEXT.format('w[i]')} AS src, {_TEXT.format('w[i + 1]')} AS dst, doc_id * 1000000 + i - 1 AS ord FROM (SELECT doc_id, w, unnest(range(1, len(w))) AS i FROM (SELECT doc_id, regexp_extract_all(lower(text), '([a-zà-ÿ]+)', 1) AS w FROM documents) WHERE len(w) > 1)",
    "links": f"SELECT page_id AS src, {_TEXT.format('h[i]')} AS dst, page_id * 1000000 + i - 1 AS ord FROM (SELECT page_id, h, unnest(range(1, len(h) + 1)) AS i FROM (SELECT page_id, regexp_extract_all(html, 'href=\"([^\"]*)\"', 1) AS h FROM pages))",
    "near": "SELECT src, dst, src * 10 + r - 1 AS ord FROM (SELECT a.vec_id AS src, b.vec_id AS dst, row_number() OVER (PARTITION BY a.vec_id ORDER BY round(list_dot_product(a.v, b.v) / (sqrt(list_dot_product(a.v, a.v)) * sqrt(list_dot_product(b.v, b.v))), 12) DESC, b.vec_id) AS r FROM (SELECT vec_id, embedding::DOUBLE[] AS v FROM embeddings) a JOIN (SELECT vec_id, embedding::DOUBLE[] AS v FROM embeddings) b ON a.vec_id <> b.vec_id) WHERE r <= 10",
    "pref": _attached_sql(16_000, 2000, str(threshold(0.7)), 5, "pref", "id // 8", "pick"),
    "dirichlet": _attached_sql(10_000, 1000, f"floor(id::DOUBLE * {FULL} / (id + 1000))", 6, "from", "pick", f"({sql_b(sql_digest(6, 'to', 'id', '0', '0'))} * 1000) >> 32"),
    "trap": "SELECT unnest([j, j, 0, j + n, 1, j + 2 * n]) AS src, unnest([j % n + 1, 0, j + n, 0, j + 2 * n, 1]) AS dst, j * 6 + unnest([0, 1, 2, 3, 4, 5]) AS ord FROM (SELECT row_number() OVER (ORDER BY c_custkey) AS j, count(*) OVER () AS n FROM customer)",
}


def edges_sql(name: str) -> str:
    return f"SELECT src, dst, min(ord)::BIGINT AS ord, count(*)::BIGINT AS mult FROM ({_RAW[name]}) WHERE src IS NOT NULL AND dst IS NOT NULL AND src <> dst GROUP BY src, dst"


def edges(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return GRAPHS[name](spark, sf_dir)
