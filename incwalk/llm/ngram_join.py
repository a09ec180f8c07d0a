"""N-gram Jaccard self-join: which documents are linked, and what they are connected to.

Rare-first prefix filtering. The global order of n-grams is by document frequency, then by hash. A
document with n distinct n-grams can only reach similarity num/den with another if they share one
of its first ``n - ceil(num * n / den) + 1`` n-grams in that order. N-grams of frequency one come
first and match nothing, so only documents whose unique n-grams leave part of the prefix free go
on, and an intersection needs n-grams of frequency two or more alone.

1. One pass over the texts counts all n-grams in a packed exchange (``packed``) and gives each
   document its shared n-grams with their frequencies.
2. Documents with equal sets form classes; one representative goes on.
3. Representatives that share a prefix n-gram, directly or through others, form candidate
   clusters, so that a representative's n-grams are sent once rather than once a pair.
4. In a cluster, a search over the not yet reached documents finds the links: prefix postings with
   length, positional and suffix filters, then one verification a pair; pairs that are already
   connected need none. Clusters over a bounded weight are dealt out as blocks and as pairs of
   blocks; a pair of blocks only meets pairs between the two, so each pair is verified once at most.
5. Components of the links, joined back to every row.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from incwalk.llm.common import forget, part_count, save, tidy
from incwalk.llm.components import connected_components
from incwalk.llm.packed import SCHEMA, Packer, _runs, by_document, count_ranges, exchange

#: Frequencies are exact below this; n-grams at or above it tie and go by hash.
CAP = 1024
#: Distinct shared n-grams in one block of a cluster; a task holds two blocks.
BLOCK = 1_000_000
_MIX = [np.uint64(x) for x in (0x9E3779B97F4A7C15, 0xC2B2AE3D27D4EB4F, 0x165667B19E3779F9, 0x27D4EB2F165667C5)]
HEAD = np.dtype([("id", "<i8"), ("has", "u1"), ("n", "<i8"), ("s1", "<u8"), ("s2", "<u8")])


def scramble(x: np.ndarray) -> np.ndarray:
    x = x ^ (x >> np.uint64(30))
    x = x * np.uint64(0xBF58476D1CE4E5B9)
    x = x ^ (x >> np.uint64(27))
    x = x * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


def shingle_set(text: bytes | None, size: int) -> np.ndarray:
    """Sorted distinct 64-bit hashes of the ``size``-word n-grams of a text, A-Z lower-cased."""
    words = text.lower().split() if text else []
    if not words:
        return np.zeros(0, np.uint64)
    hashed = xxhash.xxh3_64_intdigest
    x = np.array([hashed(w) for w in words], np.uint64)
    m = len(x) - size + 1
    if m < 1:
        return np.array([hashed(b"\n".join(words), seed=len(words))], np.uint64)
    s = np.zeros(m, np.uint64)
    for i in range(size):  # position-dependent, order-sensitive
        s = (s ^ x[i : i + m]) * _MIX[i % 4] + np.uint64(i + 1)
        s ^= s >> np.uint64(29)
    return np.unique(scramble(s))


def overlap_needed(n: int, m, num: int, den: int):
    """Least intersection with den * intersection >= num * union."""
    return -(-num * (n + m) // (num + den))


def prefix_length(n, num: int, den: int):
    return n - -(-num * n // den) + 1


def _map(size: int, parts: int, doc_parts: int):
    def run(batches):
        forget()
        packer = Packer(parts, doc_parts, CAP, has_lvl=True)
        for batch in batches:
            texts = batch.column("text").cast(pa.large_binary())
            for rid, doc_id, text in zip(batch.column("rid").to_pylist(), batch.column("doc_id").to_pylist(), texts, strict=True):
                s = shingle_set(text.as_py(), size)
                own = rid & 0xFFFFFFFFFFFFFFFF
                d = s.tobytes()
                sig = xxhash.xxh3_128_intdigest(d)
                packer.head(own, np.array([(doc_id or 0, doc_id is not None, len(s), sig & 0xFFFFFFFFFFFFFFFF, sig >> 64)], HEAD).tobytes())
                packer.add(own, s)
                if packer.full():
                    yield from packer.rows()
        yield from packer.rows()

    return tidy(run)


PROFILE = "rid long, doc_id long, n long, s1 long, s2 long, tokens binary, levels binary"
_PROFILE = pa.schema([("rid", pa.int64()), ("doc_id", pa.int64()), ("n", pa.int64()), ("s1", pa.int64()), ("s2", pa.int64()), ("tokens", pa.binary()), ("levels", pa.binary())])


def _finish(num: int, den: int):
    def finish(ids, data, x):
        head = np.frombuffer(b"".join(data), HEAD)
        at, run = _runs(x["rid"])
        where = dict(zip(x["rid"][at].tolist(), zip(at.tolist(), run.tolist(), strict=True), strict=True))
        cols = {c: [] for c in _PROFILE.names}
        signed = ids.view(np.int64).tolist()
        for i, rid in enumerate(ids.tolist()):
            n, tokens, levels = int(head["n"][i]), None, None
            if rid in where:
                s, m = where[rid]
                key, first = np.unique(x["key"][s : s + m], return_index=True)
                if n - len(key) < prefix_length(n, num, den):
                    lvl = x["lvl"][s : s + m][first]
                    order = np.lexsort((key, lvl))
                    tokens, levels = key[order].tobytes(), lvl[order].tobytes()
            for c, v in zip(_PROFILE.names, (signed[i], int(head["id"][i]) if head["has"][i] else None, n, int(head["s1"][i].view(np.int64)), int(head["s2"][i].view(np.int64)), tokens, levels), strict=True):
                cols[c].append(v)
            if len(cols["rid"]) >= 5000:
                yield pa.RecordBatch.from_pydict(cols, schema=_PROFILE)
                cols = {c: [] for c in _PROFILE.names}
        yield pa.RecordBatch.from_pydict(cols, schema=_PROFILE)

    return finish


def _postings(num: int, den: int):
    schema = pa.schema([("token", pa.int64()), ("rid", pa.int64())])

    def run(batches):
        for batch in batches:
            token, rid = [], []
            for r, n, t in zip(batch.column("rid").to_pylist(), batch.column("n").to_pylist(), batch.column("tokens").to_pylist(), strict=True):
                key = np.frombuffer(t, np.int64)
                key = key[: max(0, prefix_length(n, num, den) - (n - len(key)))]
                token.append(key)
                rid.append(np.full(len(key), r))
            if token:
                yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(token)), pa.array(np.concatenate(rid))], schema=schema)

    return tidy(run)


def link_block(n: np.ndarray, tokens: list[np.ndarray], levels: list[np.ndarray], num: int, den: int, side: np.ndarray | None = None, verified: list | None = None, every: bool = False) -> list[tuple[int, int]]:
    """Links that connect whatever is connected by links among these documents, or by links between the two values of ``side``; all links with ``every``.

    Breadth-first over documents not reached so far: a document's prefix postings give candidates,
    the length, positional and suffix filters drop most, the rest are verified together. A document
    closes before it is looked from, so no pair is verified twice; ``verified`` gathers them. With
    ``every`` a document only closes when it has been looked from itself, so each pair is met once.
    """
    size = np.array([len(t) for t in tokens])
    key, inverse = np.unique(np.concatenate(tokens), return_inverse=True)
    lvl = np.zeros(len(key), np.uint16)
    lvl[inverse] = np.concatenate(levels)
    rank = np.empty(len(key), np.int64)
    rank[np.lexsort((key, lvl))] = np.arange(len(key))
    flat = rank[inverse]
    start = np.r_[0, np.cumsum(size)]
    lone = n - size  # n-grams of frequency one: they take the first places
    prefix = np.clip(prefix_length(n, num, den) - lone, 0, size)
    doc = np.repeat(np.arange(len(n)), prefix)
    inside = np.arange(prefix.sum()) - np.repeat(np.r_[0, np.cumsum(prefix)][:-1], prefix)
    post = flat[start[doc] + inside]
    order = np.argsort(post, kind="stable")
    post, doc, place = post[order], doc[order], (inside + lone[doc])[order]
    open_ = np.ones(len(n), bool)
    marked = np.zeros(len(key), bool)
    edges = []
    for seed in range(len(n)):
        if not open_[seed]:
            continue
        open_[seed], queue = False, [seed]
        while queue:
            x = queue.pop()
            own = flat[start[x] : start[x + 1]]
            head = own[: prefix[x]]
            lo, hi = np.searchsorted(post, head), np.searchsorted(post, head, side="right")
            many = hi - lo
            if not many.any():
                continue
            at = np.repeat(lo - np.r_[0, np.cumsum(many)][:-1], many) + np.arange(many.sum())
            y, py, px = doc[at], place[at], np.repeat(np.arange(len(head)) + lone[x], many)
            on = open_[y] & (den * np.minimum(n[y], n[x]) >= num * np.maximum(n[y], n[x]))  # length filter
            if side is not None:
                on &= side[y] != side[x]
            y, first = np.unique(y[on], return_index=True)  # the first common n-gram of each
            if not len(y):
                continue
            py, px = py[on][first], px[on][first]
            need = overlap_needed(n[x], n[y], num, den)
            on = 1 + np.minimum(n[x] - px - 1, n[y] - py - 1) >= need  # positional filter
            y, py, px, need = y[on], py[on], px[on], need[on]
            if not len(y):
                continue
            # suffix filter: what lies before and behind the middle n-gram of y's suffix bounds the Hamming distance
            left_y, right_y = start[y] + (py - lone[y]) + 1, start[y + 1]
            mid = np.minimum((left_y + right_y) // 2, len(flat) - 1)
            left_x = px - lone[x] + 1
            cut = np.maximum(np.searchsorted(own, flat[mid]), left_x)
            apart = np.where(left_y < right_y, np.abs((cut - left_x) - (mid - left_y)) + np.abs((len(own) - cut) - (right_y - mid)), len(own) - left_x)
            on = px + py + apart <= n[x] + n[y] - 2 * need
            y, need = y[on], need[on]
            if not len(y):
                continue
            if verified is not None:
                verified += [(x, int(z)) for z in y]
            marked[own] = True
            many = size[y]
            at = np.repeat(start[y] - np.r_[0, np.cumsum(many)][:-1], many) + np.arange(many.sum())
            common = np.add.reduceat(marked[flat[at]].astype(np.int64), np.r_[0, np.cumsum(many)[:-1]])
            marked[own] = False
            for z in y[common >= need].tolist():
                edges.append((x, z))
                if not every:
                    open_[z] = False
                    queue.append(z)
    return edges


def _link_groups(num: int, den: int, every: bool = False):
    schema = pa.schema([("a", pa.int64()), ("b", pa.int64())])

    def close(key, rows):
        if len(rows) < 2:
            return None
        side = np.array([r[4] for r in rows]) if key[1] != key[2] else None  # pairs inside a block are met where it stands alone
        edges = link_block(np.array([r[1] for r in rows]), [np.frombuffer(r[2], np.uint64) for r in rows], [np.frombuffer(r[3], np.uint16) for r in rows], num, den, side, every=every)
        return pa.RecordBatch.from_arrays([pa.array([rows[a][0] for a, _ in edges], pa.int64()), pa.array([rows[b][0] for _, b in edges], pa.int64())], schema=schema) if edges else None

    def run(batches):
        key, rows = None, []
        for batch in batches:
            for r in zip(*(batch.column(c).to_pylist() for c in ("cluster", "i", "j", "rid", "n", "tokens", "levels", "own")), strict=True):
                if r[:3] != key:
                    if (out := close(key, rows)) is not None:
                        yield out
                    key, rows = r[:3], []
                rows.append(r[3:])
        if (out := close(key, rows)) is not None:
            yield out

    return tidy(run)


def _linked(docs: DataFrame, size: int, num: int, den: int, id_col: str, text_col: str, every: bool):
    """Profiles of all rows, classes of equal sets, and links ``a, b`` between representatives of classes."""
    rows = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text"))
    rows = rows.select("doc_id", "text", F.xxhash64("doc_id", "text").alias("rid"))
    parts = part_count(rows)
    doc_parts = max(32, parts // 2)
    packed = exchange(rows.mapInArrow(_map(size, parts, doc_parts), SCHEMA))
    answered = exchange(packed.mapInArrow(count_ranges(CAP, doc_parts, True, False), SCHEMA))
    profile = save(answered.mapInArrow(by_document(_finish(num, den), HEAD.itemsize), PROFILE), "profile")

    classes = profile.where("n > 0").groupBy("s1", "s2").agg(F.min("rid").alias("cls"))
    reps = profile.where(F.col("tokens").isNotNull()).join(classes.select(F.col("cls").alias("rid")), "rid", "left_semi")
    reps = save(reps.groupBy("rid").agg(F.first("n").alias("n"), F.first("tokens").alias("tokens"), F.first("levels").alias("levels")), "reps")
    post = reps.select("rid", "n", "tokens").mapInArrow(_postings(num, den), "token long, rid long")
    leader = post.groupBy("token").agg(F.min("rid").alias("a"))
    clusters = connected_components(post.join(leader, "token").select("a", F.col("rid").alias("b")))
    member = reps.join(clusters.select(F.col("node").alias("rid"), F.col("component").alias("cluster")), "rid")
    weight = member.groupBy("cluster").agg(F.sum(F.length("tokens") / 8).alias("w")).select("cluster", F.ceil(F.col("w") / BLOCK).cast("int").alias("blocks"))
    other = F.explode(F.sequence(F.lit(0), F.col("blocks") - 1))
    dealt = member.join(weight, "cluster").withColumn("own", F.pmod(F.xxhash64("rid"), F.col("blocks")).cast("int")).withColumn("other", other)
    dealt = dealt.select("cluster", F.least("own", "other").alias("i"), F.greatest("own", "other").alias("j"), "rid", "n", "tokens", "levels", "own")
    dealt = dealt.repartition("cluster", "i", "j").sortWithinPartitions("cluster", "i", "j", "rid")
    links = dealt.mapInArrow(_link_groups(num, den, every), "a long, b long")
    return profile, classes, links


def ngram_jaccard_join(docs: DataFrame, size: int = 5, num: int = 80, den: int = 100, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row for each row of ``docs``: ``doc_id``, ``n_shingles`` and ``component_id``.

    ``row_hash`` tells rows apart by id and text; ``is_first`` marks the row that stands for its group.
    Two documents link when ``den * |A and B| >= num * |A or B|`` over their sets of ``size``-word
    n-grams; a text with fewer words is one n-gram as a whole. ``component_id`` is the smallest id
    that links reach, the row's own included. Texts that are null or hold no word have an empty set
    and link with nothing. Rows with a null id take part and can only have a null
    ``component_id`` where no row with an id is reached. Repeated rows give a row each. Other
    columns are not read. An empty table gives an empty result.
    """
    profile, classes, links = _linked(docs, size, num, den, id_col, text_col, every=False)
    found = connected_components(links)

    keyed = profile.select("rid", "doc_id", "n", "s1", "s2").join(classes, ["s1", "s2"], "left")
    keyed = keyed.join(found.withColumnRenamed("node", "cls"), "cls", "left").select("rid", "doc_id", "n", F.when(F.col("n") > 0, F.coalesce("component", "cls")).alias("grp"))
    first = F.min(F.struct(F.col("doc_id").isNull().alias("none"), F.col("doc_id"), F.col("rid").alias("first_rid")))
    smallest = keyed.where(F.col("grp").isNotNull()).groupBy("grp").agg(first.alias("least"))
    alone = F.col("grp").isNull()
    return keyed.join(smallest, "grp", "left").select(
        "doc_id",
        F.col("n").alias("n_shingles"),
        F.when(alone, F.col("doc_id")).otherwise(F.col("least.doc_id")).alias("component_id"),
        F.col("rid").alias("row_hash"),
        (alone | (F.col("rid") == F.col("least.first_rid"))).alias("is_first"),
    )


def ngram_jaccard_links(docs: DataFrame, size: int = 5, num: int = 80, den: int = 100, id_col: str = "doc_id", text_col: str = "text") -> tuple[DataFrame, DataFrame]:
    """All links, between classes of equal sets: ``(members, links)``.

    ``members`` has a row for each row of ``docs``: ``doc_id``, ``n_shingles``, ``class_id`` (null
    without words) and ``n_links``, the other classes that the row's class is linked with. ``links`` has each linked
    pair of classes once: ``class_a < class_b``. Links inside a class are not spelled out: all its rows are
    linked. Work grows with the links, so for groups alone ``ngram_jaccard_join`` is cheaper. Nulls, empty
    texts, repeated rows and empty tables are as there.
    """
    profile, classes, links = _linked(docs, size, num, den, id_col, text_col, every=True)
    links = save(links.select(F.least("a", "b").alias("class_a"), F.greatest("a", "b").alias("class_b")), "links")
    ends = links.select(F.col("class_a").alias("cls")).unionAll(links.select(F.col("class_b").alias("cls")))
    members = profile.join(classes, ["s1", "s2"], "left").join(ends.groupBy("cls").agg(F.count("*").alias("n_links")), "cls", "left")
    return members.select("doc_id", F.col("n").alias("n_shingles"), F.when(F.col("n") > 0, F.col("cls")).alias("class_id"), F.when(F.col("n") > 0, F.coalesce("n_links", F.lit(0))).otherwise(0).alias("n_links")), links


def keep_one_of_each(docs: DataFrame, size: int = 5, num: int = 80, den: int = 100, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``docs`` with one row of each group of linked documents: the smallest id's; rows without words all stay, once each."""
    found = ngram_jaccard_join(docs.select(id_col, text_col), size, num, den, id_col, text_col).where("is_first").select(F.col("row_hash").alias("__rid"))
    rows = docs.withColumn("__rid", F.xxhash64(F.col(id_col).cast("long"), F.col(text_col).cast("string"))).join(found, "__rid", "left_semi")
    once = F.row_number().over(Window.partitionBy("__rid").orderBy("__rid"))
    return rows.withColumn("__once", once).where(F.col("__once") == 1).select(*docs.columns)
