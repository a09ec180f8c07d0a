"""Packing tokenized documents into sequences of bounded length: best fit, then local search by swaps.

Pieces are dealt out evenly into groups of bounded size that are packed apart, so work and memory
of a task do not grow with the corpus; a group wastes less than one sequence beyond its own packing.
"""

from __future__ import annotations

import os
import struct
import zlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from incwalk.llm.common import memo as new_memo
from incwalk.llm.common import save, tidy

#: Words that a worker remembers, and bytes of them and their ids.
MEMO, MEMO_BYTES = 1_000_000, 80 << 20
#: Pieces packed together in one task.
GROUP = 20_000
SIGNS = b".,#$%&*"
_STATE: dict = {}


def cut_words(text: bytes) -> list[bytes]:
    """Parts that the tokenizer treats apart. It lower-cases itself; only the strings of special tokens are told by case."""
    return text.split() if b"<|" in text else text.lower().split()


def stem_of(word: bytes) -> bytes:
    """The word without signs at its end, where a letter stands before them: there the pre-tokenizer cuts."""
    stem = word.rstrip(SIGNS)
    return stem if stem and 97 <= stem[-1] <= 122 else word


def _encoder(path: str):
    if path not in _STATE:
        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        from tokenizers import Tokenizer

        model = Tokenizer.from_file(path)
        model.no_truncation()
        model.no_padding()
        word = "abcdefghijklmnopqrstuvwxyz"
        direct = [t.id for t in model.model.tokenize(word)] == model.encode(word, add_special_tokens=False).ids
        _STATE[path] = [model, new_memo(), 0, model.model.tokenize if direct else None]
    return _STATE[path]


def word_ids(path: str, texts: list[bytes]) -> list[bytes]:
    """Little-endian 32-bit ids of each text, for lower-casing tokenizers that drop white space: part by part, from a bounded memo."""
    state = _encoder(path)
    model, memo, held, _ = state
    if not memo or len(memo) > MEMO or held > MEMO_BYTES:
        memo.clear()
        state[2] = 0
    cut = [cut_words(t) for t in texts]
    signed = {}
    new = set()
    for w in {w for words in cut for w in words if w not in memo}:
        stem = stem_of(w)
        if len(stem) < len(w):
            signed[w] = stem
            new.update(x for x in (stem, w[len(stem) :]) if x not in memo)
        else:
            new.add(w)
    # a run of ASCII letters is one token for the pre-tokenizer: it can go to the merges at once
    plain = [w for w in new if w.isalpha()] if state[3] else []
    for w in plain:
        ids = [t.id for t in state[3](w.decode())]
        memo[w] = struct.pack(f"<{len(ids)}I", *ids)
    new = [w for w in new if not w.isalpha() or not plain]
    for i in range(0, len(new), 20_000):
        own = new[i : i + 20_000]
        for w, e in zip(own, model.encode_batch_fast([x.decode() for x in own], add_special_tokens=False), strict=True):
            memo[w] = np.array(e.ids, "<u4").tobytes()
    state[2] += sum(len(w) + len(memo[w]) for own in (plain, new) for w in own)
    memo.update((w, memo[stem] + memo[w[len(stem) :]]) for w, stem in signed.items())
    get = memo.__getitem__
    return [b"".join(map(get, words)) for words in cut]


def tokenized_pieces(docs: DataFrame, tokenizer_path: str, length: int = 4096, end_id: int = 1, id_col: str = "doc_id", text_col: str = "text", with_ids: bool = False) -> DataFrame:
    """``doc_id``, ``piece``, ``start``, ``length``, ``ids_crc32`` and, if asked for, ``ids``: a document's ids and ``end_id``, cut into pieces of ``length``."""
    fields = [("doc_id", pa.int64()), ("piece", pa.int32()), ("start", pa.int64()), ("length", pa.int64()), ("ids_crc32", pa.int64())] + [("ids", pa.binary())] * with_ids
    schema = pa.schema(fields)
    end = np.array([end_id], "<u4").tobytes()

    def run(batches):
        for batch in batches:
            doc_ids = batch.column("doc_id").to_pylist()
            texts = batch.column("text").cast(pa.large_binary())
            for i in range(0, len(doc_ids), 500):
                rows = []
                for doc_id, ids in zip(doc_ids[i : i + 500], word_ids(tokenizer_path, [t.as_py() or b"" for t in texts[i : i + 500]]), strict=True):
                    ids += end
                    for p, at in enumerate(range(0, len(ids), 4 * length)):
                        own = ids[at : at + 4 * length]
                        rows.append((doc_id, p, at // 4, len(own) // 4, zlib.crc32(own), own))
                yield pa.RecordBatch.from_arrays([pa.array([r[k] for r in rows], f.type) for k, f in enumerate(schema)], schema=schema)

    rows = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text"))
    return rows.mapInArrow(tidy(run), "doc_id long, piece int, start long, length long, ids_crc32 long" + ", ids binary" * with_ids)


def best_fit(sizes: list[int], room: int) -> list[list[int]]:
    """Bins of indices: largest first, each into the fullest bin that still takes it. Bins by free space, found through a bit mask."""
    bins: list[list[int]] = []
    by_free: list[list[int]] = [[] for _ in range(room + 1)]
    mask = 0
    for i in sorted(range(len(sizes)), key=lambda k: -sizes[k]):
        s = sizes[i]
        above = mask >> s
        if above:
            free = s + (above & -above).bit_length() - 1
            b = by_free[free].pop()
            if not by_free[free]:
                mask &= ~(1 << free)
            bins[b].append(i)
        else:
            free, b = room, len(bins)
            bins.append([i])
        left = free - s
        by_free[left].append(b)
        if left:
            mask |= 1 << left
    return bins


def give_ups(own: list[int], sizes: list[int]) -> list[tuple[int, ...]]:
    """What a bin can give up in a step: nothing, one document or two, one choice for each size or pair of sizes.

    A bin of room r holds fewer than sqrt(2 r) distinct sizes, so there are about r pairs at most.
    """
    of_size: dict[int, list[int]] = {}
    for i in own:
        of_size.setdefault(sizes[i], []).append(i)
    one = [of_size[s] for s in sorted(of_size)]
    two = [(a[0], b[0]) for n, a in enumerate(one) for b in one[n + 1 :]] + [(a[0], a[1]) for a in one if len(a) > 1]
    return [()] + [(a[0],) for a in one] + two


def local_search(sizes: list[int], bins: list[list[int]], room: int) -> list[list[int]]:
    """Fills underfull bins, fullest first, out of emptier ones until bins empty.

    A step takes one document from an emptier bin for none, one or two smaller ones of the bin being
    filled, whichever leaves the least free space. Fill moves from an emptier to a fuller bin, so the
    sum of squared fills rises with each step, and the search ends. A round passes over all underfull
    bins; rounds end when none gains or at the lower bound, the total over the room.
    """
    fill = [sum(sizes[i] for i in b) for b in bins]
    least = -(-sum(fill) // room)
    while sum(1 for b in bins if b) > least:
        under = sorted((b for b in range(len(bins)) if bins[b] and fill[b] < room), key=lambda b: -fill[b])
        where: dict[int, int] = {}
        by_size: list[set[int]] = [set() for _ in range(room + 1)]
        mask = 0
        for b in under:
            for i in bins[b]:
                where[i] = b
                by_size[sizes[i]].add(i)
                mask |= 1 << sizes[i]

        def drop(i):
            nonlocal mask
            own = by_size[sizes[i]]
            own.discard(i)
            if not own:
                mask &= ~(1 << sizes[i])

        gained = False
        for b in under:
            for i in bins[b]:
                drop(i)
            while bins[b] and fill[b] < room and mask:
                free, best = room - fill[b], None
                for give in give_ups(bins[b], sizes):
                    out = sum(sizes[k] for k in give)
                    top = min(room, out + free)
                    at = (mask & ((1 << (top + 1)) - 1)).bit_length() - 1
                    if at > out and (best is None or at - out > best[0]):
                        best = (at - out, at, give)
                        if best[0] == free:
                            break
                if best is None:
                    break
                gain, at, give = best
                i = min(by_size[at], key=lambda k: (fill[where[k]], k))
                e = where[i]
                drop(i)
                bins[e].remove(i)
                bins[b].append(i)
                where[i] = b
                for k in give:
                    bins[b].remove(k)
                    bins[e].append(k)
                    where[k] = e
                    by_size[sizes[k]].add(k)
                    mask |= 1 << sizes[k]
                fill[b] += gain
                fill[e] -= gain
                gained = True
        if not gained:
            break
    return [b for b in bins if b]


def pack(pieces: DataFrame, room: int = 4096, group: int = GROUP) -> DataFrame:
    """Adds ``sequence_id`` and ``offset`` to pieces that have ``length``. No piece may be longer than ``room``."""
    from pyspark.sql import types as T
    from pyspark.sql.pandas.types import to_arrow_schema

    groups = max(1, -(-pieces.count() // group))
    dealt = pieces.withColumn("__group", F.pmod(F.xxhash64("doc_id", "piece"), F.lit(groups)).cast("long"))
    dealt = dealt.repartition("__group").sortWithinPartitions("__group")
    out = T.StructType(pieces.schema.fields + [T.StructField("sequence_id", T.LongType()), T.StructField("offset", T.LongType())])
    schema = to_arrow_schema(out)

    def close(held):
        t = pa.Table.from_batches(held).combine_chunks()
        sizes = t.column("length").to_pylist()
        g = t.column("__group")[0].as_py()
        bins = local_search(sizes, best_fit(sizes, room), room)
        seq, off = [0] * len(sizes), [0] * len(sizes)
        for b, own in enumerate(bins):
            at = 0
            for i in own:
                seq[i], off[i] = (g << 32) + b, at
                at += sizes[i]
        t = t.drop_columns(["__group"]).append_column("sequence_id", pa.array(seq, pa.int64())).append_column("offset", pa.array(off, pa.int64()))
        return t.cast(schema).to_batches()

    def run(batches):
        held, now = [], None
        for batch in batches:
            col = batch.column("__group").to_numpy()
            cuts = [0, *(np.flatnonzero(col[1:] != col[:-1]) + 1).tolist(), len(col)] if len(col) else []
            for a, b in zip(cuts, cuts[1:], strict=False):
                if held and col[a] != now:
                    yield from close(held)
                    held = []
                now = col[a]
                held.append(batch.slice(a, b - a))
        if held:
            yield from close(held)

    return dealt.mapInArrow(tidy(run), out)


def pack_documents(docs: DataFrame, tokenizer_path: str, room: int = 4096, end_id: int = 1, id_col: str = "doc_id", text_col: str = "text", with_ids: bool = False) -> DataFrame:
    """One row for each piece of each document: where it starts in the document, and its sequence and offset.

    A null or empty text is the end id alone. Only documents over ``room`` tokens are cut. Repeated
    rows and null ids are packed as rows of their own; other columns are not read. An empty table
    gives an empty result.
    """
    return pack(save(tokenized_pieces(docs, tokenizer_path, room, end_id, id_col, text_col, with_ids), "pieces"), room)
