"""Removal of passages that occur more than once, by Rabin-Karp hashes of every fixed-length word window.

A window is ``window`` consecutive words of one text. Two rounds of counting:

1. Anchors. Of the word n-grams in a window the one with the least hash is its anchor, so equal
   windows have equal anchors at equal offsets, and neighbours mostly share theirs. A text has some
   ``2 / (span + 1)`` anchors a word. A window whose anchor occurs at one place of the corpus
   occurs once itself, and is settled.
2. The other windows are counted by two Rabin-Karp hashes (80 bits and the key range).

Both go through the packed exchange. Repeated windows come back to their text, where overlapping
ones merge into maximal intervals of words.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import xxhash
from numpy.lib.stride_tricks import sliding_window_view
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from incwalk.llm.common import forget, part_count, planes, save, tidy, unplanes
from incwalk.llm.ngram_join import scramble
from incwalk.llm.packed import SCHEMA, Packer, _runs, by_document, count_ranges, exchange

ANCHOR = 8
BASES = (0x9E3779B97F4A7C15, 0xD6E8FEB86659FD93)


def word_hashes(words: list[bytes]) -> np.ndarray:
    hashed = xxhash.xxh3_64_intdigest
    return np.array([hashed(w) for w in words], np.uint64)


def rabin_karp(x: np.ndarray, length: int, base: int) -> np.ndarray:
    """Hash of every run of ``length``, modulo 2**64, from prefix sums and the inverse of the odd base."""
    n = len(x)
    powers = np.cumprod(np.r_[np.uint64(1), np.full(n - 1, base, np.uint64)], dtype=np.uint64)
    sums = np.r_[np.uint64(0), np.cumsum(x * powers, dtype=np.uint64)]
    back = np.cumprod(np.r_[np.uint64(1), np.full(n - length, pow(base, -1, 1 << 64), np.uint64)], dtype=np.uint64)
    return scramble((sums[length:] - sums[:-length]) * back)


def anchors(x: np.ndarray, window: int) -> tuple[np.ndarray, np.ndarray]:
    """Anchor hashes at every word, and the anchor's word for every window."""
    k = min(ANCHOR, window)
    h = rabin_karp(x, k, BASES[0])
    span = window - k + 1
    m = len(x) - window + 1
    at = np.empty(m, np.int64)
    for i in range(0, m, 8192):
        at[i : i + 8192] = sliding_window_view(h[i : i + 8192 + span - 1], span).argmin(axis=1)[: m - i]
    return h, at + np.arange(m)


def _texts(batch):
    return (t.as_py() for t in batch.column("text").cast(pa.large_binary()))


def _map_anchors(window: int, parts: int, doc_parts: int):
    def run(batches):
        forget()
        packer = Packer(parts, doc_parts, 2, has_pos=True)
        for batch in batches:
            for rid, text in zip(batch.column("rid").to_pylist(), _texts(batch), strict=True):
                words = text.split() if text else []
                if len(words) >= window:
                    h, at = anchors(word_hashes(words), window)
                    at = np.unique(at)
                    packer.add(rid & 0xFFFFFFFFFFFFFFFF, h[at], None, at)
                    if packer.full():
                        yield from packer.rows()
        yield from packer.rows()

    return tidy(run)


def _map_windows(window: int, parts: int, doc_parts: int):
    def run(batches):
        forget()
        packer = Packer(parts, doc_parts, 2, has_aux=True, has_pos=True)
        for batch in batches:
            for rid, text, places in zip(batch.column("rid").to_pylist(), _texts(batch), batch.column("places").to_pylist(), strict=True):
                x = word_hashes(text.split())
                hit = np.zeros(len(x), bool)
                hit[unplanes(places, np.uint32)] = True
                _, at = anchors(x, window)
                on = np.flatnonzero(hit[at])
                packer.add(rid & 0xFFFFFFFFFFFFFFFF, rabin_karp(x, window, BASES[1])[on], (rabin_karp(x, window, BASES[0])[on] >> np.uint64(32)).astype(np.uint32), on)
                if packer.full():
                    yield from packer.rows()
        yield from packer.rows()

    return tidy(run)


_PLACES = pa.schema([("rid", pa.int64()), ("places", pa.binary())])


def _finish(ids, data, x):
    at, run = _runs(x["rid"])
    rid = x["rid"][at].astype(np.uint64).view(np.int64)
    places = [planes(np.unique(x["pos"][s : s + m])) for s, m in zip(at, run, strict=True)]
    for i in range(0, len(places), 5000):
        yield pa.RecordBatch.from_arrays([pa.array(rid[i : i + 5000]), pa.array(places[i : i + 5000], pa.binary())], schema=_PLACES)


def _counted(df: DataFrame, mapper, doc_parts: int) -> DataFrame:
    packed = exchange(df.mapInArrow(mapper, SCHEMA))
    answered = exchange(packed.mapInArrow(count_ranges(2, doc_parts, False, True), SCHEMA))
    return answered.mapInArrow(by_document(_finish, 0), "rid long, places binary")


def repeated_windows(rows: DataFrame, window: int) -> DataFrame:
    """``(rid, places)`` of the texts that have repeated windows: their start words, as byte planes of uint32. ``rows``: rid, text."""
    parts = part_count(rows)
    doc_parts = max(32, parts // 2)
    first = save(_counted(rows, _map_anchors(window, parts, doc_parts), doc_parts), "anchors")
    kept = rows.join(first.hint("shuffle_hash"), "rid")
    return _counted(kept, _map_windows(window, parts, doc_parts), doc_parts)


def _cut(window: int, text_col: str, names: list[str], schema: pa.Schema):
    def run(batches):
        for batch in batches:
            texts, n_words, n_removed, removed = [], [], [], []
            for text, places in zip(batch.column("__text").cast(pa.large_binary()), batch.column("__places").to_pylist(), strict=True):
                text = text.as_py()
                words = text.split() if text else []
                n_words.append(len(words))
                spans = []
                if places is not None:
                    starts = unplanes(places, np.uint32).astype(np.int64)
                    new = np.r_[True, starts[1:] > starts[:-1] + window]
                    ends = starts[np.r_[np.flatnonzero(new)[1:] - 1, len(starts) - 1]] + window
                    spans = list(zip(starts[new].tolist(), ends.tolist(), strict=True))
                    kept, last = [], 0
                    for a, b in spans:
                        kept += words[last:a]
                        last = b
                    words = kept + words[last:]
                n_removed.append(sum(b - a for a, b in spans))
                texts.append(None if text is None else b" ".join(words).decode())
                removed.append([{"start": a, "end": b} for a, b in spans])
            cols = [batch.column(c) if c != text_col else pa.array(texts, pa.string()) for c in names]
            cols += [pa.array(n_words, pa.int64()), pa.array(n_removed, pa.int64()), pa.array(removed, schema.field("removed").type)]
            yield pa.RecordBatch.from_arrays([c.cast(f.type) for c, f in zip(cols, schema, strict=True)], schema=schema)

    return tidy(run)


def substring_dedup(docs: DataFrame, window: int = 50, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``docs`` with every word taken out that lies in a window whose words also start anywhere else.

    Adds ``n_words``, ``n_removed`` and ``removed`` (maximal intervals of words, end exclusive) and
    replaces the text by its kept words, joined by a space. Windows are judged on the input. A null
    text stays null and counts no words; texts shorter than the window lose nothing; repeated rows
    repeat each other's windows and so lose them. Other columns pass through; one that has a name
    of the added columns is dropped. An empty table gives an empty result.
    """
    from pyspark.sql.pandas.types import to_arrow_schema

    names = [c for c in docs.columns if c not in ("n_words", "n_removed", "removed")]
    rows = docs.select(*names, F.xxhash64(id_col, text_col).alias("__rid"), F.col(text_col).cast("string").alias("__text"))
    found = repeated_windows(rows.select(F.col("__rid").alias("rid"), F.col("__text").alias("text")), window)
    joined = rows.join(found.select(F.col("rid").alias("__rid"), F.col("places").alias("__places")).hint("shuffle_hash"), "__rid", "left")
    spans = T.ArrayType(T.StructType([T.StructField("start", T.LongType()), T.StructField("end", T.LongType())]))
    schema = T.StructType([T.StructField(f.name, T.StringType() if f.name == text_col else f.dataType) for f in docs.schema if f.name in names] + [T.StructField("n_words", T.LongType()), T.StructField("n_removed", T.LongType()), T.StructField("removed", spans)])
    return joined.select(*(F.col(c) for c in names if c != text_col), "__text", "__places").mapInArrow(_cut(window, text_col, names, to_arrow_schema(schema)), schema)
