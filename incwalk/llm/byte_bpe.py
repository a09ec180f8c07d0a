"""Byte-level BPE: encoding by ranked merges and decoding by concatenating the ids' byte strings.

``encode_words`` is the native form: Spark higher-order functions fold the merges over the byte
array of each distinct word, with the ranks as one literal map, kept in buckets by CRC since Spark
searches a map from its start. It suits vocabularies and word tables. ``encode_documents`` folds
the same merges in an Arrow function, over the distinct words that a worker meets: a document's ids
must come back in the order of its words, and a join of every occurrence with a table of encoded
words would shuffle some 15 bytes for each word of the corpus (README has the figures).
"""

from __future__ import annotations

import base64
import heapq
import json
import zlib

import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from incwalk.llm.common import LONGEST
from incwalk.llm.common import memo as new_memo

MEMO = 400_000
BUCKETS = 4096
_STATE: dict = {}


def load_ranks(path: str) -> dict[bytes, int]:
    with open(path, "rb") as f:
        return {base64.b64decode(a): int(b) for a, b in (line.split() for line in f if line.strip())}


def merge_word(word: bytes, ranks: dict[bytes, int]) -> list[int]:
    """Ids of one word: the adjacent pair of least rank merges, leftmost first, until none has a rank."""
    if word in ranks:
        return [ranks[word]]
    if len(word) > 48:
        return _merge_long(word, ranks)
    parts = [word[i : i + 1] for i in range(len(word))]
    pair = [ranks.get(a + b, 1 << 30) for a, b in zip(parts, parts[1:], strict=False)]
    while pair:
        low = min(pair)
        if low == 1 << 30:
            break
        i = pair.index(low)
        parts[i : i + 2] = [parts[i] + parts[i + 1]]
        del pair[i]
        if i < len(pair):
            pair[i] = ranks.get(parts[i] + parts[i + 1], 1 << 30)
        if i:
            pair[i - 1] = ranks.get(parts[i - 1] + parts[i], 1 << 30)
    return [ranks[p] for p in parts]


def _merge_long(word: bytes, ranks: dict[bytes, int]) -> list[int]:
    """The same by a heap over linked parts: n log n for words of any length."""
    n = len(word)
    part = [word[i : i + 1] for i in range(n)]
    after, before = list(range(1, n + 1)), list(range(-1, n - 1))
    heap = [(r, i, 2) for i in range(n - 1) if (r := ranks.get(word[i : i + 2])) is not None]
    heapq.heapify(heap)
    while heap:
        _, i, size = heapq.heappop(heap)
        j = after[i]
        if part[i] is None or j >= n or len(part[i]) + len(part[j]) != size or part[i] + part[j] not in ranks:
            continue
        part[i] += part[j]
        part[j] = None
        after[i] = k = after[j]
        if k < n:
            before[k] = i
            if (r := ranks.get(part[i] + part[k])) is not None:
                heapq.heappush(heap, (r, i, len(part[i]) + len(part[k])))
        if (h := before[i]) >= 0 and (r := ranks.get(part[h] + part[i])) is not None:
            heapq.heappush(heap, (r, h, len(part[h]) + len(part[i])))
    return [ranks[p] for p in part if p is not None]


def _coder(path: str, pattern: str):
    if (path, pattern) not in _STATE:
        import regex

        ranks = load_ranks(path)
        _STATE[path, pattern] = (regex.compile(pattern), ranks, {b: a for a, b in ranks.items()}, new_memo())
    return _STATE[path, pattern]


def encode_documents(docs: DataFrame, ranks_path: str, pattern: str, id_col: str = "doc_id", text_col: str = "text", with_ids: bool = True) -> DataFrame:
    """``doc_id``, ``n_tokens``, ``ids_text`` (decimal ids joined by a space), ``decoded`` and, if asked for, ``ids``.

    Each match of ``pattern`` is encoded on its own, without special tokens. A null text counts as
    empty: no ids. Repeated rows and null ids give a row each; other columns are not read.
    """
    fields = [("doc_id", pa.int64()), ("n_tokens", pa.int64()), ("ids_text", pa.string()), ("decoded", pa.binary())] + [("ids", pa.list_(pa.int32()))] * with_ids
    schema = pa.schema(fields)

    def run(batches):
        words_of, ranks, bytes_of, memo = _coder(ranks_path, pattern)
        for batch in batches:
            texts = batch.column("text").to_pylist()
            doc_ids = batch.column("doc_id").to_pylist()
            out: list[tuple] = []
            held = 0
            for doc_id, text in zip(doc_ids, texts, strict=True):
                words = words_of.findall(text) if text else []
                if len(memo) > MEMO:
                    memo.clear()
                long = {}  # not kept
                for w in set(words):
                    if w not in memo:
                        ids = merge_word(w.encode(), ranks)
                        (memo if len(w) <= LONGEST else long)[w] = (" ".join(map(str, ids)), b"".join([bytes_of[i] for i in ids]))
                got = [memo[w] for w in words] if not long else [long[w] if w in long else memo[w] for w in words]
                said = " ".join([g[0] for g in got])
                out.append((doc_id, said.count(" ") + 1 if said else 0, said, b"".join([g[1] for g in got])) + ((list(map(int, said.split())),) if with_ids else ()))
                held += len(said)
                if held > 8 << 20:
                    yield pa.RecordBatch.from_arrays([pa.array([o[i] for o in out], f.type) for i, f in enumerate(schema)], schema=schema)
                    out, held = [], 0
            if out:
                yield pa.RecordBatch.from_arrays([pa.array([o[i] for o in out], f.type) for i, f in enumerate(schema)], schema=schema)

    rows = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text"))
    return rows.mapInArrow(run, "doc_id long, n_tokens long, ids_text string, decoded binary" + ", ids array<int>" * with_ids)


def rank_literal(ranks: dict[bytes, int]) -> Column:
    """The ranks as one literal: an array of maps, keyed by the CRC's remainder; keys have a character for each byte."""
    buckets: list[dict[str, int]] = [{} for _ in range(BUCKETS)]
    for token, rank in ranks.items():
        buckets[zlib.crc32(token) % BUCKETS][token.decode("latin-1")] = rank
    return F.from_json(F.lit(json.dumps(buckets)), "array<map<string,int>>")


def encode_words(words: DataFrame, ranks: dict[bytes, int], word_col: str = "word") -> DataFrame:
    """Distinct words with ``ids`` array<int>, by higher-order functions alone. Null words are left out."""
    table = rank_literal(ranks)

    def rank_of(key: Column) -> Column:
        bucket = F.element_at(table, (F.crc32(F.encode(key, "ISO-8859-1")) % BUCKETS + 1).cast("int"))
        return F.coalesce(F.element_at(bucket, key), F.lit(1 << 30))

    def merge(parts: Column, _: Column) -> Column:
        pair = F.when(F.size(parts) > 1, F.transform(F.sequence(F.lit(1), F.size(parts) - 1), lambda i: rank_of(F.concat(F.element_at(parts, i), F.element_at(parts, i + 1))))).otherwise(F.array().cast("array<int>"))
        low = F.array_min(pair)
        at = F.array_position(pair, low).cast("int")
        merged = F.concat(F.slice(parts, F.lit(1), at - 1), F.array(F.concat(F.element_at(parts, at), F.element_at(parts, at + 1))), F.slice(parts, at + 2, F.size(parts)))
        return F.when(low < F.lit(1 << 30), merged).otherwise(parts)

    distinct = words.where(F.col(word_col).isNotNull() & (F.col(word_col) != "")).select(F.col(word_col).alias("word")).distinct()
    chars = F.decode(F.encode("word", "UTF-8"), "ISO-8859-1")
    parts = F.transform(F.sequence(F.lit(1), F.length(chars)), lambda i: F.substring(chars, i, F.lit(1)))
    folded = F.aggregate(F.sequence(F.lit(1), F.octet_length("word")), parts, merge)
    return distinct.select("word", F.transform(folded, rank_of).alias("ids"))


def decode_ids(rows: DataFrame, ranks: dict[bytes, int], ids_col: str = "ids") -> DataFrame:
    """Adds ``decoded`` binary: the pieces of the ids, looked up in a literal array and concatenated. Unknown ids give null."""
    top = max(ranks.values())
    by_rank = {v: k for k, v in ranks.items()}
    pieces = F.from_json(F.lit(json.dumps([by_rank[i].hex() if i in by_rank else None for i in range(top + 1)])), "array<string>")
    return rows.withColumn("decoded", F.unhex(F.concat_ws("", F.transform(ids_col, lambda i: F.coalesce(F.element_at(pieces, i + 1), F.lit("?"))))))
