"""Token counts of whole texts: lengths only, batches balanced by bytes, texts cut at safe boundaries.

A boundary is safe where the tokenizer cannot merge across it, so that the pieces' counts add up to
the text's. Pieces repeat: a worker keeps the counts of the short ones it has met, up to ``MEMO`` of
them, and encodes the others in batches of about ``BATCH`` bytes.
"""

from __future__ import annotations

import os
import re

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from incwalk.llm.common import LONGEST, memo

BATCH = 1 << 20
MEMO = 500_000
_RUN = re.compile(r" *[^ ]+")
_STATE: dict = {}


def byte_length(text: str) -> int:
    return len(text) if text.isascii() else len(text.encode())


def balanced(items, size=BATCH):
    """Lists of strings of about ``size`` bytes each; a longer string is alone."""
    out, held = [], 0
    for x in items:
        n = byte_length(x)
        if out and held + n > size:
            yield out
            out, held = [], 0
        out.append(x)
        held += n
    if out:
        yield out


class PieceCounter:
    """sentencepiece models whose pieces hold the space mark only in front: cut before every run of spaces.

    The library puts one mark before what it encodes, which stands for the last space of the run.
    """

    def __init__(self, path: str):
        import sentencepiece

        self.model = sentencepiece.SentencePieceProcessor(model_file=path)
        mark = "▁"
        self.safe = not any(mark in p.lstrip(mark) for p in map(self.model.id_to_piece, range(self.model.get_piece_size())))

    def pieces(self, text: str) -> list[str]:
        if not self.safe or not text.strip(" "):
            return [text] if text else []
        if "  " not in text and text[0] != " " and text[-1] != " ":
            return text.split(" ")
        runs = _RUN.findall(text)
        runs[-1] += " " * (len(text) - len(text.rstrip(" ")))
        return [runs[0]] + [r[1:] for r in runs[1:]]

    def count(self, pieces: list[str]) -> list[int]:
        return [len(x) for x in self.model.encode(pieces, num_threads=1)]


class JsonCounter:
    """tokenizers files: cut at white space where the pre-tokenizer drops it, else whole texts."""

    def __init__(self, path: str):
        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        from tokenizers import Tokenizer

        self.model = Tokenizer.from_file(path)
        self.model.no_truncation()
        self.model.no_padding()
        self.safe = len(self.model.encode("a b", add_special_tokens=False).ids) == len(self.model.encode("a \n\t b", add_special_tokens=False).ids)

    def pieces(self, text: str) -> list[str]:
        return [w.decode() for w in text.encode().split()] if self.safe else [text] if text else []

    def count(self, pieces: list[str]) -> list[int]:
        return [len(x.ids) for x in self.model.encode_batch(pieces, add_special_tokens=False)]


def _counter(path: str):
    if path not in _STATE:
        _STATE[path] = (PieceCounter(path) if path.endswith(".model") else JsonCounter(path), memo())
    return _STATE[path]


def count_texts(path: str, texts: list[str]) -> list[int]:
    counter, known = _counter(path)
    if len(known) > MEMO:
        known.clear()
    cut = [counter.pieces(t) for t in texts]
    fresh = {p for pieces in cut for p in pieces if p not in known}
    long = {p: 0 for p in fresh if len(p) > LONGEST}  # counted, and not kept
    for batch in balanced(fresh):
        for p, n in zip(batch, counter.count(batch), strict=True):
            (long if p in long else known)[p] = n
    if not long:
        get = known.__getitem__
        return [sum(map(get, pieces)) for pieces in cut]
    return [sum(known[p] if p in known else long[p] for p in pieces) for pieces in cut]


def _by_bytes(sizes, size=4 << 20):
    """Slices of a batch of about ``size`` bytes; a longer text is alone."""
    at, held = 0, 0
    for i, n in enumerate(sizes):
        if i > at and held + n > size:
            yield at, i
            at, held = i, 0
        held += n
    if at < len(sizes):
        yield at, len(sizes)


def token_counts(docs: DataFrame, tokenizer_path: str, limit: int = 4096, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``doc_id``, ``n_bytes`` (UTF-8), ``n_tokens`` and ``over_limit`` of every row.

    ``tokenizer_path`` is a ``.json`` of tokenizers or a ``.model`` of sentencepiece; it must be
    readable on every executor. No begin, end or special tokens, no truncation. A null text counts as
    empty: no bytes, no tokens. Repeated rows and null ids give a row each; other columns are not read.
    """
    schema = pa.schema([("doc_id", pa.int64()), ("n_bytes", pa.int64()), ("n_tokens", pa.int64()), ("over_limit", pa.bool_())])

    def run(batches):
        for batch in batches:
            texts = [t or "" for t in batch.column("text").to_pylist()]
            n = [x for a, b in _by_bytes(batch.column("n_bytes").to_pylist()) for x in count_texts(tokenizer_path, texts[a:b])]
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), batch.column("n_bytes"), pa.array(n, pa.int64()), pa.array([x > limit for x in n], pa.bool_())], schema=schema)

    text = F.coalesce(F.col(text_col).cast("string"), F.lit(""))
    rows = docs.select(F.col(id_col).cast("long").alias("doc_id"), text.alias("text"), F.octet_length(text).cast("long").alias("n_bytes"))
    return rows.mapInArrow(run, "doc_id long, n_bytes long, n_tokens long, over_limit boolean")
