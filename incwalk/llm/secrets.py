"""Secret scans through a ledger of blobs.

Texts are content-addressed; the ledger remembers which blob was scanned under which version of the
rules, and what was found. A run scans each blob that the ledger does not have under this version
once, whatever number of paths or versions hold it, and joins findings back to all of them.
"""

from __future__ import annotations

import math
import re
from collections import Counter

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from incwalk.llm.common import save, tidy

RULES_VERSION = 1
# The base patterns and least lengths, in the order of kinds. Cases fold in ASCII alone, so that no look-alike swallows a match.
ASSIGN = re.compile(r"""((?ai:password|passwd|secret|token|api_?key))["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""")
ACCESS = re.compile(r"AKIA[A-Z0-9]+")
HEX = re.compile(r"[0-9a-f]{16,}")  # the same as runs of any length that are 16 long at least
BASE_KINDS = ("assign", "access", "hex")
#: Kinds that the method adds: private key blocks, signed web tokens, bearer credentials of high entropy.
KEY_BLOCK = re.compile(r"-----BEGIN [A-Z ]*PRIVATE KEY-----.*?-----END [A-Z ]*PRIVATE KEY-----", re.S)
WEB_TOKEN = re.compile(r"\beyJ[A-Za-z0-9_-]{8,}\.[A-Za-z0-9_-]{8,}\.[A-Za-z0-9_-]{8,}")
BEARER = re.compile(r"\b[Bb]earer\x20+([A-Za-z0-9+/_.=-]{20,})")
KINDS = BASE_KINDS + ("keyblock", "webtoken", "bearer")
_WORDS = ("password", "passwd", "secret", "token", "apikey", "api_key")


def entropy(s: str) -> float:
    n = len(s)
    return -sum(c / n * math.log2(c / n) for c in Counter(s).values())


def scan(text: str) -> list[tuple[int, int, str]]:
    """``(start, end, kind)`` in code points, by start, then by kind as listed."""
    out = []
    low = text.lower()
    if any(w in low for w in _WORDS) or "ſ" in text or "K" in text:
        out += [(m.start(), m.end(), 0) for m in ASSIGN.finditer(text) if len(m[2]) >= 12 and m[1].isascii()]
    if "AKIA" in text:
        out += [(m.start(), m.end(), 1) for m in ACCESS.finditer(text) if m.end() - m.start() >= 18]
    out += [(m.start(), m.end(), 2) for m in HEX.finditer(text)]
    if "-----BEGIN" in text:
        out += [(m.start(), m.end(), 3) for m in KEY_BLOCK.finditer(text)]
    if "eyJ" in text:
        out += [(m.start(), m.end(), 4) for m in WEB_TOKEN.finditer(text)]
    if "earer" in text:
        out += [(m.start(), m.end(), 5) for m in BEARER.finditer(text) if entropy(m[1]) >= 3.5]
    return [(a, b, KINDS[k]) for a, b, k in sorted(out, key=lambda x: (x[0], x[2], x[1]))]


LEDGER = "blob string, rules int, n_assign long, n_access long, n_hex long, base_spans string, spans string"
_LEDGER = pa.schema([("blob", pa.string()), ("rules", pa.int32()), ("n_assign", pa.int64()), ("n_access", pa.int64()), ("n_hex", pa.int64()), ("base_spans", pa.string()), ("spans", pa.string())])


def _scan_blobs(batches):
    for batch in batches:
        cols: dict[str, list] = {c: [] for c in _LEDGER.names}
        for blob, text in zip(batch.column("blob").to_pylist(), batch.column("text"), strict=True):
            found = scan(text.as_py())
            n = Counter(k for _, _, k in found)
            said = [f"{k}:{a}:{b}" for a, b, k in found]
            base = [s for s, f in zip(said, found, strict=True) if f[2] in BASE_KINDS]
            for c, v in zip(_LEDGER.names, (blob, RULES_VERSION, n["assign"], n["access"], n["hex"], ",".join(base), ",".join(said)), strict=True):
                cols[c].append(v)
        yield pa.RecordBatch.from_pydict(cols, schema=_LEDGER)


def address(text) -> F.Column:
    return F.sha2(F.encode(text, "UTF-8"), 256)


def scan_unseen(versions: DataFrame, ledger: DataFrame | None, key: str = "path", text_col: str = "text") -> tuple[DataFrame, DataFrame]:
    """``(paths, found)``: every row's key and blob, and new ledger rows for blobs that ``ledger`` lacks under these rules.

    ``versions`` holds every historical version of every path as a row. The text of one row for each
    unseen blob moves, and no other. Null texts count as empty.
    """
    text = F.coalesce(F.col(text_col).cast("string"), F.lit(""))
    paths = versions.select(F.col(key).alias("key"), address(text).alias("blob"))
    one = paths.groupBy("blob").agg(F.min(F.struct(F.col("key").isNull(), F.col("key")))["key"].alias("key"))
    if ledger is not None:
        one = one.join(ledger.where(F.col("rules") == RULES_VERSION).select("blob"), "blob", "left_anti")
    # the key alone goes through the join; a blob that shares the key of another is told apart by its address
    rows = versions.select(F.coalesce(F.col(key).cast("string"), F.lit("\0")).alias("k"), address(text).alias("blob"), text.alias("text"))
    one = one.select(F.coalesce(F.col("key").cast("string"), F.lit("\0")).alias("k"), "blob")
    fresh = rows.join(one.hint("shuffle_hash"), ["k", "blob"], "left_semi")
    return paths, fresh.select("blob", "text").mapInArrow(tidy(_scan_blobs), LEDGER)


def secret_findings(versions: DataFrame, ledger: DataFrame | None = None, key: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row for each row of ``versions``: its key, counts by base kind, ``base_spans`` and ``spans``.

    Texts that are null or empty have no findings; repeated rows and equal texts get the same ones;
    a null key gives a row. Other columns are not read. An empty table gives an empty result.
    """
    paths, found = scan_unseen(versions, ledger, key, text_col)
    found = save(found.dropDuplicates(["blob"]), "ledger")
    every = found if ledger is None else found.unionByName(ledger.where(F.col("rules") == RULES_VERSION)).dropDuplicates(["blob"])
    return paths.join(every, "blob", "left").select(F.col("key").alias(key), "blob", *(F.coalesce(c, F.lit(0)).alias(c) for c in ("n_assign", "n_access", "n_hex")), *(F.coalesce(c, F.lit("")).alias(c) for c in ("base_spans", "spans")))


def redact(docs: DataFrame, text_col: str = "text", mark: str = "[secret]", ledger: DataFrame | None = None, id_col: str = "doc_id") -> DataFrame:
    """``docs`` with every found span replaced by ``mark``; all rows and columns stay. Overlapping spans become one mark."""
    from pyspark.sql.pandas.types import to_arrow_schema

    schema = docs.schema
    arrow = to_arrow_schema(schema)

    def run(batches):
        for batch in batches:
            texts = []
            for text, spans in zip(batch.column(text_col), batch.column("__spans").to_pylist(), strict=True):
                text = text.as_py()
                if spans:
                    out, last = [], 0
                    for s in spans.split(","):
                        _, a, b = s.split(":")
                        a, b = int(a), int(b)
                        if a >= last:
                            out += [text[last:a], mark]
                        last = max(last, b)
                    text = "".join(out) + text[last:]
                texts.append(text)
            cols = [batch.column(c) if c != text_col else pa.array(texts, pa.string()) for c in arrow.names]
            yield pa.RecordBatch.from_arrays([c.cast(f.type) for c, f in zip(cols, arrow, strict=True)], schema=arrow)

    found = secret_findings(docs.select(id_col, text_col), ledger, id_col, text_col).where("spans <> ''").select(F.col("blob").alias("__blob"), F.col("spans").alias("__spans")).distinct()
    rows = docs.withColumn("__blob", address(F.coalesce(F.col(text_col), F.lit(""))))
    return rows.join(found, "__blob", "left").select(*docs.columns, "__spans").mapInArrow(tidy(run), schema)
