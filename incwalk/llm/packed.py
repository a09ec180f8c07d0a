"""Counting of very many hashed keys through a packed exchange.

Counting every n-gram or window of a corpus as Spark rows costs some 25 bytes a key in the
shuffle, twice if the documents have to learn the counts. Here a task packs its entries
``(key, document, position)`` into one binary row for each key range, so that an entry takes 8 to
14 bytes; the range's reducer counts the keys and answers only those that occur at least twice, in
rows packed by document. Counts are exact up to ``cap`` and say ``cap`` beyond it. A key that
reaches ``cap`` inside one buffer is answered on the spot and only its count travels; a reducer
that has seen ``cap`` entries of a key answers them and keeps one marker. So no key, however hot,
gathers in one place, and memory is bounded by the distinct keys of a range.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from incwalk.llm.common import forget, planes, tidy, unplanes

SCHEMA = "part int, kind int, rid binary, run binary, key binary, aux binary, pos binary, lvl binary"
ARROW = pa.schema([("part", pa.int32()), ("kind", pa.int32())] + [(c, pa.binary()) for c in ("rid", "run", "key", "aux", "pos", "lvl")])
ENTRY, MARKER, HIT, HEAD = 0, 1, 2, 3
#: Entries held by a task before it packs them or compacts them.
BUFFER = 1_000_000


def part_of(keys: np.ndarray, parts: int) -> np.ndarray:
    return ((keys >> np.uint64(32)) * np.uint64(parts) >> np.uint64(32)).astype(np.int32)


def _runs(x: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Starts and lengths of runs of equal neighbours."""
    if not len(x):
        return np.zeros(0, np.int64), np.zeros(0, np.int64)
    at = np.flatnonzero(np.r_[True, x[1:] != x[:-1]])
    return at, np.diff(np.r_[at, len(x)])


def _row(part: int, kind: int, rid, key, aux, pos, lvl) -> tuple:
    """rid: a run of equal values is kept once, sorted ones as differences."""
    at, run = _runs(rid)
    ids = rid[at].astype(np.uint64)
    return (int(part), kind, planes(np.diff(ids, prepend=np.uint64(0))), planes(run.astype(np.uint32)), planes(key, 6), planes(aux) if aux is not None else None, planes(pos) if pos is not None else None, planes(lvl) if lvl is not None else None)


def _unrow(r: dict) -> dict:
    ids, run = np.cumsum(unplanes(r["rid"], np.uint64), dtype=np.uint64), unplanes(r["run"], np.uint32)
    return {"rid": np.repeat(ids, run), "key": unplanes(r["key"], np.uint64, 6), "aux": unplanes(r["aux"], np.uint32) if r["aux"] is not None else None, "pos": unplanes(r["pos"], np.uint32) if r["pos"] is not None else None, "lvl": unplanes(r["lvl"], np.uint16) if r["lvl"] is not None else None}


def _batch(rows: list[tuple]) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array([r[i] for r in rows], f.type) for i, f in enumerate(ARROW)], schema=ARROW)


def _group(key, aux) -> tuple[np.ndarray, np.ndarray]:
    """An order that puts equal keys together, and the group number of each place in it."""
    order = np.argsort(key, kind="stable") if aux is None else np.lexsort((aux, key))
    k = key[order]
    new = np.r_[False, k[1:] != k[:-1]]
    if aux is not None:
        a = aux[order]
        new |= np.r_[False, a[1:] != a[:-1]]
    return order, np.cumsum(new)


class Packer:
    """Map side. ``add`` entries and heads, ``rows`` when there is enough or at the end."""

    def __init__(self, parts: int, doc_parts: int, cap: int, has_aux: bool = False, has_pos: bool = False, has_lvl: bool = False):
        self.parts, self.doc_parts, self.cap = parts, doc_parts, cap
        self.has_aux, self.has_pos, self.has_lvl = has_aux, has_pos, has_lvl
        self.clear()

    def clear(self):
        self.n, self.rid, self.len, self.key, self.aux, self.pos, self.heads = 0, [], [], [], [], [], []

    def add(self, rid: int, key: np.ndarray, aux=None, pos=None):
        """rid: unsigned 64-bit."""
        if len(key):
            self.rid.append(rid)
            self.len.append(len(key))
            self.key.append(key)
            self.aux.append(aux)
            self.pos.append(pos)
            self.n += len(key)

    def head(self, rid: int, data: bytes):
        self.heads.append((rid, data))

    def full(self) -> bool:
        return self.n >= BUFFER or len(self.heads) >= 50_000

    def rows(self) -> Iterator[pa.RecordBatch]:
        if self.n:
            docs = np.array(self.rid, np.uint64)
            by_doc = np.argsort(docs, kind="stable")  # so that a blob holds its documents in ascending order
            n = np.array(self.len)[by_doc]
            rid = np.repeat(docs[by_doc], n)
            key = np.concatenate([self.key[i] for i in by_doc])
            aux = np.concatenate([self.aux[i] for i in by_doc]).astype(np.uint32) if self.has_aux else None
            pos = np.concatenate([self.pos[i] for i in by_doc]).astype(np.uint32) if self.has_pos else None
            part = part_of(key, self.parts)
            low = key & np.uint64((1 << 48) - 1)
            order, group = _group(key, aux)
            count = np.bincount(group)
            hot = np.zeros(len(key), bool)
            hot[order] = count[group] >= self.cap
            if hot.any():
                first = order[np.flatnonzero(np.r_[True, group[1:] != group[:-1]] & (count[group] >= self.cap))]
                full = np.full(len(first), self.cap, np.uint16)
                yield from self._deal(part[first], MARKER, self.parts, np.zeros(len(first), np.uint64), low[first], aux[first] if self.has_aux else None, None, full)
                at = np.flatnonzero(hot)
                yield from hits(rid[at], low[at] | part[at].astype(np.uint64) << np.uint64(48) if not self.has_pos else None, pos[at] if self.has_pos else None, np.full(len(at), self.cap, np.uint16) if self.has_lvl else None, self.doc_parts)
                at = np.flatnonzero(~hot)
                rid, low, part = rid[at], low[at], part[at]
                aux, pos = aux[at] if self.has_aux else None, pos[at] if self.has_pos else None
            yield from self._deal(part, ENTRY, self.parts, rid, low, aux, pos, None)
        by = {}
        for rid, data in self.heads:
            by.setdefault(int(part_of(np.array([rid], np.uint64), self.doc_parts)[0]), []).append((rid, data))
        rows = []
        for p, own in by.items():
            rows.append((p, HEAD, planes(np.array([r for r, _ in own], np.uint64)), None, b"".join(d for _, d in own), None, None, None))
        if rows:
            yield _batch(rows)
        self.clear()

    def _deal(self, part, kind, parts, rid, key, aux, pos, lvl):
        order = np.argsort(part.astype(np.uint16) if parts <= 65536 else part, kind="stable")
        cuts = np.searchsorted(part[order], np.arange(parts + 1))
        rows, held = [], 0
        for p in range(parts):
            at = order[cuts[p] : cuts[p + 1]]
            if len(at):
                rows.append(_row(p, kind, rid[at], key[at], aux[at] if aux is not None else None, pos[at] if pos is not None else None, lvl[at] if lvl is not None else None))
                held += len(at)
                if held > 500_000:
                    yield _batch(rows)
                    rows, held = [], 0
        if rows:
            yield _batch(rows)


def hits(rid, key, pos, lvl, doc_parts: int) -> Iterator[pa.RecordBatch]:
    """Answers, packed by range of documents. A key of 64 bits goes as 48 and, in aux, 16 of them."""
    order = np.argsort(rid, kind="stable")
    rid = rid[order]
    key, pos, lvl = (x[order] if x is not None else None for x in (key, pos, lvl))
    part = part_of(rid, doc_parts)
    at, n = _runs(part)
    rows = []
    for s, m in zip(at, n, strict=True):
        k = key[s : s + m] if key is not None else np.zeros(0, np.uint64)
        rows.append(_row(part[s], HIT, rid[s : s + m], k & np.uint64((1 << 48) - 1), (k >> np.uint64(48)).astype(np.uint32) if key is not None else None, pos[s : s + m] if pos is not None else None, lvl[s : s + m] if lvl is not None else None))
        if len(rows) >= 2000:
            yield _batch(rows)
            rows = []
    if rows:
        yield _batch(rows)


def _rows(batches) -> Iterator[dict]:
    """Rows as dictionaries, one at a time, so that a batch's blobs aren't held twice."""
    forget()
    for batch in batches:
        for i in range(batch.num_rows):
            yield {f.name: batch.column(k)[i].as_py() for k, f in enumerate(ARROW)}


class _Range:
    """Reducer of one range of keys."""

    def __init__(self, part: int, doc_parts: int, cap: int, has_lvl: bool, has_pos: bool):
        self.part, self.doc_parts, self.cap, self.has_lvl, self.has_pos, self.held, self.n, self.base = part, doc_parts, cap, has_lvl, has_pos, [], 0, 0

    def add(self, r: dict):
        x = _unrow(r)
        x["w"] = np.ones(len(x["key"]), np.uint16) if r["kind"] == ENTRY else x["lvl"]
        x["real"] = np.full(len(x["key"]), r["kind"] == ENTRY)
        if self.has_pos and x["pos"] is None:
            x["pos"] = np.zeros(len(x["key"]), np.uint32)
        self.held.append(x)
        self.n += len(x["key"])

    def compact(self, last: bool) -> Iterator[pa.RecordBatch]:
        if not self.held:
            return
        names = ["rid", "key", "w", "real"] + ["aux"] * (self.held[0]["aux"] is not None) + ["pos"] * self.has_pos
        x = {c: np.concatenate([h[c] for h in self.held]) for c in names}
        self.held, self.n = [], 0
        sub = (x["key"] & np.uint64(7)).astype(np.uint8)
        for s in range(8):  # an eighth of the keys at a time: what sorting needs stays small
            at = np.flatnonzero(sub == s)
            if len(at):
                yield from self._settle({c: v[at] for c, v in x.items()}, last)
        self.base = self.n

    def _settle(self, x: dict, last: bool) -> Iterator[pa.RecordBatch]:
        order, group = _group(x["key"], x.get("aux"))
        total = np.minimum(np.bincount(group, weights=x["w"][order]), self.cap).astype(np.uint16)[group]
        x = {c: v[order] for c, v in x.items()}
        out = x["real"] & (total >= (2 if last else self.cap))
        if out.any():
            key = None if "pos" in x else x["key"][out] | np.uint64(self.part & 0xFFFF) << np.uint64(48)
            yield from hits(x["rid"][out], key, x["pos"][out] if "pos" in x else None, total[out] if self.has_lvl else None, self.doc_parts)
        if not last:
            first = np.r_[True, group[1:] != group[:-1]]
            stay = (total < self.cap) | first  # of a full group, one marker
            x["real"] &= total < self.cap
            x["w"] = np.where(total < self.cap, x["w"], self.cap).astype(np.uint16)
            self.held.append({c: None for c in ("aux", "pos")} | {c: v[stay] for c, v in x.items()})
            self.n += int(stay.sum())


def count_ranges(cap: int, doc_parts: int, has_lvl: bool, has_pos: bool) -> Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]:
    """Reducer over rows that come sorted by ``part``; answers and heads leave it by range of documents."""

    def run(batches):
        own: dict[str, _Range | None] = {"now": None}
        passing = []
        for r in _rows(batches):
            if r["kind"] in (HIT, HEAD):
                passing.append(tuple(r[f.name] for f in ARROW))
                if len(passing) >= 256:
                    yield _batch(passing)
                    passing = []
                continue
            now = own["now"]
            if now is None or now.part != r["part"]:
                if now is not None:
                    yield from now.compact(True)
                now = own["now"] = _Range(r["part"], doc_parts, cap, has_lvl, has_pos)
            now.add(r)
            if now.n - now.base > BUFFER:
                yield from now.compact(False)
        if own["now"] is not None:
            yield from own["now"].compact(True)
        if passing:
            yield _batch(passing)

    return tidy(run)


def by_document(finish: Callable[[np.ndarray, list[bytes], dict], Iterator[pa.RecordBatch]], head_bytes: int):
    """Second reducer: gives ``finish`` a whole range of documents: head ids, heads, and the answers sorted by id."""

    def run(batches):
        part, heads, data, found = None, [], [], []

        def close():
            ids = np.concatenate(heads) if heads else np.zeros(0, np.uint64)
            if found:
                x = {c: np.concatenate([f[c] for f in found]) for c in ("rid", "key", "aux", "pos", "lvl") if found[0][c] is not None and (c != "key" or found[0]["pos"] is None)}
                order = np.argsort(x["rid"], kind="stable")
                x = {c: v[order] for c, v in x.items()}
                if "key" in x:
                    x["key"] = x["key"] | x.pop("aux").astype(np.uint64) << np.uint64(48)
            else:
                x = {"rid": np.zeros(0, np.uint64)}
            return finish(ids, data, x)

        for r in _rows(batches):
            if r["part"] != part:
                if part is not None:
                    yield from close()
                part, heads, data, found = r["part"], [], [], []
            if r["kind"] == HEAD:
                heads.append(unplanes(r["rid"], np.uint64))
                data += [r["key"][i : i + head_bytes] for i in range(0, len(r["key"]), head_bytes)] if head_bytes else []
            else:
                found.append(_unrow(r))
        if part is not None:
            yield from close()

    return tidy(run)


def exchange(df: DataFrame) -> DataFrame:
    return df.repartition("part").sortWithinPartitions("part")
