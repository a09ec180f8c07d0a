"""Coins: random numbers as functions of keys.

A step of a walk is decided by ``(seed, tag, walk, epoch, position)``, so retried tasks, other
partitionings and other engines take the same walk. The portable coin is two 32-bit numbers out of
an MD5 digest, which SQL engines share; the fast one is XXH64, for production runs.
"""

from __future__ import annotations

import hashlib

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F

FULL = 1 << 32


def threshold(eps: float) -> int:
    return int(eps * FULL)


def digest(seed: int, tag: str, walk, epoch, pos) -> Column:
    return F.md5(F.concat_ws("|", F.lit(str(seed)), F.lit(tag), *(c.cast("string") if isinstance(c, Column) else F.lit(str(c)) for c in (walk, epoch, pos))))


def portable(h: Column) -> tuple[Column, Column]:
    return F.conv(F.substring(h, 1, 8), 16, 10).cast("long"), F.conv(F.substring(h, 9, 8), 16, 10).cast("long")


def fast(seed: int, tag: str, walk, epoch, pos) -> tuple[Column, Column]:
    h = F.xxhash64(F.lit(seed), F.lit(tag), walk, epoch if isinstance(epoch, Column) else F.lit(epoch), pos if isinstance(pos, Column) else F.lit(pos))
    return F.shiftrightunsigned(h, 32), h.bitwiseAND(F.lit(FULL - 1))


def coin(seed: int, tag: str, walk, epoch, pos, kind: str = "portable") -> tuple[Column, Column]:
    return fast(seed, tag, walk, epoch, pos) if kind == "fast" else portable(digest(seed, tag, walk, epoch, pos))


def slot(b: Column, degree: Column) -> Column:
    return F.shiftright(b * degree.cast("long"), 32)


def python_coin(seed: int, tag: str, walk: int, epoch: int, pos: int) -> tuple[int, int]:
    h = hashlib.md5(f"{seed}|{tag}|{walk}|{epoch}|{pos}".encode()).digest()
    return int.from_bytes(h[:4], "big"), int.from_bytes(h[4:8], "big")


#: Walks from which on their digests are taken together, and how many together, so that they stay in a core's cache.
MANY, CHUNK = 1024, 16384
_SINES = np.floor(np.abs(np.sin(np.arange(1, 65))) * 2.0**32).astype(np.uint64).astype(np.uint32)
_TURNS = [t for four in ((7, 12, 17, 22), (5, 9, 14, 20), (4, 11, 16, 23), (6, 10, 15, 21)) for t in four * 4]
_WORDS = [(i, 5 * i + 1, 3 * i + 5, 7 * i)[i // 16] % 16 for i in range(64)]
_START = [np.uint32(x) for x in (0x67452301, 0xEFCDAB89, 0x98BADCFE, 0x10325476)]


def _digests(blocks: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """The first two words of the MD5 digests of padded messages: a column each, of 16 words."""
    n = blocks.shape[1]
    a, b, c, d = (np.full(n, x) for x in _START)
    f, t = np.empty(n, np.uint32), np.empty(n, np.uint32)
    filled = [bool(w.any()) for w in blocks]
    for i in range(64):
        if i < 32:
            x, y, z = (b, c, d) if i < 16 else (d, b, c)
            np.bitwise_xor(y, z, out=f)
            np.bitwise_and(f, x, out=f)
            np.bitwise_xor(f, z, out=f)
        elif i < 48:
            np.bitwise_xor(b, c, out=f)
            np.bitwise_xor(f, d, out=f)
        else:
            np.bitwise_not(d, out=f)
            np.bitwise_or(f, b, out=f)
            np.bitwise_xor(f, c, out=f)
        f += a
        f += _SINES[i]
        if filled[_WORDS[i]]:
            f += blocks[_WORDS[i]]
        np.left_shift(f, _TURNS[i], out=t)
        np.right_shift(f, 32 - _TURNS[i], out=f)
        f |= t
        f += b
        a, b, c, d, f = d, f, b, c, a
    return a + _START[0], b + _START[1]


def _bytes(texts: list[str]) -> tuple[np.ndarray, np.ndarray]:
    """ASCII texts as rows of bytes, zeros after their ends, and their lengths."""
    x = np.array(texts, dtype=bytes)
    return x.view(np.uint8).reshape(len(x), x.itemsize), np.char.str_len(x)


def python_coins(seed: int, tag: str, walks: list[str], epoch: int, pos: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Both numbers for many walks, each at its position."""
    head, mid = f"{seed}|{tag}|", f"|{epoch}|"
    if len(walks) >= MANY:
        at, which = np.unique(pos, return_inverse=True)
        tails, tail_size = _bytes([f"{mid}{p}" for p in at.tolist()])
        names, size = _bytes(walks)
        if len(head) + names.shape[1] + tails.shape[1] <= 55:  # one block a message
            return _coins_together(np.frombuffer(head.encode(), np.uint8), names, size, tails, tail_size, which)
    md5 = hashlib.md5
    raw = b"".join(md5(f"{head}{w}{mid}{p}".encode()).digest() for w, p in zip(walks, pos.tolist(), strict=True))
    ab = np.frombuffer(raw, ">u4").reshape(-1, 4)[:, :2].astype(np.int64)
    return ab[:, 0], ab[:, 1]


def _coins_together(head, names, size, tails, tail_size, which) -> tuple[np.ndarray, np.ndarray]:
    a, b = np.empty(len(names), np.int64), np.empty(len(names), np.int64)
    for first in range(0, len(names), CHUNK):
        part = slice(first, first + CHUNK)
        w, ends = which[part], size[part] + len(head)
        rows, text = np.arange(len(w)), np.zeros((len(w), 64), np.uint8)
        text[:, : len(head)] = head
        text[:, len(head) : len(head) + names.shape[1]] = names[part]
        for j in range(tails.shape[1]):
            text[rows, ends + j] = tails[w, j]
        ends = ends + tail_size[w]
        text[rows, ends] = 0x80
        blocks = np.ascontiguousarray(text.view("<u4").T)
        blocks[14] = ends * 8
        a[part], b[part] = (x.astype("<u4").view(">u4") for x in _digests(blocks))
    return a, b


def sql_digest(seed: int, tag: str, walk: str, epoch: str, pos: str) -> str:
    return f"md5('{seed}|{tag}|' || {walk} || '|' || {epoch} || '|' || {pos})"


def sql_a(h: str) -> str:
    return f"('0x' || substr({h}, 1, 8))::BIGINT"


def sql_b(h: str) -> str:
    return f"('0x' || substr({h}, 9, 8))::BIGINT"
