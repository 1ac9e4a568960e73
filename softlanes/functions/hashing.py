"""Reproducible randomness: 32 bits of an MD5 digest, the same in Spark and in any SQL engine."""

from __future__ import annotations

import hashlib
from math import sin

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F

SPAN = float(1 << 32)


def hash_uniform(*parts) -> Column:
    """Uniform on [0, 1) from the parts joined by '-'; parts are columns or plain values."""
    columns = [p if isinstance(p, Column) else F.lit(p) for p in parts]
    text = F.concat_ws("-", *[c.cast("string") for c in columns])
    return F.conv(F.substring(F.md5(text), 1, 8), 16, 10).cast("double") / SPAN


def hash_uniform_sql(*parts: str) -> str:
    """DuckDB text of ``hash_uniform``; parts are SQL expressions."""
    return f"(('0x' || substr(md5(concat_ws('-', {', '.join(parts)})), 1, 8))::BIGINT / 4294967296.0)"


def hash_uniform_value(*parts) -> float:
    """The same on the driver."""
    return int(hashlib.md5("-".join(map(str, parts)).encode()).hexdigest()[:8], 16) / SPAN


_SINES = [int(abs(sin(t + 1)) * 2**32) for t in range(64)]
_TURNS = [(7, 12, 17, 22), (5, 9, 14, 20), (4, 11, 16, 23), (6, 10, 15, 21)]
_WORDS = [lambda t: t, lambda t: (5 * t + 1) % 16, lambda t: (3 * t + 5) % 16, lambda t: 7 * t % 16]
_INITIAL = 0x67452301, 0xEFCDAB89, 0x98BADCFE, 0x10325476


def first_bits(starts: np.ndarray, end: bytes) -> np.ndarray:
    """The first 32 bits of the MD5 digests of many texts at once: each row of bytes of ``starts``, followed by ``end``."""
    n, size = starts.shape
    length = size + len(end)
    if length > 55:  # more than a block
        return np.array([int.from_bytes(hashlib.md5(row.tobytes() + end).digest()[:4], "big") for row in starts], np.uint32)
    varying = -(-size // 4)
    tail = end + b"\x80" + bytes(55 - length) + (8 * length).to_bytes(8, "little")
    block = np.empty((n, 4 * varying), np.uint8)
    block[:, :size], block[:, size:] = starts, np.frombuffer(tail[: 4 * varying - size], np.uint8)
    words = list(np.ascontiguousarray(block.view("<u4").T)) + np.frombuffer(tail[4 * varying - size :], "<u4").tolist()
    a, b, c, d = (np.full(n, x, np.uint32) for x in _INITIAL)
    f, g = np.empty(n, np.uint32), np.empty(n, np.uint32)
    for t in range(64):
        kind = t // 16
        if kind == 0:
            np.bitwise_and(np.bitwise_xor(c, d, out=f), b, out=f)
            np.bitwise_xor(f, d, out=f)
        elif kind == 1:
            np.bitwise_and(np.bitwise_xor(b, c, out=f), d, out=f)
            np.bitwise_xor(f, c, out=f)
        elif kind == 2:
            np.bitwise_xor(np.bitwise_xor(b, c, out=f), d, out=f)
        else:
            np.bitwise_or(np.invert(d, out=f), b, out=f)
            np.bitwise_xor(f, c, out=f)
        word, turn = words[_WORDS[kind](t)], _TURNS[kind][t % 4]
        a += f
        if isinstance(word, int):
            a += np.uint32((word + _SINES[t]) % 2**32)
        else:
            a += word
            a += np.uint32(_SINES[t])
        np.right_shift(a, np.uint32(32 - turn), out=g)
        np.left_shift(a, np.uint32(turn), out=a)
        a |= g
        a += b
        a, b, c, d = d, a, b, c
    a += np.uint32(_INITIAL[0])
    return a.astype("<u4").view(">u4").astype(np.uint32)
