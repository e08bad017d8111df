"""Seeded uniform numbers from stable keys; the same everywhere, on every retry and in SQL."""

from __future__ import annotations

import hashlib
import math

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F


_TURNS = [t for four in ((7, 12, 17, 22), (5, 9, 14, 20), (4, 11, 16, 23), (6, 10, 15, 21)) for t in four * 4]
_SINES = [np.uint32(int(abs(math.sin(i + 1)) * 2**32)) for i in range(64)]
_WORDS = [(i, 5 * i + 1, 3 * i + 5, 7 * i)[i // 16] % 16 for i in range(64)]


def md5_heads(texts: list[bytes], at_once: int = 4096) -> np.ndarray:
    """The first 32 bits of each text's md5, many texts at once; those of over 55 bytes by themselves."""
    out = np.empty(len(texts), dtype=np.uint32)
    for start in range(0, len(texts), at_once):
        given = texts[start : start + at_once]
        n, sizes = len(given), np.fromiter(map(len, given), dtype=np.int64, count=len(given))
        block = np.zeros((16, n), dtype="<u4")
        block[:14] = np.array(given, dtype="S56").view("<u4").reshape(n, 14).T
        few = np.minimum(sizes, 55)
        block[few >> 2, np.arange(n)] |= np.uint32(0x80) << (8 * (few & 3)).astype(np.uint32)
        block[14] = 8 * sizes
        a, b, c, d = (np.full(n, v, dtype=np.uint32) for v in (0x67452301, 0xEFCDAB89, 0x98BADCFE, 0x10325476))
        f, g = np.empty(n, dtype=np.uint32), np.empty(n, dtype=np.uint32)
        for i in range(64):
            if i < 32:  # the bits of the first where the mask is set, of the second elsewhere
                first, second, mask = (c, d, b) if i < 16 else (b, c, d)
                np.bitwise_xor(first, second, out=f)
                f &= mask
                f ^= second
            elif i < 48:
                np.bitwise_xor(b, c, out=f)
                f ^= d
            else:
                np.invert(d, out=f)
                f |= b
                f ^= c
            f += a
            f += _SINES[i]
            f += block[_WORDS[i]]
            np.right_shift(f, np.uint32(32 - _TURNS[i]), out=g)
            f <<= np.uint32(_TURNS[i])
            f |= g
            f += b
            a, b, c, d, f = d, f, b, c, a
        a = (a + np.uint32(0x67452301)).byteswap()
        for i in np.flatnonzero(sizes > 55):
            a[i] = int(hashlib.md5(given[i]).hexdigest()[:8], 16)
        out[start : start + n] = a
    return out


def md5_int(text: Column) -> Column:
    return F.conv(F.substring(F.md5(text), 1, 8), 16, 10).cast("bigint")


def uniform(key: Column, seed: int | str) -> Column:
    """In [0, 1): the first 32 bits of md5(seed:key)."""
    return md5_int(F.concat(F.lit(f"{seed}:"), key.cast("string"))) / F.lit(4294967296.0)


def below(key: Column, seed: int | str, rate: float) -> Column:
    """``uniform(key, seed) < rate`` by the digits themselves, which costs less for each row."""
    bar = math.ceil(min(max(rate, 0.0), 1.0) * 4294967296)
    return F.when(key.isNotNull(), True) if bar == 4294967296 else F.substring(F.md5(F.concat(F.lit(f"{seed}:"), key.cast("string"))), 1, 8) < F.lit(f"{bar:08x}")


def uniform_sql(key: str, seed: int | str) -> str:
    """The same in DuckDB."""
    return f"(('0x' || substr(md5('{seed}:' || {key}::VARCHAR), 1, 8))::BIGINT / 4294967296.0::DOUBLE)"
