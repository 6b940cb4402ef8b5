"""Uniform numbers from keys: the same for every engine, partitioning and retry; never a generator whose state goes from one key to the next."""

from __future__ import annotations

import hashlib
import os

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F

SPAN = 1 << 48
_GOLDEN, _MASK = 0x9E3779B97F4A7C15, (1 << 64) - 1


def u01(*keys, engine: str = "md5") -> Column:
    """A number in [0, 1) from key columns or constants.

    "md5": the first 12 hex digits of md5(key|key|...), as SQL engines give it too. "xx": xxhash64, about ten times faster.
    """
    cols = [k if isinstance(k, Column) else F.lit(k) for k in keys]
    if engine == "md5":
        text = F.concat_ws("|", *[c.cast("string") for c in cols])
        return F.conv(F.substring(F.md5(text), 1, 12), 16, 10).cast("bigint").cast("double") / float(SPAN)
    if engine == "xx":
        return F.shiftrightunsigned(F.xxhash64(*cols), 16).cast("double") / float(SPAN)
    raise ValueError(f"no engine {engine}")


def u01_sql(*keys: str) -> str:
    """The same as u01(engine="md5"), as DuckDB SQL over expressions."""
    text = " || '|' || ".join(f"CAST({k} AS VARCHAR)" for k in keys)
    return f"(CAST(CAST(('0x' || substr(md5({text}), 1, 12)) AS BIGINT) AS DOUBLE) / {SPAN}.0)"


def mix(x: np.ndarray) -> np.ndarray:
    """Spreads 64 bits."""
    y = x >> np.uint64(30)
    y ^= x
    y *= np.uint64(0xBF58476D1CE4E5B9)
    z = y >> np.uint64(27)
    y ^= z
    y *= np.uint64(0x94D049BB133111EB)
    y ^= np.right_shift(y, np.uint64(31), out=z) if isinstance(z, np.ndarray) else y >> np.uint64(31)
    return y


_XX = [np.uint64(x) for x in (0x9E3779B185EBCA87, 0xC2B2AE3D27D4EB4F, 0x165667B19E3779F9, 0x85EBCA77C2B2AE63, 0x27D4EB2F165667C5)]


def _xx_end(h: np.ndarray, turn: int, factor: np.uint64, more: np.uint64 | None) -> np.ndarray:
    """What xxhash64 ends with: a turn by bits, a factor, and the spreading of bits. Changes h."""
    z = h << np.uint64(turn)
    h >>= np.uint64(64 - turn)
    h |= z
    h *= factor
    if more is not None:
        h += more
    for bits, times in ((33, _XX[1]), (29, _XX[2]), (32, None)):
        h ^= np.right_shift(h, np.uint64(bits), out=z)
        if times is not None:
            h *= times
    return h


def xx_int(before: np.ndarray, x: np.ndarray) -> np.ndarray:
    """Spark's xxhash64 after an INT column, from the hash before it."""
    h = before + (_XX[4] + np.uint64(4))
    h ^= (x.astype(np.uint64) & np.uint64(0xFFFFFFFF)) * _XX[0]
    return _xx_end(h, 23, _XX[1], _XX[2])


def xx_byte(before: np.ndarray, byte: int) -> np.ndarray:
    """The same after a text of one byte."""
    h = before + (_XX[4] + np.uint64(1))
    h ^= np.uint64(byte * int(_XX[4]) & _MASK)
    return _xx_end(h, 11, _XX[0], None)


def keyed(seed: int, ids: np.ndarray, salt: int = 0) -> np.ndarray:
    """64 keyed bits per id."""
    start = np.uint64((seed * 0xD1342543DE82EF95 + salt * _GOLDEN) & _MASK)
    return mix(mix(ids.astype(np.int64).view(np.uint64) * np.uint64(_GOLDEN) + start) + np.uint64(salt & _MASK))


def stream_starts(keys: np.ndarray) -> np.ndarray:
    """States (keys x 4) at which streams of the keys start."""
    begin = np.ones((len(keys), 4), np.uint64)
    begin[:, :3] = mix(keys[:, None] + np.arange(1, 4, dtype=np.uint64) * np.uint64(_GOLDEN))
    return begin


class Stream:
    """Many 64-bit words of one key: a generator that starts anew each time."""

    def __init__(self):
        self.source = np.random.SFC64(0)

    def words(self, start: np.ndarray, n: int) -> np.ndarray:
        self.source.state = {"bit_generator": "SFC64", "state": {"state": start}, "has_uint32": 0, "uinteger": 0}
        self.source.random_raw(12, output=False)  # until the key is in all of the state
        return self.source.random_raw(n)


def new_secret() -> bytes:
    """A key that nobody knows."""
    return os.urandom(32)


def public(seed: int | None) -> int:
    """A seed for draws that need not be secret: the given one, or a new one."""
    return int.from_bytes(os.urandom(6), "little") if seed is None else seed


def secret_words(secret: bytes, ids: np.ndarray, salt: int, n: int) -> np.ndarray:
    """len(ids) x n 32-bit numbers: SHAKE-128 of the secret, the salt and the id. Without the secret they cannot be told from random ones."""
    out, head = np.empty((len(ids), n), np.uint32), hashlib.shake_128(secret + salt.to_bytes(8, "little"))
    for row, own in enumerate(ids.astype(np.int64).view(np.uint64).tolist()):
        h = head.copy()
        h.update(own.to_bytes(8, "little"))
        out[row] = np.frombuffer(h.digest(4 * n), "<u4")
    return out


def floats(bits: np.ndarray) -> np.ndarray:
    """64 random bits as numbers in [0, 1)."""
    return (bits >> np.uint64(11)).astype(np.float64) * 2.0**-53
