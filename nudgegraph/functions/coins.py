"""Stateless coins: an edge's state in a world is a pure function of their ids.

``fast`` coins hash with the engine's own 64-bit hash, ``portable`` ones with
md5, which other SQL engines can replay. Both have a twin for Python workers
that gives the very same number.
"""

from __future__ import annotations

import hashlib

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F

SPAN = 1 << 32
MODES = ("fast", "portable")


def coin(mode: str, salt: int, *ids: str | Column) -> Column:
    """A number in [0, 2^32) of the salt and the ids."""
    columns = [F.col(c) if isinstance(c, str) else c for c in ids]
    if mode == "portable":
        text = F.concat_ws("|", F.lit(str(salt)), *[c.cast("string") for c in columns])
        return F.conv(F.substring(F.md5(text), 1, 8), 16, 10).cast("long")
    return F.shiftrightunsigned(F.xxhash64(F.lit(salt).cast("long"), *[c.cast("long") for c in columns]), 32)


def threshold(p: str | Column) -> Column:
    return F.floor((F.col(p) if isinstance(p, str) else p) * SPAN).cast("long")


def root_coin(mode: str, salt: int, sketch: str | Column) -> Column:
    return coin(mode, salt, F.lit("root") if mode == "portable" else F.lit(-1), sketch)


# fixed values: the five primes of the 64-bit xxHash
_P1, _P2, _P3, _P4, _P5 = (np.uint64(x) for x in (0x9E3779B185EBCA87, 0xC2B2AE3D27D4EB4F, 0x165667B19E3779F9, 0x85EBCA77C2B2AE63, 0x27D4EB2F165667C5))


def _turn(x: np.ndarray, n: int) -> np.ndarray:
    return (x << np.uint64(n)) | (x >> np.uint64(64 - n))


def _hash_long(value: np.ndarray, seed: np.ndarray) -> np.ndarray:
    h = seed + _P5 + np.uint64(8)
    h = _turn(h ^ (_turn(value * _P2, 31) * _P1), 27) * _P1 + _P4
    h = (h ^ (h >> np.uint64(33))) * _P2
    h = (h ^ (h >> np.uint64(29))) * _P3
    return h ^ (h >> np.uint64(32))


def coin_array(mode: str, salt: int, *ids: np.ndarray | int) -> np.ndarray:
    """The same numbers as ``coin`` for arrays of ids."""
    if mode == "portable":
        rows = [np.asarray(x) for x in ids]
        shape = np.broadcast_shapes(*[r.shape for r in rows])
        lead = next((i for i, r in enumerate(rows) if r.ndim), len(rows))  # ids that are the same for all
        head = "".join(f"{x}|" for x in (salt, *rows[:lead]))
        texts = zip(*[r.ravel().tolist() for r in np.broadcast_arrays(*rows[lead:])], strict=True) if lead < len(rows) else [()]
        md5 = hashlib.md5
        if len(rows) - lead == 2:
            out = [md5(f"{head}{a}|{b}".encode()).digest()[:4] for a, b in texts]
        else:
            out = [md5((head + "|".join(map(str, t)) if t else head[:-1]).encode()).digest()[:4] for t in texts]
        return np.frombuffer(b"".join(out), ">u4").astype(np.int64).reshape(shape)
    with np.errstate(over="ignore"):
        h = np.uint64(42)
        for x in (salt, *ids):
            h = _hash_long(np.asarray(x, np.int64).astype(np.uint64), h)
    return (h >> np.uint64(32)).astype(np.int64)


def root_array(mode: str, salt: int, sketches: np.ndarray) -> np.ndarray:
    return coin_array(mode, salt, "root" if mode == "portable" else -1, sketches)
