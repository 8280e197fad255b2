"""Random maps as pure functions of (seed, column, direction): a retried task draws the same numbers again."""

from __future__ import annotations

import hashlib

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F

LAWS = ("gaussian", "sign", "sparse_sign")


def _mixed(seed: int, ids: np.ndarray, r: int, lane: int = 0) -> np.ndarray:
    with np.errstate(over="ignore"):
        x = ids.astype(np.uint64)[:, None] * np.uint64(0x9E3779B97F4A7C15) + np.arange(r, dtype=np.uint64)[None] * np.uint64(0xC2B2AE3D27D4EB4F)
        x = x + np.uint64((seed * 0x165667B19E3779F9 + lane * 0x27D4EB2F165667C5) & (1 << 64) - 1)
        for shift, factor in ((30, 0xBF58476D1CE4E5B9), (27, 0x94D049BB133111EB)):
            x = (x ^ (x >> np.uint64(shift))) * np.uint64(factor)
        return x ^ (x >> np.uint64(31))


def uniform_block(seed: int, ids: np.ndarray, r: int, lane: int = 0) -> np.ndarray:
    return ((_mixed(seed, ids, r, lane) >> np.uint64(11)).astype(np.float64) + 0.5) / float(1 << 53)


def hashed_number(*parts) -> int:
    """The number of :func:`hashed` for plain values."""
    return int(hashlib.md5(":".join(map(str, parts)).encode()).hexdigest()[:8], 16)


def sparsity(law, s, n: int = 0):
    """The s of the sparse law: a number, or 'sqrt' of the number of columns n."""
    return max(1, round(n**0.5)) if s == "sqrt" else s


def hashed_block(seed: int, ids: np.ndarray, r: int, law="sparse_sign", s: int = 3) -> np.ndarray:
    """The entries that :func:`omega` gives, n x r, for the kernels: the same draws as in SQL."""
    h = np.array([[hashed_number(seed, int(i), k) for k in range(1, r + 1)] for i in ids], dtype=np.int64).reshape(len(ids), r)
    if law == "sign":
        return (h % 2 * 2 - 1).astype(np.float64)
    if law == "sparse_sign":
        return np.where(h % (2 * s) == 0, 1.0, np.where(h % (2 * s) == 1, -1.0, 0.0))
    if law == "gaussian":
        other = np.array([[hashed_number(seed + 1, int(i), k) for k in range(1, r + 1)] for i in ids], dtype=np.float64).reshape(len(ids), r)
        return np.sqrt(-2 * np.log((h + 0.5) / 2.0**32)) * np.cos(2 * np.pi * (other + 0.5) / 2.0**32)
    raise ValueError(f"unknown law {law!r}")


def block(seed: int, ids: np.ndarray, r: int, law="sparse_sign", s: int = 3, draws: str = "mixed") -> np.ndarray:
    """Entries of the map for these columns, n x r; ``law`` may be a function of uniforms.

    draws: 'mixed', fast, or 'hash', which SQL can repeat.
    """
    if draws == "hash":
        return hashed_block(seed, ids, r, law, s)
    u = uniform_block(seed, ids, r)
    if callable(law):
        return law(u)
    if law == "sign":
        return np.where(u < 0.5, -1.0, 1.0)
    if law == "sparse_sign":
        return np.where(u < 0.5 / s, -1.0, np.where(u < 1.0 / s, 1.0, 0.0))
    if law == "gaussian":
        return np.sqrt(-2 * np.log(u)) * np.cos(2 * np.pi * uniform_block(seed, ids, r, 1))
    raise ValueError(f"unknown law {law!r}")


def hashed(*parts: Column) -> Column:
    """32-bit number from the first eight hex digits of an md5; any SQL engine can repeat it."""
    return F.conv(F.substring(F.md5(F.concat_ws(":", *[p.cast("string") for p in parts]).cast("binary")), 1, 8), 16, 10).cast("long")


def omega(seed: int, col_id: Column, k: Column, law: str = "sparse_sign", s: int = 3) -> Column:
    """Entry of the map as a SQL expression: integer laws, and the gaussian by two hashes."""
    h = hashed(F.lit(seed), col_id, k)
    if law == "sign":
        return (h % 2 * 2 - 1).cast("double")
    if law == "sparse_sign":
        return F.when(h % (2 * s) == 0, 1.0).when(h % (2 * s) == 1, -1.0).otherwise(0.0)
    if law == "gaussian":
        u, v = ((x.cast("double") + 0.5) / float(1 << 32) for x in (h, hashed(F.lit(seed + 1), col_id, k)))
        return F.sqrt(-2 * F.ln(u)) * F.cos(2 * np.pi * v)
    raise ValueError(f"unknown law {law!r}")
