"""Random numbers that depend on keys alone, so that a task that runs again, or on other partitions, draws the same."""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F


def _key(seed: int, keys: tuple) -> Column:
    return F.concat_ws(":", F.lit(str(seed)), *[k.cast("string") if isinstance(k, Column) else F.lit(str(k)) for k in keys])


def draw(seed: int, *keys: Column | int | str, mode: str = "fast") -> Column:
    """A number in [0, 1) per row from the seed and keys.  ``portable`` equals DuckDB's value of ``draw_sql``; ``fast`` stays in generated code."""
    if mode == "portable":
        return F.conv(F.substring(F.md5(_key(seed, keys).cast("binary")), 1, 12), 16, 10).cast("double") / float(1 << 48)
    if mode == "fast":
        cols = [k if isinstance(k, Column) else F.lit(k) for k in keys]
        return F.shiftrightunsigned(F.xxhash64(F.lit(seed), *cols), 11).cast("double") / float(1 << 53)
    raise ValueError(f"unknown mode {mode}")


# fixed values: the primes of the 64-bit hash that Spark's xxhash64 uses
_P1, _P2, _P3, _P4, _P5 = (np.uint64(x) for x in (0x9E3779B185EBCA87, 0xC2B2AE3D27D4EB4F, 0x165667B19E3779F9, 0x85EBCA77C2B2AE63, 0x27D4EB2F165667C5))


def _turned(x: np.ndarray, n: int) -> np.ndarray:
    return (x << np.uint64(n)) | (x >> np.uint64(64 - n))


def _hashed(value: np.ndarray, so_far: np.ndarray, wide: bool) -> np.ndarray:
    """One column more in the chain of hashes: 8 bytes of it, or 4."""
    v = value.astype(np.int64).view(np.uint64)
    if wide:
        h = so_far + _P5 + np.uint64(8) ^ _turned(v * _P2, 31) * _P1
        h = _turned(h, 27) * _P1 + _P4
    else:
        h = so_far + _P5 + np.uint64(4) ^ (v & np.uint64(0xFFFFFFFF)) * _P1
        h = _turned(h, 23) * _P2 + _P3
    h = (h ^ h >> np.uint64(33)) * _P2
    h = (h ^ h >> np.uint64(29)) * _P3
    return h ^ h >> np.uint64(32)


def draws(seed: int, *keys: np.ndarray | int) -> np.ndarray:
    """What ``draw`` gives in its fast mode, for arrays of 64-bit keys and integers."""
    shape = np.broadcast_shapes(*[np.shape(k) for k in keys])
    h = np.uint64(42)  # one number until the first array: seed and iteration are hashed once for all rows
    with np.errstate(over="ignore"):
        for k in (seed, *keys):
            array = isinstance(k, np.ndarray)
            h = _hashed(np.asarray(k, np.int64), h, array or not -(1 << 31) <= k < 1 << 31)
    return np.broadcast_to(h >> np.uint64(11), shape).astype(float) / float(1 << 53)


def draw_sql(seed: int, *keys: str) -> str:
    """DuckDB expression of the portable draw; keys are SQL expressions."""
    text = " || ':' || ".join([f"'{seed}'", *[f"CAST({k} AS VARCHAR)" for k in keys]])
    return f"(CAST('0x' || substr(md5({text}), 1, 12) AS BIGINT) / 281474976710656.0::DOUBLE)"


def generator(seed: int, *keys: int) -> np.random.Generator:
    """A counter-based numpy generator for one (iteration, leg, sender)."""
    return np.random.Generator(np.random.Philox(np.random.SeedSequence([seed & 0xFFFFFFFF, *[k & 0xFFFFFFFF for k in keys]])))
