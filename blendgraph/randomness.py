"""Draws that are functions of their keys: the same in every plan, retry and number of partitions, and in NumPy."""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F

SPAN = 1 << 32


def draw(*keys: Column | str | int) -> Column:
    """32 bits of md5 over the keys joined by '|', as a long. SQL engines agree on it, so walks have an oracle."""
    cols = [k if isinstance(k, Column) else F.lit(str(k)) for k in keys]
    return F.conv(F.substring(F.md5(F.concat_ws("|", *[c.cast("string") for c in cols]).cast("binary")), 1, 8), 16, 10).cast("long")


def fast_draw(*keys: Column | str | int) -> Column:
    """As draw, by xxhash64: cheaper, without an oracle in other engines."""
    cols = [k if isinstance(k, Column) else F.lit(k) for k in keys]
    return F.pmod(F.shiftright(F.xxhash64(*cols), 16), F.lit(SPAN))


def unit(*keys: Column | str | int, fast: bool = True) -> Column:
    """A double in [0, 1)."""
    return (fast_draw(*keys) if fast else draw(*keys)) / F.lit(float(SPAN))


def long_unit(*keys: Column | int) -> Column:
    """A double in [0, 1) of 53 bits, by xxhash64 over the keys as longs."""
    cols = [(k if isinstance(k, Column) else F.lit(k)).cast("long") for k in keys]
    return F.shiftrightunsigned(F.xxhash64(*cols), 11) / F.lit(float(1 << 53))


def normal(*keys: Column | str | int) -> Column:
    """A standard normal value from two draws."""
    u = (fast_draw(*keys, F.lit("radius")) + 1) / F.lit(SPAN + 1.0)
    return F.sqrt(-2 * F.log(u)) * F.cos(2 * 3.141592653589793 * unit(*keys, F.lit("angle")))


# fixed values: the primes of XXH64
_P1, _P2, _P3, _P4, _P5 = (np.uint64(x) for x in (0x9E3779B185EBCA87, 0xC2B2AE3D27D4EB4F, 0x165667B19E3779F9, 0x85EBCA77C2B2AE63, 0x27D4EB2F165667C5))


def _rotl(x: np.ndarray, r: int) -> np.ndarray:
    return (x << np.uint64(r)) | (x >> np.uint64(64 - r))


def xxhash_long(values: np.ndarray, seed: np.ndarray) -> np.ndarray:
    """XXH64 of 8-byte values, as the engine's xxhash64 chains it over columns."""
    h = seed + _P5 + np.uint64(8)
    h = h ^ (_rotl(values.astype(np.int64).view(np.uint64) * _P2, 31) * _P1)
    h = _rotl(h, 27) * _P1 + _P4
    h = (h ^ (h >> np.uint64(33))) * _P2
    h = (h ^ (h >> np.uint64(29))) * _P3
    return h ^ (h >> np.uint64(32))


def numpy_draw(seed: int, walk: np.ndarray, at: int) -> np.ndarray:
    """fast_draw(seed, walk_id, at) in NumPy. seed is a 4-byte value there."""
    with np.errstate(over="ignore"):
        h = np.full(1, 42, np.uint64) + _P5 + np.uint64(4)
        h = h ^ (np.array([seed], np.int64).view(np.uint64) & np.uint64(0xFFFFFFFF)) * _P1
        h = _rotl(h, 23) * _P2 + _P3
        h = (h ^ (h >> np.uint64(33))) * _P2
        h = (h ^ (h >> np.uint64(29))) * _P3
        h = h ^ (h >> np.uint64(32))
        h = xxhash_long(np.full(len(walk), at), xxhash_long(walk, np.full(len(walk), h[0])))
    return np.mod(h.view(np.int64) >> 16, SPAN)


def numpy_long_unit(*keys: np.ndarray | int) -> np.ndarray:
    """long_unit in NumPy, for keys that broadcast together."""
    with np.errstate(over="ignore"):
        h = np.full(1, 42, np.uint64)
        for k in np.broadcast_arrays(*(np.asarray(k, np.int64) for k in keys)):
            h = xxhash_long(np.ascontiguousarray(k).ravel(), h if len(h) == k.size else np.full(max(1, k.size), h[0]))
    return (h >> np.uint64(11)) / float(1 << 53)
