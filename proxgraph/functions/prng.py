"""Counter-based random numbers: a draw is a function of (seed, trial, walk, step, lane) alone.

Results do not depend on how rows are laid out or whether a task is run again.  The portable
generator uses 31-bit modular arithmetic that numpy, Spark SQL and DuckDB all have; with W walks about
W**2 / 2**32 pairs of walks share their draws.  The wide one is Spark's 64-bit xxHash of the five numbers,
written again for numpy, so that both engines draw the same.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F

P = 2147483647
_LANE = 15485863


def mix31(x: np.ndarray) -> np.ndarray:
    x = (x * 1103515245 + 12345) % P
    x = x ^ (x >> 15)
    x = (x * 48271) % P
    x = x ^ (x >> 13)
    return (x * 69621 + 7) % P


def walk_key(seed: int, trial: np.ndarray, walk: np.ndarray) -> np.ndarray:
    return mix31((mix31((np.int64(seed) * 7919 + np.asarray(trial, np.int64) * 104729) % P) + np.asarray(walk, np.int64)) % P)


def draw(key: np.ndarray, step: int, lane: int) -> np.ndarray:
    """An integer in [0, P)."""
    return mix31((key + np.int64(2 * step + lane) * _LANE) % P)


#: Fixed values of 64-bit xxHash, and the seed that Spark's function starts from.
_XX1, _XX2, _XX3, _XX4, _XX5 = (
    np.uint64(0x9E3779B185EBCA87),
    np.uint64(0xC2B2AE3D27D4EB4F),
    np.uint64(0x165667B19E3779F9),
    np.uint64(0x85EBCA77C2B2AE63),
    np.uint64(0x27D4EB2F165667C5),
)
_XX_START = 42


def wide_key(seed: int, trial: np.ndarray, walk: np.ndarray) -> np.ndarray:
    trial, walk = np.broadcast_arrays(np.asarray(trial, np.int64), np.asarray(walk, np.int64))
    key = np.full(walk.shape, _XX_START, np.uint64)
    return _xx(_xx(_xx(key, np.int64(seed)), trial), walk)


def wide_draw(key: np.ndarray, step: int, lane: int) -> np.ndarray:
    """An integer in [0, P) from 64 bits."""
    return _xx(_xx(key, np.int64(step)), np.int64(lane)).view(np.int64) % P


def _rotated(x: np.ndarray, by: int) -> np.ndarray:
    return (x << np.uint64(by)) | (x >> np.uint64(64 - by))


def _xx(state: np.ndarray, value) -> np.ndarray:
    """xxHash of one 64-bit number from ``state``; ``state`` is an array, so sums wrap without a warning."""
    value = np.atleast_1d(np.asarray(value, np.int64)).view(np.uint64)
    h = (state + _XX5 + np.uint64(8)) ^ (_rotated(value * _XX2, 31) * _XX1)
    h = _rotated(h, 27) * _XX1 + _XX4
    h = (h ^ (h >> np.uint64(33))) * _XX2
    h = (h ^ (h >> np.uint64(29))) * _XX3
    return h ^ (h >> np.uint64(32))


def stop_limit(alpha: float) -> int:
    """A walk stops when its draw is under this."""
    return int(round(alpha * P))


# the same as Spark columns


def _let(x: Column, use) -> Column:
    """``use(x)`` with x computed once, however often ``use`` names it (the plan would copy it else)."""
    return F.transform(F.array(x), use)[0]


def mix31_col(x: Column) -> Column:
    p = F.lit(P).cast("long")
    x = _let((x * F.lit(1103515245).cast("long") + F.lit(12345).cast("long")) % p, lambda v: v.bitwiseXOR(F.shiftright(v, 15)))
    x = _let((x * F.lit(48271).cast("long")) % p, lambda v: v.bitwiseXOR(F.shiftright(v, 13)))
    return (x * F.lit(69621).cast("long") + F.lit(7).cast("long")) % p


def walk_key_col(seed: int, trial: Column, walk: Column) -> Column:
    p = F.lit(P).cast("long")
    return mix31_col((mix31_col((F.lit(seed).cast("long") * 7919 + trial.cast("long") * 104729) % p) + walk.cast("long")) % p)


def draw_col(key: Column, step: Column, lane: int) -> Column:
    return mix31_col((key + (step.cast("long") * 2 + lane) * F.lit(_LANE).cast("long")) % F.lit(P).cast("long"))


def wide_draw_col(seed: int, trial: Column, walk: Column, step: Column, lane: int) -> Column:
    numbers = [x.cast("long") for x in (F.lit(seed), trial, walk, step, F.lit(lane))]
    return F.pmod(F.xxhash64(*numbers), F.lit(P).cast("long"))


# and as SQL text


def mix31_sql(x: str) -> str:
    a = f"((({x}) * 1103515245 + 12345) % {P})"
    b = f"xor({a}, {a} >> 15)"
    c = f"(({b} * 48271) % {P})"
    return f"((xor({c}, {c} >> 13) * 69621 + 7) % {P})"
