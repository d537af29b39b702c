"""Counter-based random draws: a pure function of seed, source, walk and step.

A retried task repeats its walks exactly, walks can be added to an index later, and every
execution mode draws the same numbers. `md5` has the same value in any SQL engine;
`xxhash64` is the faster production generator. Each has a Column form and a NumPy form.
"""

from __future__ import annotations

import hashlib

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F

SPAN = 1 << 32


def stop_bound(c: float) -> int:
    """Draws below this stop a walk."""
    return int(c * SPAN)


def draw_columns(rng: str, seed: int, source: Column, walk: Column, step: Column) -> tuple[Column, Column]:
    """Two draws in [0, 2^32): the stop test and the choice of a neighbour."""
    if rng == "md5":
        h = F.md5(F.concat_ws("|", F.lit(seed), source, walk, step))
        return F.conv(F.substring(h, 1, 8), 16, 10).cast("long"), F.conv(F.substring(h, 9, 8), 16, 10).cast("long")
    if rng == "xxhash64":
        h = F.xxhash64(F.lit(seed).cast("long"), source.cast("long"), walk.cast("long"), step.cast("long"))
        return F.shiftrightunsigned(h, 32), h.bitwiseAND(F.lit(SPAN - 1))
    raise ValueError(f"unknown generator {rng!r}")


def choose(draw: Column, degree: Column) -> Column:
    """Neighbour position 0 .. degree-1 for a draw, in integers only."""
    return F.shiftright(draw * degree, 32)


# The primes of the 64-bit xxHash.
_P1, _P2, _P3, _P4, _P5 = (
    np.uint64(0x9E3779B185EBCA87), np.uint64(0xC2B2AE3D27D4EB4F), np.uint64(0x165667B19E3779F9),
    np.uint64(0x85EBCA77C2B2AE63), np.uint64(0x27D4EB2F165667C5),
)


def _rotate(x: np.ndarray, n: int) -> np.ndarray:
    return (x << np.uint64(n)) | (x >> np.uint64(64 - n))


def _hash_long(value: np.ndarray, seed: np.ndarray) -> np.ndarray:
    h = seed + _P5 + np.uint64(8)
    h = _rotate(h ^ (_rotate(value * _P2, 31) * _P1), 27) * _P1 + _P4
    h = (h ^ (h >> np.uint64(33))) * _P2
    h = (h ^ (h >> np.uint64(29))) * _P3
    return h ^ (h >> np.uint64(32))


def draw_arrays(rng: str, seed: int, source: np.ndarray, walk: np.ndarray, step: int, vertex: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray]:
    """The same draws for arrays of sources and walks; those of compressed walks also depend on the vertex."""
    if rng == "md5":
        out = np.empty((2, len(source)), np.int64)
        tails = [f"{step}"] * len(source) if vertex is None else [f"{step}|{v}" for v in vertex.tolist()]
        for n, (s, w, t) in enumerate(zip(source.tolist(), walk.tolist(), tails)):
            h = hashlib.md5(f"{seed}|{s}|{w}|{t}".encode()).digest()
            out[0, n], out[1, n] = int.from_bytes(h[:4], "big"), int.from_bytes(h[4:8], "big")
        return out[0], out[1]
    if rng == "xxhash64":
        with np.errstate(over="ignore"):
            h = np.full(len(source), 42, np.uint64)
            for part in (np.full(len(source), seed), source, walk, np.full(len(source), step), *(() if vertex is None else (vertex,))):
                h = _hash_long(part.astype(np.int64).view(np.uint64), h)
        return (h >> np.uint64(32)).astype(np.int64), (h & np.uint64(SPAN - 1)).astype(np.int64)
    raise ValueError(f"unknown generator {rng!r}")
