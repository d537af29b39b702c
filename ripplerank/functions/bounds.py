"""Closed forms: tail bound of the full-path estimator, walk counts, residual masses."""

from __future__ import annotations

import math

from pyspark.sql import Column
from pyspark.sql import functions as F

TELEPORT = 0.15


def tail_bound(gamma: float, walks: int, c: float = TELEPORT, clip: bool = True) -> float:
    """Upper bound of the chance that a full-path score is off by gamma or more (either way)."""
    raw = (1 + gamma * c / 10) / math.sqrt(c) * math.exp(-gamma * gamma * walks / 20)
    return min(1.0, raw) if clip else raw


def tail_bound_column(gamma: Column, walks: Column, c: Column) -> Column:
    return F.least(F.lit(1.0), (1 + gamma * c / 10) / F.sqrt(c) * F.exp(-gamma * gamma * walks / 20))


def walks_for_precision(gamma: float, delta: float, c: float = TELEPORT) -> int:
    """Least number of walks for which the tail bound is at most delta."""
    return math.ceil(20 / gamma**2 * math.log((1 + gamma * c / 10) / (delta * math.sqrt(c))))


def walks_for_precision_column(gamma: Column, delta: Column, c: Column) -> Column:
    return F.ceil(20 / (gamma * gamma) * F.log((1 + gamma * c / 10) / (delta * F.sqrt(c)))).cast("long")


def equivalent_endpoint_walks(walks: int, c: float = TELEPORT) -> int:
    """End-point walks that give as many samples as `walks` full-path walks have visits."""
    return round(walks / c)


def equivalent_endpoint_walks_column(walks: Column, c: float = TELEPORT) -> Column:
    return F.round(walks / F.lit(c)).cast("long")


def mean_length(c: float = TELEPORT) -> float:
    return 1 / c


def truncated_mass(steps: int, c: float = TELEPORT) -> float:
    """Share of walks still alive after `steps` moves without dangling vertices."""
    return (1 - c) ** steps


def laps_for_residual(target: float, c: float = TELEPORT) -> int:
    """Laps after which the frontier holds at most `target`."""
    return max(0, math.ceil(math.log(target) / math.log(1 - c)))


def index_bound(vertices: int, walks: int, c: float = TELEPORT) -> float:
    """Expected number of visits, and so a bound of index entries."""
    return vertices * walks / c
