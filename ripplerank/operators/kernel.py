"""Array kernels for graphs that fit one machine; every function works on neighbour lists alone."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np

from ..functions.draws import draw_arrays, stop_bound
from .graph import LocalGraph, runs

#: Walks advanced together: bounds a task's scratch memory.
WALKERS = 200_000
#: Edges that a block of queries follows together.
EDGES = 2_000_000
#: Index entries that are gathered at once.
GATHERED = 1 << 18


def walk(
    g: LocalGraph, starts: np.ndarray, walks: int, c: float, seed: int, rng: str, first_walk: int, dangling: str, max_steps: int | None
) -> Iterator[tuple[int, np.ndarray, np.ndarray, np.ndarray, np.ndarray]]:
    """Steps of all walks of the start positions: (step, start index, walk, position, stops here)."""
    s = np.repeat(np.arange(len(starts)), walks)
    w = np.tile(np.arange(first_walk, first_walk + walks), len(starts))
    v = starts[s]
    ids, bound, step = g.ids[starts], stop_bound(c), 0
    while len(s):
        h1, h2 = draw_arrays(rng, seed, ids[s], w, step)
        stop = h1 < bound
        yield step, s, w, v, stop
        if max_steps is not None and step >= max_steps:
            return
        on = ~stop
        if dangling == "absorb":
            on &= g.degree[v] > 0
        s, w, v, h2 = s[on], w[on], v[on], h2[on]
        deg = g.degree[v]
        spot = g.first[v] + ((h2 * deg) >> 32)
        v = np.where(deg > 0, g.dst[np.minimum(spot, len(g.dst) - 1)] if len(g.dst) else v, starts[s])
        step += 1


def walk_counts(g: LocalGraph, starts: np.ndarray, *how) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """start index, position, visits, ends of all walks."""
    n, seen, ended = len(g.ids), [], []
    for _, s, _, v, stop in walk(g, starts, *how):
        key = s * n + v
        seen.append(key)
        ended.append(key[stop])
    if not seen:
        return (np.zeros(0, np.int64),) * 4
    keys, visits = np.unique(np.concatenate(seen), return_counts=True)
    at, ends = np.unique(np.concatenate(ended), return_counts=True)
    out = np.zeros(len(keys), np.int64)
    out[np.searchsorted(keys, at)] = ends
    return keys // n, keys % n, visits, out


def laps_block(g: LocalGraph, starts: np.ndarray, depth: int, c: float, eps: float, residual: float | None = None):
    """Settled rows of a block of starts, and the frontier (row, position, mass) after `depth` laps.

    All starts advance together over one pass of the neighbour lists a lap. With `residual`, a row whose
    frontier holds at most that much goes no further. What falls under eps is dropped.
    """
    n = len(g.ids)
    settled = np.zeros((len(starts), n))
    flat = settled.ravel()
    row, at, mass = np.arange(len(starts)), starts.astype(np.int64), np.ones(len(starts))
    rest: list[tuple[np.ndarray, np.ndarray, np.ndarray]] = []
    for _ in range(depth):
        if residual is not None:
            over = np.bincount(row, mass, len(starts))[row] > residual
            rest.append((row[~over], at[~over], mass[~over]))
            row, at, mass = row[over], at[over], mass[over]
        if not len(at):
            break
        flat[row * n + at] += c * mass
        row, at, mass = _lap_block(g, row, at, mass, c, n, len(starts))
        if eps > 0:
            high = mass >= eps
            row, at, mass = row[high], at[high], mass[high]
    rest.append((row, at, mass))
    return settled, *(np.concatenate(x) for x in zip(*rest))


def _lap_block(g: LocalGraph, row: np.ndarray, at: np.ndarray, mass: np.ndarray, c: float, n: int, rows: int):
    """One lap for rows in ascending order, a bounded number of edges at a time."""
    deg = g.degree[at]
    on = deg > 0
    row, at, deg, mass = row[on], at[on], deg[on], mass[on]
    share, total = mass * ((1 - c) / np.maximum(deg, 1)), np.cumsum(deg)
    out, begin = [], 0
    # A run holds whole rows: their sums are final.
    ends = np.append(np.flatnonzero(np.diff(row)) + 1, len(row)) if len(row) else np.zeros(0, int)
    while begin < len(row):
        limit = (total[begin - 1] if begin else 0) + EDGES
        end = int(ends[max(np.searchsorted(total[ends - 1], limit, "right") - 1, np.searchsorted(ends, begin, "right"))])
        part = slice(begin, end)
        size = deg[part]
        spots = np.arange(int(size.sum())) + np.repeat(g.first[at[part]] - (np.cumsum(size) - size), size)
        base = int(row[begin])
        key = g.dst[spots] + np.repeat((row[part] - base) * n, size)
        cells = (int(row[end - 1]) - base + 1) * n
        if len(key) * 4 > cells:
            dense = np.bincount(key, np.repeat(share[part], size), cells)
            to = np.flatnonzero(dense)
            value = dense[to]
        else:
            to, where = np.unique(key, return_inverse=True)
            value = np.bincount(where, np.repeat(share[part], size), len(to))
        out.append((to // n + base, to % n, value))
        begin = end
    if not out:
        return np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0)
    return tuple(np.concatenate(x) for x in zip(*out))


def rows_of(first: np.ndarray, values: np.ndarray) -> list[np.ndarray]:
    """Views of the values of each position."""
    return [values[a:b] for a, b in zip(first[:-1].tolist(), first[1:].tolist())]


def close_block(settled: np.ndarray, row: np.ndarray, at: np.ndarray, mass: np.ndarray, size: np.ndarray, vertex: list[np.ndarray], weight: list[np.ndarray]) -> None:
    """Add the stored vectors of frontier positions, times their mass, to the settled rows.

    `size` holds the entries of each position's vector, `vertex` and `weight` views of them. A row's vectors are gathered some at a
    time, so that what is gathered stays in the cache.
    """
    n = settled.shape[1]
    order = np.argsort(row, kind="stable")
    row, at, mass = row[order], at[order], mass[order]
    entries = size[at]
    total = np.cumsum(entries)
    names = at.tolist()
    ends = np.searchsorted(row, np.arange(len(settled)), "right").tolist()
    begin = 0
    for i, end in enumerate(ends):
        while begin < end:
            stop = min(end, max(begin + 1, int(np.searchsorted(total, (total[begin - 1] if begin else 0) + GATHERED, "right"))))
            part = names[begin:stop]
            w = np.concatenate([weight[u] for u in part])
            w *= np.repeat(mass[begin:stop], entries[begin:stop])
            settled[i] += np.bincount(np.concatenate([vertex[u] for u in part]), w, n)
            begin = stop


def power(g: LocalGraph, start: np.ndarray, weight: np.ndarray, c: float, tol: float, most: int, to_source: bool) -> np.ndarray:
    """Iterate p = (1-c) p A + c e from p = e, dangling mass led back to e or lost."""
    n = len(g.ids)
    e = np.zeros(n)
    e[start] = weight
    p, deg = e.copy(), np.maximum(g.degree, 1)
    loose, parts = g.degree == 0, runs(g.first, EDGES)
    for _ in range(most):
        share, pushed = p / deg, np.zeros(n)
        for a, b in parts:
            pushed += np.bincount(g.dst[g.first[a] : g.first[b]], np.repeat(share[a:b], g.degree[a:b]), n)
        q = (1 - c) * pushed + c * e
        if to_source:
            q += (1 - c) * p[loose].sum() * e
        change = np.abs(q - p).sum()
        p = q
        if change <= tol:
            break
    return p


def chunks(total: int, walks: int) -> Iterator[slice]:
    """Runs of sources whose walks stay within WALKERS."""
    step = max(1, WALKERS // max(1, walks))
    for a in range(0, total, step):
        yield slice(a, min(total, a + step))
