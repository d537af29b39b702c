"""Vectorised work on Arrow text columns: words, word hashes and rolling word hashes, without decoding."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

_SPACE = np.zeros(256, bool)
_SPACE[[0x20, *range(0x09, 0x0E)]] = True
_LOWER = np.arange(256, dtype=np.uint8)
_LOWER[65:91] += 32
_BASE = np.uint64(0x9E3779B97F4A7C15 | 1)


def slices(batch: pa.RecordBatch, text: str, most: int = 1 << 20) -> Iterator[tuple[pa.RecordBatch, np.ndarray, np.ndarray]]:
    """Runs of rows with about `most` bytes of text: (rows, bytes, offsets). Null counts as empty.

    A text longer than `most` comes alone, so scratch memory is bounded by it.
    """
    col = pc.fill_null(batch.column(text), "").cast(pa.large_string())
    n = len(col)
    if not n:
        return
    offsets = np.frombuffer(col.buffers()[1], np.int64, n + 1, col.offset * 8)
    raw = col.buffers()[2]
    data = np.frombuffer(raw, np.uint8) if raw is not None and raw.size else np.zeros(0, np.uint8)
    at = 0
    while at < n:
        to = max(at + 1, int(np.searchsorted(offsets, offsets[at] + most, "right")) - 1)
        to = min(to, n)
        yield batch.slice(at, to - at), data[offsets[at] : offsets[to]], offsets[at : to + 1] - offsets[at]
        at = to


def mix(x: np.ndarray) -> np.ndarray:
    """The finaliser of a 64-bit counter generator: a bijection that spreads all bits."""
    x = x ^ (x >> np.uint64(30))
    x = x * np.uint64(0xBF58476D1CE4E5B9)
    x = x ^ (x >> np.uint64(27))
    x = x * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


def _powers(n: int) -> np.ndarray:
    out = np.full(n, _BASE, np.uint64)
    out[0] = 1
    return np.multiply.accumulate(out)


def word_hashes(data: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """64-bit hashes of all words (A-Z lower-cased, split at ASCII space), and where each text's words begin."""
    if not len(data):
        return np.zeros(0, np.uint64), np.zeros(len(offsets), np.int64)
    inside = ~_SPACE[data]
    first = inside.copy()
    first[1:] &= ~inside[:-1]
    heads = offsets[:-1][offsets[:-1] < len(data)]
    first[heads] = inside[heads]
    at = np.flatnonzero(inside)
    begins = np.flatnonzero(first)
    if not len(begins):
        return np.zeros(0, np.uint64), np.zeros(len(offsets), np.int64)
    runs = np.flatnonzero(first[at])
    lengths = np.diff(np.append(runs, len(at)))
    place = np.arange(len(at)) - np.repeat(runs, lengths)
    value = (_LOWER[data[at]].astype(np.uint64) + np.uint64(1)) * _powers(int(lengths.max()) + 1)[place]
    h = mix(np.add.reduceat(value, runs) + lengths.astype(np.uint64) * np.uint64(0xD6E8FEB86659FD93))
    return h, np.searchsorted(begins, offsets).astype(np.int64)


def rolling(h: np.ndarray, k: int) -> np.ndarray:
    """Hash of each k consecutive word hashes, by first word; the caller masks windows that leave a text."""
    n = len(h) - k + 1
    if n <= 0:
        return np.zeros(0, np.uint64)
    out = np.zeros(n, np.uint64)
    for i in range(k):
        out = out * np.uint64(0xC2B2AE3D27D4EB4F) + h[i : i + n]
    return mix(out)


def window_min(x: np.ndarray, w: int) -> np.ndarray:
    """Least value of each w consecutive ones, in passes whose number does not depend on w."""
    n = len(x) - w + 1
    if n <= 0:
        return x[:0]
    whole = np.full(-(-len(x) // w) * w, np.iinfo(x.dtype).max, x.dtype)
    whole[: len(x)] = x
    blocks = whole.reshape(-1, w)
    ahead = np.minimum.accumulate(blocks[:, ::-1], 1)[:, ::-1].ravel()
    behind = np.minimum.accumulate(blocks, 1).ravel()
    return np.minimum(ahead[:n], behind[w - 1 : w - 1 + n])
