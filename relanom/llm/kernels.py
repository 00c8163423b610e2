"""Vectorised text kernels shared by the operators; numpy only, no Spark.

Hashes are polynomial prefix hashes modulo 2**64 behind a final mixer.  They only
select positions and candidates: every decision is confirmed on the bytes
themselves or on a 128-bit cryptographic digest.
"""

from __future__ import annotations

from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa

_U = np.uint64
_BASE = 0x9E3779B97F4A7C15
_INVERSE = pow(_BASE, -1, 1 << 64)
_BLOCK = 1 << 21
_powers: list[np.ndarray] = []


def mix(x: np.ndarray) -> np.ndarray:
    """Finaliser of a 64-bit hash (shifts and odd multiplications)."""
    x = x ^ (x >> _U(30))
    x = x * _U(0xBF58476D1CE4E5B9)
    x = x ^ (x >> _U(27))
    x = x * _U(0x94D049BB133111EB)
    return x ^ (x >> _U(31))


def _power_tables(n: int) -> list[np.ndarray]:
    if not _powers or len(_powers[0]) < n:
        size = max(n, _BLOCK + 4096)
        _powers[:] = [np.cumprod(np.concatenate((np.ones(1, _U), np.full(size - 1, b, _U)))) for b in (_BASE, _INVERSE)]
    return _powers


def prefix_hash(values: np.ndarray) -> np.ndarray:
    """``P`` with ``(P[e] - P[s]) * inverse**s`` the hash of ``values[s:e]``."""
    up, _ = _power_tables(len(values) + 1)
    out = np.zeros(len(values) + 1, _U)
    np.cumsum((values.astype(_U) + _U(1)) * up[: len(values)], out=out[1:])
    return out


def span_hashes(prefix: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
    _, down = _power_tables(len(prefix))
    return mix((prefix[ends] - prefix[starts]) * down[starts] + (ends - starts).astype(_U))


def word_spans(data: np.ndarray, inside: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Starts and ends of the maximal runs of bytes with ``inside[byte]``."""
    flag = np.zeros(len(data) + 2, np.int8)
    flag[1:-1] = inside[data]
    change = np.diff(flag)
    return np.flatnonzero(change == 1), np.flatnonzero(change == -1)


def word_hashes(data: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
    """One hash per word, in blocks so that a very long text needs little extra memory."""
    out = np.empty(len(starts), _U)
    at = 0
    while at < len(starts):
        low = starts[at]
        to = max(at + 1, int(np.searchsorted(ends, low + _BLOCK)))
        out[at:to] = span_hashes(prefix_hash(data[low : ends[to - 1]]), starts[at:to] - low, ends[at:to] - low)
        at = to
    return out


def gram_hashes(words: np.ndarray, k: int) -> np.ndarray:
    """Hash of every ``k`` consecutive word hashes."""
    n = len(words) - k + 1
    if n <= 0:
        return np.empty(0, _U)
    total = np.zeros(n, _U)
    for i in range(k):
        total = total * _U(_BASE) + words[i : i + n]
    return mix(total)


def window_minima(hashes: np.ndarray, w: int) -> np.ndarray:
    """For each window of ``w`` consecutive hashes the position of its least hash, the leftmost of equals.

    The top 40 bits decide, so equal windows choose the same relative position wherever they stand.
    """
    n = len(hashes) - w + 1
    if n <= 0:
        return np.empty(0, np.int64)
    if len(hashes) > 1 << 23:
        step = (1 << 23) - w
        parts = [window_minima(hashes[i : i + step + w - 1], w) + i for i in range(0, n, step)]
        return np.concatenate(parts)
    keys = (hashes & _U(0xFFFFFFFFFF000000)) | np.arange(len(hashes), dtype=_U)
    blocks = -(-len(keys) // w)
    padded = np.full(blocks * w, np.iinfo(np.uint64).max, _U)
    padded[: len(keys)] = keys
    grid = padded.reshape(blocks, w)
    before = np.minimum.accumulate(grid, axis=1).ravel()
    after = np.minimum.accumulate(grid[:, ::-1], axis=1)[:, ::-1].ravel()
    least = np.minimum(after[:n], before[w - 1 : w - 1 + n])
    return (least & _U(0xFFFFFF)).astype(np.int64)


def as_bytes(column: pa.Array) -> list[bytes | None]:
    """UTF-8 bytes of a text column."""
    return column.cast(pa.binary()).to_pylist()


def merged(spans: Iterable[tuple[int, int]]) -> list[tuple[int, int]]:
    """Union of half-open intervals as maximal disjoint ones."""
    out: list[list[int]] = []
    for a, b in sorted(spans):
        if out and a <= out[-1][1]:
            out[-1][1] = max(out[-1][1], b)
        else:
            out.append([a, b])
    return [(a, b) for a, b in out]


def flagged_runs(flags: np.ndarray) -> list[tuple[int, int]]:
    """Half-open runs of True."""
    edge = np.diff(np.concatenate(([0], flags.astype(np.int8), [0])))
    return list(zip(np.flatnonzero(edge == 1).tolist(), np.flatnonzero(edge == -1).tolist()))


def row_batches(rows: Iterator[tuple], schema: pa.Schema, size: int = 20_000) -> Iterator[pa.RecordBatch]:
    """Record batches of at most ``size`` rows."""
    held: list[tuple] = []
    for row in rows:
        held.append(row)
        if len(held) >= size:
            yield _batch(held, schema)
            held = []
    if held:
        yield _batch(held, schema)


def _batch(rows: list[tuple], schema: pa.Schema) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(zip(*rows), schema)], schema=schema)
