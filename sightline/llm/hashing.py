"""Vectorised word and shingle hashes over Arrow string columns, exact sets per text."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

_MASK = (1 << 64) - 1
_RADIX = np.uint64(0x9E3779B97F4A7C15)
_CHUNK = 1 << 18


def mix(x: np.ndarray, seed: int = 0) -> np.ndarray:
    """A bijective 64-bit finaliser (xor-shift and multiply), seeded."""
    x = x ^ np.uint64((seed * 0xD1B54A32D192ED03) & _MASK)
    x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


_BYTE = mix(np.arange(1, 257, dtype=np.uint64), 1)
_POW: dict[str, np.ndarray] = {}


def _powers(n: int) -> np.ndarray:
    have = _POW.get("p")
    if have is None or len(have) < n:
        factors = np.full(n, _RADIX, dtype=np.uint64)
        factors[0] = 1
        have = np.multiply.accumulate(factors)
        if n <= _CHUNK:
            _POW["p"] = have
    return have[:n]


def word_hashes(data: np.ndarray, bounds: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of the words of consecutive texts.

    ``data``: their UTF-8 bytes; ``bounds``: len(texts) + 1 byte offsets. Words are runs without ASCII white
    space; A-Z counts as a-z. Returns the hashes and the number of words before each bound.
    """
    upper = (data >= 65) & (data <= 90)
    data = data + (upper.view(np.uint8) << 5)
    space = (data == 32) | ((data >= 9) & (data <= 13))
    first = ~space
    opens = first.copy()
    opens[1:] &= space[:-1]
    inner = bounds[(bounds > 0) & (bounds < len(data))]
    opens[inner] = first[inner]
    starts = np.flatnonzero(opens)
    if not len(starts):
        return np.zeros(0, np.uint64), np.zeros(len(bounds), np.int64)
    run = np.arange(len(data), dtype=np.int64)
    run -= starts[np.maximum(np.cumsum(opens) - 1, 0)]
    run[space] = 0
    np.maximum(run, 0, out=run)
    value = _BYTE[data]
    value[space] = 0
    value *= _powers(int(run.max()) + 1)[run]
    return mix(np.add.reduceat(value, starts)), np.searchsorted(starts, bounds)


def shingle_sets(column: pa.Array, k: int):
    """Yield, text by text, the sorted distinct 64-bit hashes of its ``k``-word shingles.

    A text of one to k-1 words gives the whole sequence as its one shingle; null, empty or blank texts give
    an empty set. Works through the column in slices of about a quarter of a megabyte, so memory follows the largest text.
    """
    weights = mix(np.arange(1, k + 1, dtype=np.uint64), 7)
    for data, bounds in _slices(column):
        hashes, before = word_hashes(data, bounds)
        rolled = None
        if len(hashes) >= k:
            rolled = np.zeros(len(hashes) - k + 1, np.uint64)
            for i in range(k):
                rolled += (hashes[i : i + len(rolled)] ^ weights[i]) * (weights[k - 1 - i] | np.uint64(1))
            rolled = mix(rolled, 3)
        for lo, hi in zip(before[:-1].tolist(), before[1:].tolist()):
            if hi - lo >= k:
                part = np.sort(rolled[lo : hi - k + 1])
                keep = np.ones(len(part), bool)
                np.not_equal(part[1:], part[:-1], out=keep[1:])
                yield part[keep]
            elif hi > lo:
                whole = (hashes[lo:hi] ^ weights[: hi - lo]) * (weights[::-1][: hi - lo] | np.uint64(1))
                yield mix(whole.sum(keepdims=True), 100 + hi - lo)
            else:
                yield np.zeros(0, np.uint64)


def _slices(column: pa.Array):
    column = pc.fill_null(column.cast(pa.large_string()), "")
    offsets = np.frombuffer(column.buffers()[1], np.int64)[column.offset : column.offset + len(column) + 1]
    raw = column.buffers()[2]
    data = np.frombuffer(raw, np.uint8) if raw is not None else np.zeros(0, np.uint8)
    at, n = 0, len(column)
    while at < n:
        to = int(np.searchsorted(offsets, offsets[at] + _CHUNK, "right")) - 1
        to = min(n, max(to, at + 1))
        yield data[offsets[at] : offsets[to]], offsets[at : to + 1] - offsets[at]
        at = to
