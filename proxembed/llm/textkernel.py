"""Vectorised word and shingle hashing over the UTF-8 bytes of Arrow string batches.

Words are maximal runs of bytes that a 256-entry table maps to non-zero; the table also folds A-Z to a-z.
A word's hash is a polynomial of its bytes modulo 2**64, taken from one prefix sum per chunk, then mixed.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa

_M1, _M2 = np.uint64(0xBF58476D1CE4E5B9), np.uint64(0x94D049BB133111EB)
_BASE = 0x9E3779B97F4A7C15 | 1
_INVERSE = pow(_BASE, -1, 1 << 64)
_POWERS: dict[str, np.ndarray] = {}
CHUNK_BYTES = 2_000_000
SHINGLE_WORDS = 5
_COEFFICIENTS = [np.uint64(x | 1) for x in (0xD6E8FEB86659FD93, 0xA0761D6478BD642F, 0xE7037ED1A0B428DB, 0x8EBC6AF09C88C6E3, 0x589965CC75374CC3)]


def mix(x: np.ndarray) -> np.ndarray:
    """A bijective 64-bit finaliser."""
    with np.errstate(over="ignore"):
        x = x ^ (x >> np.uint64(30))
        x = x * _M1
        x = x ^ (x >> np.uint64(27))
        x = x * _M2
        return x ^ (x >> np.uint64(31))


def space_table() -> np.ndarray:
    """ASCII white space separates words; A-Z fold to a-z; every other byte stands for itself."""
    table = np.arange(256, dtype=np.uint8)
    table[65:91] += 32
    table[0] = 1
    table[[9, 10, 11, 12, 13, 32]] = 0
    return table


def letter_table() -> np.ndarray:
    """Words of ASCII letters, digits and all bytes of other scripts; A-Z fold to a-z."""
    table = np.zeros(256, dtype=np.uint8)
    table[48:58] = np.arange(48, 58)
    table[97:123] = np.arange(97, 123)
    table[65:91] = np.arange(97, 123)
    table[128:] = np.arange(128, 256)
    return table


def _powers(n: int) -> tuple[np.ndarray, np.ndarray]:
    if len(_POWERS.get("up", ())) < n:
        size = max(n, CHUNK_BYTES + 1)
        for name, base in (("up", _BASE), ("down", _INVERSE)):
            column = np.full(size, base, dtype=np.uint64)
            column[0] = 1
            _POWERS[name] = np.cumprod(column, dtype=np.uint64)
    return _POWERS["up"], _POWERS["down"]


def string_chunks(column: pa.Array | pa.ChunkedArray, limit: int = CHUNK_BYTES) -> Iterator[tuple[int, np.ndarray, np.ndarray]]:
    """(first row, bytes, offsets) for runs of rows of about `limit` bytes; nulls are empty, one long row is a run of its own."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks() if column.num_chunks != 1 else column.chunk(0)
    column = column.cast(pa.large_string()).fill_null("")
    n = len(column)
    if n == 0:
        return
    buffers = column.buffers()
    offsets = np.frombuffer(buffers[1], dtype=np.int64, count=n + 1 + column.offset)[column.offset :]
    data = np.frombuffer(buffers[2], dtype=np.uint8) if buffers[2] is not None and buffers[2].size else np.zeros(0, dtype=np.uint8)
    first = 0
    while first < n:
        last = int(np.searchsorted(offsets, offsets[first] + limit, side="right")) - 1
        last = min(n, max(first + 1, last))
        yield first, data[offsets[first] : offsets[last]], offsets[first : last + 1] - offsets[first]
        first = last


def word_hashes(data: np.ndarray, offsets: np.ndarray, table: np.ndarray, prefix: int = 0) -> tuple[np.ndarray, np.ndarray]:
    """All words' 64-bit hashes in order, and for each row the index of its first word (one entry more at the end).

    With `prefix`, a second row of hashes stands for the words' first bytes; words no longer than that hash to 0 there.
    """
    rows = len(offsets) - 1
    if len(data) == 0:
        return np.zeros((2, 0) if prefix else 0, dtype=np.uint64), np.zeros(rows + 1, dtype=np.int64)
    folded = table[data]
    inside = folded != 0
    start = inside.copy()
    start[1:] &= ~inside[:-1]
    cuts = offsets[1:-1]
    cuts = cuts[cuts < len(data)]
    start[cuts] = inside[cuts]
    starts = np.flatnonzero(start)
    end = inside.copy()
    end[:-1] &= ~inside[1:]
    before = cuts[cuts > 0] - 1
    end[before] = inside[before]
    ends = np.flatnonzero(end) + 1
    up, down = _powers(len(data) + 1)
    with np.errstate(over="ignore"):
        sums = np.zeros(len(data) + 1, dtype=np.uint64)
        np.cumsum(folded * up[: len(data)], dtype=np.uint64, out=sums[1:])
        hashes = mix((sums[ends] - sums[starts]) * down[starts] + (ends - starts).astype(np.uint64))
        if prefix:
            long = ends - starts > prefix
            head = (sums[np.where(long, starts + prefix, starts)] - sums[starts]) * down[starts]
            hashes = np.stack([hashes, np.where(long, mix(head + np.uint64(0x5851F42D4C957F2D)), np.uint64(0))])
    return hashes, np.searchsorted(starts, offsets)


def shingle_sets(words: np.ndarray, first: np.ndarray) -> list[np.ndarray]:
    """Per row the sorted distinct 5-word shingle hashes; with 1 to 4 words the whole sequence is the one shingle."""
    with np.errstate(over="ignore"):
        if len(words) >= SHINGLE_WORDS:
            rolled = words[: len(words) - 4] * _COEFFICIENTS[0]
            for k in range(1, SHINGLE_WORDS):
                rolled = rolled + words[k : len(words) - 4 + k] * _COEFFICIENTS[k]
            rolled = mix(rolled)
        else:
            rolled = np.zeros(0, dtype=np.uint64)
        out = []
        for a, b in zip(first[:-1].tolist(), first[1:].tolist(), strict=True):
            n = b - a
            if n >= SHINGLE_WORDS:
                x = np.sort(rolled[a : b - 4])
                out.append(x[np.concatenate(([True], x[1:] != x[:-1]))] if len(x) > 1 else x)
            elif n:
                short = np.uint64(n)
                for k in range(n):
                    short = short * np.uint64(0x2545F4914F6CDD1D) + words[a + k] * _COEFFICIENTS[k]
                out.append(mix(np.array([short], dtype=np.uint64)))
            else:
                out.append(np.zeros(0, dtype=np.uint64))
    return out
